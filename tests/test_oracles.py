"""Every query with SQL gives DuckDB's rows on the smallest tables."""

import duckdb
import pytest

from relprop.queries import ORACLE, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def rows(df):
    cols = sorted(df.columns)
    cell = lambda v: "" if v is None or v != v else f"{v:.6g}" if isinstance(v, float) else str(v).removesuffix(" 00:00:00")
    return cols, sorted(tuple(cell(v) for v in r) for r in df[cols].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", sorted(set(QUERIES) & set(ORACLE)))
def test_query_equals_sql(spark, sf, con, name):
    assert rows(QUERIES[name](spark, sf).toPandas()) == rows(con.sql(ORACLE[name]).df())
