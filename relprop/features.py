"""Feature encoding: categories, min-max, dates, field vectors, vector columns, text and JSON figures."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schema import Catalog


@dataclass
class CategoryCodec:
    """Value -> dense id from 1 on, in order of value; 0 stands for null and for values that were not seen.

    Columns of one domain share a dictionary.  A dictionary of more than ``max_size`` values is replaced by hash
    buckets, so what is broadcast has a bound.
    """

    dictionaries: dict[str, DataFrame]
    sizes: dict[str, int]  # max_size + 1 stands for any number above max_size
    columns: dict[str, str]
    max_size: int

    @classmethod
    def fit(cls, sources: list[tuple[DataFrame, str, str]], max_size: int = 65_536) -> CategoryCodec:
        """``sources``: (frame, column, domain)."""
        by_domain: dict[str, DataFrame] = {}
        for df, column, domain in sources:
            vals = df.select(F.col(column).cast("string").alias("value")).filter("value is not null").distinct()
            by_domain[domain] = vals if domain not in by_domain else by_domain[domain].unionByName(vals).distinct()
        dicts, sizes = {}, {}
        for d, v in by_domain.items():
            # At most max_size values and one reach the driver; a dictionary is found once, not by each use.
            found = sorted((r[0] for r in v.limit(max_size + 1).collect()), key=lambda s: s.encode())
            sizes[d] = len(found)
            if len(found) <= max_size:
                dicts[d] = v.sparkSession.createDataFrame(pa.table({"value": pa.array(found, pa.string()), "id": pa.array(range(1, len(found) + 1), pa.int32())}))
        return cls(dicts, sizes, {c: d for _, c, d in sources}, max_size)

    def transform(self, df: DataFrame, column: str, out: str | None = None) -> DataFrame:
        out, domain = out or f"{column}_id", self.columns[column]
        if domain in self.dictionaries:
            d = F.broadcast(self.dictionaries[domain].select(F.col("value").alias("_v"), F.col("id").alias("_i")))
            return df.join(d, F.col(column).cast("string") == F.col("_v"), "left").withColumn(out, F.coalesce("_i", F.lit(0))).drop("_v", "_i")
        bucket = F.pmod(F.xxhash64(F.col(column).cast("string")), F.lit(self.max_size - 1)).cast("int") + 1
        return df.withColumn(out, F.when(F.col(column).isNull(), 0).otherwise(bucket))

    def cardinality(self, column: str) -> int:
        return min(self.sizes[self.columns[column]], self.max_size) + 1


@dataclass
class MinMaxCodec:
    """Numbers to [0, 1] by the range seen when fitting; others are clamped, constants give 0, nulls stay null."""

    bounds: dict[str, tuple[float, float]]

    @classmethod
    def fit(cls, df: DataFrame, columns: list[str]) -> MinMaxCodec:
        if not columns:
            return cls({})
        row = df.agg(*[f(F.col(c).cast("double")).alias(f"{n}_{c}") for c in columns for n, f in (("lo", F.min), ("hi", F.max))]).first()
        return cls({c: (row[f"lo_{c}"], row[f"hi_{c}"]) for c in columns})

    def unit(self, column: str) -> Column:
        lo, hi = self.bounds[column]
        x = F.col(column).cast("double")
        if lo is None or hi == lo:
            return F.when(x.isNotNull(), F.lit(0.0))
        return F.when(x.isNotNull(), F.greatest(F.lit(0.0), F.least(F.lit(1.0), (x - F.lit(lo)) / F.lit(hi - lo))))  # greatest passes over nulls

    def transform(self, df: DataFrame, suffix: str = "_unit") -> DataFrame:
        return df.withColumns({f"{c}{suffix}": self.unit(c) for c in self.bounds})


def expand_dates(df: DataFrame, columns: list[str]) -> DataFrame:
    """Add c_year, c_month, c_day, c_weekday (Monday is 0) as longs."""
    parts = (("year", F.year), ("month", F.month), ("day", F.dayofmonth), ("weekday", F.weekday))
    return df.withColumns({f"{c}_{n}": f(F.col(c)).cast("long") for c in columns for n, f in parts})


def field_affine(x: Column, w: list[float], b: list[float]) -> list[Column]:
    """The d components of relu(x * w + b)."""
    return [F.greatest(F.lit(0.0), x * F.lit(float(wj)) + F.lit(float(bj))) for wj, bj in zip(w, b, strict=True)]


def field_lookup(ident: Column, table: list[list[float]]) -> list[Column]:
    """The d components of a row of a small table, by id."""
    return [F.coalesce(F.get(F.array(*[F.lit(float(r[j])) for r in table]), ident), F.lit(0.0)) for j in range(len(table[0]))]


def feature_columns(catalog: Catalog, table: str) -> list[str]:
    """Features alone: keys, foreign keys and the label are no features."""
    used = {*catalog.key(table), *(k.column for k in catalog.forward(table))}
    return [c for c in catalog.specs[table].features if c not in used]


def impute(df: DataFrame, values: dict[str, float]) -> DataFrame:
    """Fill nulls and add c_missing (0 or 1) for each column."""
    return df.withColumns({f"{c}_missing": F.col(c).isNull().cast("int") for c in values}).fillna(values)


def vector_fields(df: DataFrame, column: str, size: int, prefix: str = "v") -> DataFrame:
    """One numeric column a component."""
    return df.select("*", *[F.get(column, F.lit(j)).cast("double").alias(f"{prefix}_{j}") for j in range(size)])


def text_stats(column: str) -> dict[str, Column]:
    """Figures of a text: length, words, lines, shares of digits, capitals and marks."""
    t = F.coalesce(F.col(column), F.lit(""))
    n = F.greatest(F.length(t), F.lit(1))
    share = lambda p: F.regexp_count(t, F.lit(p)) / n
    return {"n_chars_t": F.length(t).cast("long"), "n_words": F.regexp_count(t, F.lit(r"[^ \n\t]+")).cast("long"), "n_lines": (F.regexp_count(t, F.lit("\n")) + 1).cast("long"), "digit_share": share("[0-9]"), "upper_share": share("[A-Z]"), "mark_share": share("[^A-Za-z0-9 \n]")}


def json_fields(df: DataFrame, column: str, schema: str) -> DataFrame:
    """Typed fields of a JSON column; malformed texts give nulls."""
    parsed = df.withColumn("_j", F.from_json(column, schema))
    return parsed.select("*", "_j.*").drop("_j")
