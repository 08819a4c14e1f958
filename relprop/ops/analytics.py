"""Aggregates, windows, sets and functions around the methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def agg_where(df: DataFrame, key: str, conditions: dict[str, Column], value: str | None = None) -> DataFrame:
    """A count (or a sum of ``value``) for each condition."""
    f = lambda c: F.coalesce(F.sum(F.when(c, F.col(value) if value else 1)), F.lit(0))
    return df.groupBy(key).agg(*[f(c).alias(n) for n, c in conditions.items()])


def pivot_counts(df: DataFrame, key: str, column: str, values: list[str]) -> DataFrame:
    return df.groupBy(key).pivot(column, values).agg(F.count(F.lit(1))).fillna(0)


def cube_report(df: DataFrame, keys: list[str], measures: list[Column]) -> DataFrame:
    return df.cube(*keys).agg(F.grouping_id().alias("gid"), *measures)


def grouping_sets(df: DataFrame, sets: list[list[str]], keys: list[str], measures: list[Column]) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *keys).agg(*measures)


def nunique(df: DataFrame, key: str, column: str, approximate: bool = False, error: float = 0.02) -> DataFrame:
    f = F.approx_count_distinct(column, error) if approximate else F.count_distinct(column)
    return df.groupBy(key).agg(f.alias("n_distinct"))


def quantiles(df: DataFrame, column: str, at: list[float], approximate: bool = False) -> DataFrame:
    f = F.percentile_approx(column, at, 10_000) if approximate else F.percentile(column, F.array(*[F.lit(q) for q in at]))
    return df.agg(f.alias("q")).select(*[F.get("q", F.lit(i)).alias(f"q_{int(q * 1000)}") for i, q in enumerate(at)])


def sketch_quantiles(df: DataFrame, column: str, at: list[float]) -> DataFrame:
    """From a mergeable quantile sketch, for inputs that an exact one would not fit."""
    s = df.agg(F.kll_sketch_agg_double(F.col(column).cast("double")).alias("s"))
    return s.select(*[F.kll_sketch_get_quantile_double("s", F.lit(q)).alias(f"q_{int(q * 1000)}") for q in at])


def latest_value(df: DataFrame, key: str, ts: str, value: str, tie: str) -> DataFrame:
    return df.groupBy(key).agg(F.max_by(value, F.struct(ts, tie)).alias("latest"))


def rank_in_group(df: DataFrame, group: str, order: list[Column], key: list[str], ties: list[Column] | None = None) -> DataFrame:
    """rn (ties settled by ``ties``), rk and dr (ties share a rank)."""
    w = W.partitionBy(group)
    v = w.orderBy(*order)
    row, rank, dense = F.row_number().over(w.orderBy(*order, *(ties or []))), F.rank().over(v), F.dense_rank().over(v)
    return df.select(*key, row.cast("long").alias("rn"), rank.cast("long").alias("rk"), dense.cast("long").alias("dr"))


def lag_lead(df: DataFrame, group: str, ts: str, tie: str) -> DataFrame:
    """Seconds to the event before of the same group (null at the first)."""
    w = W.partitionBy(group).orderBy(ts, tie)
    before = F.lag(ts).over(w)
    return df.select(tie, group, F.timestamp_diff("SECOND", before, F.col(ts)).alias("gap_s"))


def trailing_agg(df: DataFrame, group: str, ts: str, tie: str, seconds: int, value: str) -> DataFrame:
    """Count and sum over the rows of the last ``seconds``, the row itself included."""
    t = F.unix_micros(F.col(ts).cast("timestamp"))
    w = W.partitionBy(group).orderBy(F.col("_t")).rangeBetween(-seconds * 1_000_000, 0)
    return df.withColumn("_t", t).select(tie, group, F.count("*").over(w).alias("n_trailing"), F.sum(value).over(w).alias("sum_trailing"))


def topk(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    return df.orderBy(*order).limit(k)


def topk_per(df: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rn", F.row_number().over(W.partitionBy(group).orderBy(*order))).filter(F.col("rn") <= k)


def set_ops(a: DataFrame, b: DataFrame) -> dict[str, DataFrame]:
    return {"union_all": a.unionByName(b), "union": a.unionByName(b).distinct(), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}


def sample_rows(df: DataFrame, key: str, rate: float) -> DataFrame:
    """The same rows each time: by md5 of the key."""
    from ..schema import bucket_of

    return df.filter(bucket_of([key], 0, 10_000) < round(rate * 10_000))


def stratified_sample(df: DataFrame, key: str, stratum: str, rates: dict[str, float], other: float = 0.0) -> DataFrame:
    """The same rows each time, each stratum at its rate, strata without one at ``other``."""
    from ..schema import bucket_of

    limit = F.lit(round(other * 10_000))
    for value, rate in rates.items():
        limit = F.when(F.col(stratum) == value, F.lit(round(rate * 10_000))).otherwise(limit)
    return df.filter(bucket_of([key], 0, 10_000) < limit)


def cogroup_ratio(left: DataFrame, right: DataFrame) -> DataFrame:
    """key, n_left, n_right, ratio of the sums of x: two frames by key in one Python call a key.

    Both sides are added up first, so that a call sees one row of either, however many a key has.
    """
    import pandas as pd

    total = lambda df: df.groupBy("key").agg(F.count("*").alias("n"), F.sum("x").alias("t"))

    def one(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        ratio = round(a.t.iloc[0] / b.t.iloc[0], 6) if len(a) and len(b) else None
        return pd.DataFrame({"key": [key[0]], "n_left": [int(a.n.sum())], "n_right": [int(b.n.sum())], "ratio": [ratio]})

    return total(left).groupBy("key").cogroup(total(right).groupBy("key")).applyInPandas(one, "key long, n_left long, n_right long, ratio double")


def vec_dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def vec_relu(a: str) -> Column:
    return F.transform(a, lambda x: F.greatest(F.lit(0.0), x.cast("double")))


def vec_concat(*cols: str) -> Column:
    return F.concat(*cols)


def props_fields(df: DataFrame, column: str, schema: str) -> DataFrame:
    from ..features import json_fields

    return json_fields(df, column, schema)


def date_diffs(a: str, b: str) -> dict[str, Column]:
    return {"days": F.datediff(b, a).cast("long"), "months": F.months_between(b, a), "hours": F.timestamp_diff("HOUR", F.col(a), F.col(b))}


def group_mode_udf():
    """A grouped pandas aggregate: the most frequent value, of several the smallest.  ``mode`` does it in the JVM; this
    shows how a custom aggregate is plugged in."""
    import pandas as pd

    def most(v: pd.Series) -> str:
        c = v.dropna().value_counts()
        return min(c[c == c.max()].index) if len(c) else None

    most.__annotations__ = {"v": pd.Series, "return": str}
    return F.pandas_udf(most, "string")


def sigmoid_udf():
    import numpy as np
    import pandas as pd

    def s(v: pd.Series) -> pd.Series:
        return 1 / (1 + np.exp(-v))

    s.__annotations__ = {"v": pd.Series, "return": pd.Series}
    return F.pandas_udf(s, "double")
