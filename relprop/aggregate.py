"""Neighbour summaries: mean, max, min with partial aggregation, and their scaling by degree."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

STATS = (("mean", F.avg), ("max", F.max), ("min", F.min))


def neighbour_stats(children: DataFrame, fk: str, columns: list[str], out: str = "key") -> DataFrame:
    """``out``, deg, and mean_c, max_c, min_c of each column, for rows that something refers to.

    Means, maxima and minima are algebraic: a hub is one partial row a task, whatever its degree.
    """
    aggs = [f(F.col(c).cast("double")).alias(f"{n}_{c}") for n, f in STATS for c in columns]
    return children.filter(F.col(fk).isNotNull()).groupBy(F.col(fk).alias(out)).agg(F.count("*").alias("deg"), *aggs)


def with_empty(parents: DataFrame, key: str, stats: DataFrame, out: str = "key") -> DataFrame:
    """The same for all parents: without children the degree and the summaries are zero."""
    cols = [c for c in stats.columns if c != out]
    joined = parents.select(F.col(key).alias("_p")).join(stats, F.col("_p") == F.col(out), "left")
    return joined.select(F.col("_p").alias(out), *[F.coalesce(F.col(c), F.lit(0)).cast("long" if c == "deg" else "double").alias(c) for c in cols])


def delta_of(degrees: DataFrame, column: str = "deg") -> float:
    """Mean of log(1 + degree) over the nodes of an edge type."""
    return degrees.agg(F.avg(F.log1p(F.col(column)))).first()[0] or 1.0


def scalers(deg: Column, delta: float, kind: str = "log1p", eps: float = 1e-2) -> tuple[Column, Column, Column]:
    """Identity, amplification, attenuation.  ``raw`` takes the plain logarithm, kept above ``eps``."""
    s = F.log1p(deg) if kind == "log1p" else F.greatest(F.log(F.greatest(deg, F.lit(1))), F.lit(eps))
    return F.lit(1.0), s / F.lit(delta), F.when(deg > 0, F.lit(delta) / s).otherwise(0.0)


def degree_scaled(stats: DataFrame, columns: list[str], delta: float, kind: str = "log1p", key: str = "key") -> DataFrame:
    """The nine vectors: s0 to s2 times mean, max and min."""
    s = scalers(F.col("deg"), delta, kind)
    return stats.select(key, "deg", *[(s[i] * F.col(f"{n}_{c}")).alias(f"s{i}_{n}_{c}") for i in range(3) for n, _ in STATS for c in columns])


def salted_agg(df: DataFrame, key: str, column: str, salts: int = 16) -> DataFrame:
    """key, n, total, low, high: aggregation in two steps, so that no task gets all rows of one key unsummed."""
    salt = F.pmod(F.xxhash64(*df.columns), F.lit(salts))
    part = df.groupBy(key, salt.alias("_s")).agg(F.count(column).alias("n"), F.sum(column).alias("total"), F.min(column).alias("low"), F.max(column).alias("high"))
    return part.groupBy(key).agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.min("low").alias("low"), F.max("high").alias("high"))
