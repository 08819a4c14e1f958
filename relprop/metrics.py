"""Accuracy and cost measures."""

from __future__ import annotations

import resource
import time
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import graph_stats, tables_reached
from .schema import Catalog


def auc(df: DataFrame, score: str, label: str) -> DataFrame:
    """pos, neg, auc: exact, ties count half.

    Scores are counted, range-partitioned and summed up within partitions; only one total a partition meets on one
    task.  Null when a class is missing.
    """
    from pyspark.sql import Window as W

    counts = df.filter(F.col(score).isNotNull() & F.col(label).isNotNull()).groupBy(F.col(score).cast("double").alias("s")).agg(F.sum(F.col(label).cast("long")).alias("p"), F.sum(1 - F.col(label).cast("long")).alias("n"))
    placed = counts.repartitionByRange("s").withColumn("part", F.spark_partition_id())
    inside = placed.withColumn("below", F.coalesce(F.sum("n").over(W.partitionBy("part").orderBy("s").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    parts = inside.groupBy("part").agg(F.min("s").alias("first"), F.sum("p").alias("p"), F.sum("n").alias("n"), F.sum(F.col("p").cast("double") * (F.col("below") + F.col("n") / 2)).alias("inner"))
    run = parts.withColumn("before", F.coalesce(F.sum("n").over(W.orderBy("first").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    total = run.agg(F.sum("p").alias("pos"), F.sum("n").alias("neg"), F.sum(F.col("inner") + F.col("p").cast("double") * F.col("before")).alias("u"))
    return total.select(F.coalesce("pos", F.lit(0)).alias("pos"), F.coalesce("neg", F.lit(0)).alias("neg"), F.when((F.col("pos") > 0) & (F.col("neg") > 0), F.col("u") / (F.col("pos").cast("double") * F.col("neg"))).alias("auc"))


def auc_binned(df: DataFrame, score: str, label: str, bins: int = 1000) -> DataFrame:
    """auc and bound: from scores in [0, 1] cut into bins; the error is at most half the share of pairs within a bin."""
    from pyspark.sql import Window as W

    b = F.least(F.floor(F.col(score) * bins), F.lit(bins - 1))
    counts = df.groupBy(b.alias("b")).agg(F.sum(F.col(label).cast("long")).alias("p"), F.sum(1 - F.col(label).cast("long")).alias("n"))
    run = counts.withColumn("below", F.coalesce(F.sum("n").over(W.orderBy("b").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))  # at most `bins` rows
    pairs = F.sum("p").cast("double") * F.sum("n")
    return run.agg((F.sum(F.col("p").cast("double") * (F.col("below") + F.col("n") / 2)) / pairs).alias("auc"), (F.sum(F.col("p").cast("double") * F.col("n")) / 2 / pairs).alias("bound"))


def auc_ml(df: DataFrame, score: str, label: str) -> float:
    """The library's trapezoid area, as a cross-check."""
    from pyspark.ml.evaluation import BinaryClassificationEvaluator

    rows = df.select(F.col(score).cast("double").alias("rawPrediction"), F.col(label).cast("double").alias("label"))
    return BinaryClassificationEvaluator(numBins=0).evaluate(rows)


def auc_local(scores, labels) -> float:
    """The same measure of arrays."""
    import numpy as np

    s, y = np.asarray(scores, float), np.asarray(labels, float)
    _, inv = np.unique(s, return_inverse=True)
    p, n = np.bincount(inv, y), np.bincount(inv, 1 - y)
    if not p.sum() or not n.sum():
        return float("nan")
    return float((p * (np.cumsum(n) - n / 2)).sum() / (p.sum() * n.sum()))


def summarise(runs: DataFrame) -> DataFrame:
    """task, method, runs, mean_auc, std_auc of rerun rows (task, method, auc)."""
    return runs.groupBy("task", "method").agg(F.count("*").alias("runs"), F.avg("auc").alias("mean_auc"), F.stddev_samp("auc").alias("std_auc"))


def label_balance(df: DataFrame, label: str = "label") -> DataFrame:
    return df.agg(F.count("*").alias("rows"), F.avg(F.col(label).cast("double")).alias("share_of_ones"))


def block_cost(kind: str, fields: int, d: int, width: int = 0) -> int:
    """Multiplications of one row of a single-table model."""
    width = width or 2 * d
    return {"linear": fields * d, "fm": fields * d, "mlp": fields * d * width, "deepfm": fields * d + fields * d * width, "transformer": fields * d * d + fields * fields * d}[kind]


def subgraph_bound(max_degree: int, depth: int, total: int) -> int:
    """Rows that a K-hop subgraph can have: the sum over hops of degree^hop, at most the database."""
    return min(sum(max_degree**j for j in range(depth + 1)), total)


def cost_model(catalog: Catalog, target: str, depth: int, d: int, kind: str = "deepfm") -> DataFrame:
    """rows, max_degree, bound, printed_bound, per_row and total cost of one prediction."""
    stats = graph_stats(catalog)
    row = stats.agg(F.sum(F.when(F.col("kind") == "table", F.col("n"))).alias("rows"), F.max("max_degree").alias("D"))
    spec = max(len(s.features) for s in catalog.specs.values()) + max(len(catalog.forward(t)) + len(catalog.backward(t)) for t in catalog.specs)
    p = block_cost(kind, spec, d)
    dd = F.col("D").cast("double")
    bound = sum((F.pow(dd, F.lit(j)) for j in range(1, depth + 1)), F.lit(1.0))
    per = F.lit(p + d * d) + dd * d
    n = F.least(bound, F.col("rows").cast("double"))
    return row.select(F.col("rows"), F.col("D").alias("max_degree"), n.alias("bound"), F.least(F.pow(dd, F.lit(depth)), F.col("rows").cast("double")).alias("printed_bound"), per.alias("per_row"), (F.lit(float(depth)) * n * per).alias("total"))


@dataclass
class RunReport:
    """What one training run cost and gave."""

    task: str
    method: str
    depth: int
    seed: int
    auc: float = float("nan")
    seconds: float = 0.0
    s_per_epoch: float = 0.0
    peak_rss: int = 0
    shuffle_bytes: int = 0
    tables_reached: int = 0
    n_features: int = 0

    SCHEMA = "task string, method string, depth long, seed long, auc double, seconds double, s_per_epoch double, peak_rss long, shuffle_bytes long, tables_reached long, n_features long"

    def row(self) -> tuple:
        return tuple(getattr(self, f.split()[0]) for f in self.SCHEMA.split(", "))


def shuffle_written(spark) -> int:
    """Shuffle bytes that the application has written so far, from the status store."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(executors.apply(i).totalShuffleWrite() for i in range(executors.length()))


def peak_memory() -> int:
    """Peak resident bytes of this Python process."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024


@contextmanager
def measured(report: RunReport, catalog: Catalog | None = None, target: str | None = None):
    """Wall time and peak resident memory of the driver's Python; tables reached where a catalog is given."""
    began = time.time()
    yield report
    report.seconds = time.time() - began
    report.peak_rss = peak_memory()
    if catalog is not None:
        report.tables_reached = tables_reached(catalog, target, report.depth)[report.depth]


def smoothing_curve(rounds: list[DataFrame], columns: list[str]) -> list[float]:
    """Spread of node vectors by layer: total variance over total second moment; 0 where all are one vector."""
    out = []
    for df in rounds:
        var = sum((F.var_pop(F.col(c)) for c in columns), F.lit(0.0))
        sq = sum((F.avg(F.col(c) * F.col(c)) for c in columns), F.lit(0.0))
        out.append(df.agg((var / F.greatest(sq, F.lit(1e-300))).alias("x")).first()["x"])
    return out
