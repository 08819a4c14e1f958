"""Connected components of a graph of longs, by alternating large-star and small-star steps on DataFrames; of a small graph, by one task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import cut


def local_components(n: int, a: np.ndarray, b: np.ndarray, label: np.ndarray | None = None) -> np.ndarray:
    """Smallest index of each node's component."""
    label = np.arange(n) if label is None else label
    while len(a):
        la, lb = label[a], label[b]
        open_ = la != lb
        if not open_.any():
            break
        a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
        np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
        while not np.array_equal(up := label[label], label):
            label = up
    return label


def _in_one_task(edges: DataFrame) -> DataFrame:
    """a, b: each node with the least of its component, where that is another one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        ends = [np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in got]) for i in range(2)]
        nodes, at = np.unique(np.concatenate(ends), return_inverse=True)
        label = local_components(len(nodes), at[: len(ends[0])], at[len(ends[0]) :])
        far = np.flatnonzero(label != np.arange(len(nodes)))
        yield pa.RecordBatch.from_arrays([pa.array(nodes[far]), pa.array(nodes[label[far]])], names=["a", "b"])

    return edges.coalesce(1).mapInArrow(run, "a long, b long")


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One star step on edges (a > b).  Minima are grouped with partial sums, so that a hub is one row per task."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    if large:
        both = both.unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("x"), F.least("u", "m").alias("m"))
    joined = both.join(low, F.col("u") == F.col("x"))
    if large:
        out = joined.filter(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = joined.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(low.select(F.col("x").alias("a"), F.col("m").alias("b")))
    return out.filter("a > b").distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, few: int = 0) -> DataFrame:
    """node, root: the smallest node of its component, for every node that has an edge and is not a root.

    ``edges`` has longs a and b in any order, repeats and loops allowed.  Each round is written to the checkpoint
    folder; the number of rounds follows the logarithm of the longest path.  A graph of at most ``few`` edges, repeats
    included, takes no rounds: it goes to one task as it is.
    """
    now = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a > b")
    if few:
        now = cut(now)
        if now.count() <= few:
            return cut(_in_one_task(now)).select(F.col("a").alias("node"), F.col("b").alias("root"))
    now = cut(now.distinct())
    seen = _mark(now)
    while True:
        now = cut(_star(_star(now, True), False))
        if (mark := _mark(now)) == seen:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        seen = mark
