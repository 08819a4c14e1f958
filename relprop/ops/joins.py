"""Joins that users of relational prediction need: lookups, ranges, as-of, containment, siblings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Rows up to which a dimension is broadcast.
BROADCAST_ROWS = 1_000_000


def lookup(df: DataFrame, dim: DataFrame, on: Column, how: str = "left", rows: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast join after a look at the dimension's size; a plain join beyond it."""
    small = dim.limit(rows + 1).count() <= rows
    return df.join(F.broadcast(dim) if small else dim, on, how)


#: Names of the physical joins that a hint can ask for.
HINTS = ("broadcast", "merge", "shuffle_hash", "shuffle_replicate_nl")


#: Cells (rows times columns) up to which a hint to broadcast is followed: the table is built in the driver's memory.
BROADCAST_CELLS = 1_000_000
#: Row pairs up to which nested loops go over rows and not over blocks of rows.
LOOP_PAIRS = 100_000_000


def hinted(left: DataFrame, right: DataFrame, on: Column, strategy: str, how: str = "inner", rows: int = BROADCAST_ROWS, keys: tuple[str, str] | None = None) -> DataFrame:
    """A join by a named strategy.  What a strategy would copy to every task (broadcast, replicated nested loops) is looked
    at first; above ``rows`` rows (BROADCAST_CELLS cells of a broadcast) the hint is left out and Spark chooses.

    ``keys``: the columns of an inner join that ``on`` holds to be equal; nested loops over many rows then go by blocks.
    """
    if strategy not in HINTS:
        raise ValueError(f"no join strategy {strategy}")
    copied = strategy in ("broadcast", "shuffle_replicate_nl")
    most = min(rows, BROADCAST_CELLS // len(right.columns)) if strategy == "broadcast" else rows
    if copied and right.limit(most + 1).count() > most:
        return left.join(right, on, how)
    if strategy == "shuffle_replicate_nl" and keys and how == "inner" and (pairs := left.count() * right.count()) > LOOP_PAIRS:
        return block_loops(left, right, *keys, pairs)
    return left.join(right.hint(strategy), on, how)


def block_loops(left: DataFrame, right: DataFrame, left_key: str, right_key: str, pairs: int) -> DataFrame:
    """Equi-join by replicated nested loops over blocks of rows, then over the rows of matching blocks.

    A block holds the rows of one hash value of the key.  With B blocks a side there are B * B pairs of blocks and about
    ``pairs`` / B pairs of rows within matching ones; B is chosen so that the sum is least.  The rows of one key are one block's.
    """
    blocks = max(1, round((pairs / 2) ** (1 / 3)))

    def side(df: DataFrame, key: str, name: str) -> DataFrame:
        block = F.pmod(F.xxhash64(F.col(key).cast("string")), F.lit(blocks)).alias(f"_b{name}")
        return df.filter(F.col(key).isNotNull()).groupBy(block).agg(F.collect_list(F.struct(*df.columns)).alias(f"_r{name}"))

    met = side(left, left_key, "l").join(side(right, right_key, "r").hint("shuffle_replicate_nl"), F.col("_bl") == F.col("_br"))
    rows = met.select(F.explode("_rl").alias("_l"), "_rr").select("_l", F.explode("_rr").alias("_r")).filter(F.col("_l")[left_key] == F.col("_r")[right_key])
    return rows.select(*[F.col("_l")[c].alias(c) for c in left.columns], *[F.col("_r")[c].alias(c) for c in right.columns])


def restrict_to(df: DataFrame, keys: DataFrame, column: str, key: str) -> DataFrame:
    return df.join(keys.select(F.col(key).alias("_k")), F.col(column) == F.col("_k"), "left_semi")


def orphans(df: DataFrame, parents: DataFrame, column: str, key: str) -> DataFrame:
    """Rows that refer to nothing; null references are no orphans."""
    return df.filter(F.col(column).isNotNull()).join(parents.select(F.col(key).alias("_k")), F.col(column) == F.col("_k"), "left_anti")


def range_join(left: DataFrame, right: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows with low <= value < high, by bins of ``width``: an interval is repeated for the bins it touches."""
    l = left.withColumn("_bin", F.floor(F.col(value).cast("double") / width))  # noqa: E741
    r = right.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(low).cast("double") / width), F.floor(F.col(high).cast("double") / width))))
    return l.join(r, "_bin").filter((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def range_counts(left: DataFrame, right: DataFrame, key: str, value: str, low: str, high: str, width: float) -> DataFrame:
    """key, n: how many rows of ``left`` have low <= value < high, for each key of ``right`` with any; no pair is laid out.

    The count of an interval is the number of values below its end less that below its start.  Values and bounds are put
    in order within bins of ``width``; the totals of the bins before are a row a bin.
    """
    at = F.when(F.isnan("v"), F.lit(2**63 - 1)).otherwise(F.floor(F.col("v") / width))
    points = left.filter(F.col(value).isNotNull()).groupBy(F.col(value).cast("double").alias("v")).agg(F.count("*").alias("w")).withColumn("bin", at)
    total = points.groupBy("bin").agg(F.sum("w").alias("w"))
    spans = right.filter(F.col(low) < F.col(high))
    ends = [spans.select(F.col(c).cast("double").alias("v"), F.col(key).alias("k"), F.lit(sign).alias("sign")) for c, sign in ((low, -1), (high, 1))]
    bounds = ends[0].unionByName(ends[1]).withColumn("bin", at)
    # A bin without values still needs the total before it.
    bins = total.unionByName(bounds.select("bin", F.lit(0).cast("long").alias("w")).distinct()).groupBy("bin").agg(F.sum("w").alias("w"))
    before = bins.select(F.col("bin").alias("_bin"), F.coalesce(F.sum("w").over(W.orderBy("bin").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    both = points.select("bin", "v", "w", F.lit(0).alias("sign"), F.lit(None).cast(dict(right.dtypes)[key]).alias("k")).unionByName(bounds.withColumn("w", F.lit(0).cast("long")))
    # Of equal values the bounds come first, as they count what is below them.
    upto = F.sum("w").over(W.partitionBy("bin").orderBy("v", F.col("sign") == 0).rowsBetween(W.unboundedPreceding, 0))
    counted = both.withColumn("upto", upto).filter("sign <> 0").join(before, F.col("bin") == F.col("_bin"))
    n = F.sum(F.col("sign") * (F.col("upto") + F.col("before")))
    return counted.groupBy(F.col("k").alias(key)).agg(n.alias("n")).filter("n > 0")


def interval_join(points: DataFrame, intervals: DataFrame, on: list[str], ts: str, start: str, end: str) -> DataFrame:
    """Points within an interval of the same key: start <= ts < end."""
    r = intervals.select(*[F.col(c).alias(f"_{c}") for c in on], *[c for c in intervals.columns if c not in on])
    cond = [F.col(c) == F.col(f"_{c}") for c in on]
    return points.join(r, cond).filter((F.col(ts) >= F.col(start)) & (F.col(ts) < F.col(end))).drop(*[f"_{c}" for c in on])


def asof_join(left: DataFrame, right: DataFrame, on: str, left_ts: str, right_ts: str, value: str, out: str = "asof_value", tie: str | None = None) -> DataFrame:
    """The value of the last right row of the same key at or before each left row; one shuffle of both sides together.

    A hot key is cut by nothing but its own sort, which spills; only the key, the time and the value travel from the right.
    """
    both = left.withColumns({"_ts": F.col(left_ts), "_side": F.lit(1), "_val": F.lit(None).cast(dict(right.dtypes)[value]), "_tie": F.lit(0).cast("long")})
    r = right.select(F.col(on), F.col(right_ts).alias("_ts"), F.lit(0).alias("_side"), F.struct(F.col(value)).alias("_s"), (F.col(tie).cast("long") if tie else F.lit(0).cast("long")).alias("_tie"))
    l = both.drop("_val").withColumn("_s", F.lit(None).cast(dict(r.dtypes)["_s"]))  # noqa: E741
    u = l.unionByName(r, allowMissingColumns=True)
    w = W.partitionBy(on).orderBy("_ts", "_side", "_tie").rowsBetween(W.unboundedPreceding, 0)
    return u.withColumn(out, F.last("_s", ignorenulls=True).over(w)[value]).filter("_side = 1").select(*left.columns, out)


def contains_join(texts: DataFrame, text: str, needles: DataFrame, needle: str, rows: int = 10_000) -> DataFrame:
    """Pairs in which a text contains a needle; the needles are few (checked), and long texts are told by length first."""
    if needles.limit(rows + 1).count() > rows:
        raise ValueError("too many needles for a nested loop")
    return texts.join(F.broadcast(needles), (F.length(text) >= F.length(needle)) & F.expr(f"contains({text}, {needle})"))


def siblings(df: DataFrame, key: str, fk: str, value: str) -> DataFrame:
    """key, n_siblings, mean_siblings: over the other rows with the same reference, without pairing them."""
    s = df.filter(F.col(fk).isNotNull()).groupBy(F.col(fk).alias("_f")).agg(F.count(value).alias("n"), F.sum(value).alias("t"))
    joined = df.join(s, F.col(fk) == F.col("_f"), "left")
    n = F.coalesce(F.col("n") - F.col(value).isNotNull().cast("int"), F.lit(0))
    return joined.select(key, n.cast("long").alias("n_siblings"), F.when(n > 0, (F.col("t") - F.coalesce(value, F.lit(0.0))) / n).alias("mean_siblings"))


def compare_frames(a: DataFrame, b: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """only_left, only_right, differing: row counts of a full outer comparison."""
    x = a.select(F.col(key).alias("_a"), *[F.col(c).alias(f"a_{c}") for c in columns])
    y = b.select(F.col(key).alias("_b"), *[F.col(c).alias(f"b_{c}") for c in columns])
    j = x.join(y, F.col("_a") == F.col("_b"), "full")
    same = F.lit(True)
    for c in columns:
        same = same & F.col(f"a_{c}").eqNullSafe(F.col(f"b_{c}"))
    n = lambda cond: F.coalesce(F.sum(F.when(cond, 1)), F.lit(0)).cast("long")
    both = F.col("_a").isNotNull() & F.col("_b").isNotNull()
    return j.agg(n(F.col("_b").isNull()).alias("only_left"), n(F.col("_a").isNull()).alias("only_right"), n(both & ~same).alias("differing"))


def param_cross(**values) -> list[dict]:
    """All combinations of driver-side parameters."""
    from itertools import product

    return [dict(zip(values, v, strict=True)) for v in product(*values.values())]
