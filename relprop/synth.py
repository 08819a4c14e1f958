"""The two synthetic databases, deterministic by md5 of ids so that SQL engines can repeat them, and their shapes over the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .schema import Catalog, ForeignKey, TableSpec, Task, read_tables

TAU = 25.0


def uniform(*parts) -> Column:
    """[0, 1) from the first 32 bits of md5."""
    text = F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def pick(n: int, *parts) -> Column:
    return F.floor(uniform(*parts) * n).cast("long")


def children(spark: SparkSession, n_c: int, mean: int = 50, spread: int = 10) -> DataFrame:
    """bID, cID: between mean - spread and mean + spread rows a key."""
    c = spark.range(n_c).select(F.col("id").alias("cID"), (F.lit(mean - spread) + pick(2 * spread + 1, "n", F.col("id").cast("string"))).alias("n"))
    rows = c.select("cID", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("i"))
    return rows.select((F.col("cID") * 1000 + F.col("i")).alias("bID"), "cID")


def labelled(a: DataFrame, sums: DataFrame) -> DataFrame:
    return a.join(sums, a["cID"] == sums["_c"], "left").withColumn("label", (F.coalesce("total", F.lit(0.0)) >= TAU).cast("int")).drop("_c", "total")


def schema1(spark: SparkSession, n_a: int = 1000, n_c: int = 100, seed: int = 0) -> Task:
    """A -> B, A -> C, B -> C; the label is 1 iff y over the B rows that share A's C sums up to TAU or more."""
    s = f"s1-{seed}"
    b = children(spark, n_c).withColumn("y", uniform(s, "y", F.col("bID").cast("string")))
    key = F.col("aid").cast("string")
    a = spark.range(n_a).select(F.col("id").alias("aid")).withColumns({"cID": pick(n_c, s, "c", key), "x": F.lit(1.0)})
    # Any B row will do as A's own: the first of another C.
    a = a.withColumn("bID", pick(n_c, s, "b", key) * 1000 + pick(40, s, "i", key))
    c = spark.range(n_c).select(F.col("id").alias("cID"), F.lit(1.0).alias("z"))
    a = labelled(a, b.groupBy(F.col("cID").alias("_c")).agg(F.sum("y").alias("total")))
    specs = [TableSpec("A", ("aid",), ("x",)), TableSpec("B", ("bID",), ("y",)), TableSpec("C", ("cID",), ("z",))]
    fks = [ForeignKey("A", "bID", "B"), ForeignKey("A", "cID", "C"), ForeignKey("B", "cID", "C")]
    return Task(Catalog.build(specs, fks, {"A": a, "B": b, "C": c}), "A", name="syn1")


def schema2(spark: SparkSession, n_a: int = 1000, n_c: int = 100, n_d: int = 500, seed: int = 0) -> Task:
    """A -> C, A -> D, B -> C, B -> D; the label is 1 iff z over the D rows of the B rows that share A's C is TAU or more."""
    s = f"s2-{seed}"
    b = children(spark, n_c).withColumn("dID", pick(n_d, s, "d", F.col("bID").cast("string"))).withColumnRenamed("bID", "bid")
    d = spark.range(n_d).select(F.col("id").alias("dID")).withColumn("z", uniform(s, "z", F.col("dID").cast("string")))
    key = F.col("aid").cast("string")
    a = spark.range(n_a).select(F.col("id").alias("aid")).withColumns({"cID": pick(n_c, s, "c", key), "dID": pick(n_d, s, "ad", key), "x": F.lit(1.0)})
    c = spark.range(n_c).select(F.col("id").alias("cID"), F.lit(1.0).alias("y"))
    sums = b.join(d.withColumnRenamed("dID", "_d"), F.col("dID") == F.col("_d")).groupBy(F.col("cID").alias("_c")).agg(F.sum("z").alias("total"))
    specs = [TableSpec("A", ("aid",), ("x",)), TableSpec("B", ("bid",)), TableSpec("C", ("cID",), ("y",)), TableSpec("D", ("dID",), ("z",))]
    fks = [ForeignKey("A", "cID", "C"), ForeignKey("A", "dID", "D"), ForeignKey("B", "cID", "C"), ForeignKey("B", "dID", "D")]
    return Task(Catalog.build(specs, fks, {"A": labelled(a, sums), "B": b, "C": c, "D": d}), "A", name="syn2")


#: What the values of the given tables are divided by, so that TAU is about the middle of their sums.
UNIT1, UNIT2 = 100_000.0, 200.0


def _ids(df: DataFrame, key: str) -> int:
    """Keys run from 0 on; a key that is missing is a reference to nothing."""
    return (df.agg(F.max(key)).first()[0] or 0) + 1


def given1(spark: SparkSession, folder: str) -> Task:
    """The first shape over given tables: A suppliers, B orders, C customers.

    References of A are picked by md5; those of B, and all values, are the tables'.  The label is 1 iff the prices of the
    orders of A's customer sum up to TAU units or more.
    """
    t = read_tables(spark, folder, ["supplier", "orders", "customer"])
    b = t["orders"].select(F.col("o_orderkey").alias("bID"), F.col("o_custkey").alias("cID"), (F.col("o_totalprice") / UNIT1).alias("y"))
    c = t["customer"].select(F.col("c_custkey").alias("cID"), F.col("c_acctbal").alias("z"))
    key = F.col("aid").cast("string")
    a = t["supplier"].select(F.col("s_suppkey").alias("aid")).withColumns({"cID": pick(_ids(c, "cID"), "g1", "c", key), "bID": pick(_ids(b, "bID"), "g1", "b", key), "x": F.lit(1.0)})
    a = labelled(a, b.groupBy(F.col("cID").alias("_c")).agg(F.sum("y").alias("total")))
    specs = [TableSpec("A", ("aid",), ("x",)), TableSpec("B", ("bID",), ("y",)), TableSpec("C", ("cID",), ("z",))]
    fks = [ForeignKey("A", "bID", "B"), ForeignKey("A", "cID", "C"), ForeignKey("B", "cID", "C")]
    return Task(Catalog.build(specs, fks, {"A": a, "B": b, "C": c}), "A", name="syn1")


def given2(spark: SparkSession, folder: str) -> Task:
    """The second shape over given tables: A suppliers, B lines, C orders, D parts.

    References of A are picked by md5; those of B, and all values, are the tables'.  The label is 1 iff the retail prices
    of the parts of A's order sum up to TAU units or more.
    """
    t = read_tables(spark, folder, ["supplier", "orders", "lineitem", "part"])
    line = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    b = t["lineitem"].select(*line, F.col("l_orderkey").alias("cID"), F.col("l_partkey").alias("dID"))
    c = t["orders"].select(F.col("o_orderkey").alias("cID"), F.col("o_totalprice").alias("y"))
    d = t["part"].select(F.col("p_partkey").alias("dID"), (F.col("p_retailprice") / UNIT2).alias("z"))
    key = F.col("aid").cast("string")
    a = t["supplier"].select(F.col("s_suppkey").alias("aid")).withColumns({"cID": pick(_ids(c, "cID"), "g2", "c", key), "dID": pick(_ids(d, "dID"), "g2", "d", key), "x": F.lit(1.0)})
    sums = b.join(d.withColumnRenamed("dID", "_d"), F.col("dID") == F.col("_d")).groupBy(F.col("cID").alias("_c")).agg(F.sum("z").alias("total"))
    specs = [TableSpec("A", ("aid",), ("x",)), TableSpec("B", tuple(line)), TableSpec("C", ("cID",), ("y",)), TableSpec("D", ("dID",), ("z",))]
    fks = [ForeignKey("A", "cID", "C"), ForeignKey("A", "dID", "D"), ForeignKey("B", "cID", "C"), ForeignKey("B", "dID", "D")]
    return Task(Catalog.build(specs, fks, {"A": labelled(a, sums), "B": b, "C": c, "D": d}), "A", name="syn2")


#: Traversal orders of the two databases: the second takes the misleading edge first.
ORDERS = {"syn1": (["A.cID", "B.cID", "A.bID"], ["A.bID", "B.cID", "A.cID"]), "syn2": (["A.cID", "B.cID", "B.dID", "A.dID"], ["A.dID", "B.dID", "B.cID", "A.cID"])}
#: The way along which the label can be known.
GOLDEN = {"syn1": ("A.cID>", "B.cID<"), "syn2": ("A.cID>", "B.cID<", "B.dID>")}
