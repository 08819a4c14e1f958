"""Properties that the method is said to have: paths that are seen, order that does not matter, labels that do not leak."""

import pytest
from pyspark.sql import functions as F

from relprop import graph, propagate
from relprop.aggregate import neighbour_stats
from relprop.params import LatticeParams
from relprop.rollup import rollup, rollup_plan
from relprop.schema import Catalog, ForeignKey, TableSpec, Task


@pytest.fixture(scope="module")
def chain(spark):
    """a -> b <- c -> d: d is three steps from a."""
    frames = {
        "a": spark.createDataFrame([(1, 1, 0.2), (2, 2, 0.9)], "aid int, bid int, x double"),
        "b": spark.createDataFrame([(1, 0.1), (2, 0.7)], "bid int, y double"),
        "c": spark.createDataFrame([(1, 1, 1, 0.3), (2, 2, 2, 0.8), (3, 1, 2, 0.5)], "cid int, bid int, did int, u double"),
        "d": spark.createDataFrame([(1, 0.4), (2, 0.6), (3, 0.0), (4, 9.0)], "did int, z double"),
    }
    specs = [TableSpec("a", ("aid",), ("x",)), TableSpec("b", ("bid",), ("y",)), TableSpec("c", ("cid",), ("u",)), TableSpec("d", ("did",), ("z",))]
    return Catalog.build(specs, [ForeignKey("a", "bid", "b"), ForeignKey("c", "bid", "b"), ForeignKey("c", "did", "d")], frames)


@pytest.mark.parametrize("depth", [1, 2, 3])
def test_a_cell_counts_from_its_distance_on(chain, depth):
    params, fitted = LatticeParams(2, 11), propagate.Fitted.of(chain)
    at = lambda cat: propagate.predict(cat, "a", depth, params, fitted, kind="linear").filter("aid = 1").first()["logit"]
    changed = chain.with_frames({"d": chain.frame("d").withColumn("z", F.when(F.col("did") == 1, 5.0).otherwise(F.col("z")))})
    moved = abs(at(chain) - at(changed)) > 1e-12
    assert moved == (depth >= 3)
    assert graph.tables_reached(chain, "a", depth)[depth] == depth


def test_summaries_depend_on_the_set_alone(spark, sf):
    df = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_quantity")
    one = neighbour_stats(df, "l_orderkey", ["l_quantity"])
    two = neighbour_stats(df.repartition(7).orderBy(F.rand(3)), "l_orderkey", ["l_quantity"])
    assert one.exceptAll(two).count() == 0


def test_permuted_labels_leave_all_inputs(chain):
    def task(label):
        frame = chain.frame("a").withColumn("label", label)
        spec = TableSpec("a", ("aid",), ("x", "label"))
        return Task(Catalog.build([spec, *[s for n, s in chain.specs.items() if n != "a"]], list(chain.fks), {**chain.frames, "a": frame}), "a")

    params = LatticeParams(2, 3)
    one, two = task(F.col("aid") % 2), task(1 - F.col("aid") % 2)
    for depth in (1, 2):
        x, y = (propagate.predict(t.catalog, "a", depth, params).orderBy("aid").collect() for t in (one, two))
        assert x == y
        x, y = (rollup(t.catalog, rollup_plan(t.catalog, "a", depth)).orderBy("aid").collect() for t in (one, two))
        assert x == y


def test_zeroed_context_is_the_target_alone(chain):
    params, fitted = LatticeParams(2, 3), propagate.Fitted.of(chain)
    zero = {t: chain.frame(t).select(*dict.fromkeys([*chain.key(t), *(k.column for k in chain.forward(t))]), F.lit(0.0).alias("h_0"), F.lit(0.0).alias("h_1")) for t in chain.specs}
    a = propagate.message(chain, "a", zero, params, fitted, "head.a", 1, "linear").orderBy("aid").collect()
    b = propagate.message(chain, "a", None, params, fitted, "head.a", 1, "linear").orderBy("aid").collect()
    assert [r["h_0"] for r in a] == pytest.approx([r["h_0"] for r in b])


def test_range_join_takes_all_lines(spark, tmp_path):
    """Against brute force: lines of high order keys count, equal prices as often as they occur."""
    from relprop.queries import QUERIES

    lines = [(1 + 37 * i % 900, float(100 * (i % 40))) for i in range(300)]
    orders = [(i, 90.5 * i) for i in range(60)]
    spark.createDataFrame(lines, "l_orderkey long, l_extendedprice double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    want = {o: n for o, t in orders if (n := sum(t <= p < t + 500 for _, p in lines))}
    assert {r["o_orderkey"]: r["n"] for r in QUERIES["range_join_prices"](spark, str(tmp_path)).collect()} == want


def test_khop_takes_every_order(spark, sf):
    from relprop.queries import QUERIES

    got = QUERIES["khop_orders_k2"](spark, sf)
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").join(spark.read.parquet(f"{sf}/orders.parquet"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").distinct().count()
    assert got.filter("tbl = 'lineitem'").agg(F.sum("n")).first()[0] == lines and got.filter("tbl = 'orders'").count() == 7


@pytest.mark.parametrize("depth", [0, 1, 2, 3])
def test_layerwise_scores_are_those_of_packed_neighbourhoods(spark, sf, depth):
    """Every target's logit, at any depth; rows that nothing refers to included."""
    from relprop import layers, tasks
    from relprop.train import Coder, Trained, packed_batches, rep_model

    task = tasks.orders_task(spark, sf)
    task = type(task)(task.catalog.with_frames({"orders": task.catalog.frame("orders").filter("o_orderkey < 200")}), "orders")
    coder = Coder.fit(task)
    model = rep_model(coder, task, depth, 4, squash=depth == 3)
    params = model.init(3)
    got = {r["key"]: r["logit"] for r in layers.transform(task, coder, model, params).collect()}
    want = {r["key"]: r["logit"] for r in Trained(model, params).score(packed_batches(task, coder, depth, 64)).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-6 * max(1, abs(want[k])) for k in want)


def test_medians_and_ranks_are_exact(spark):
    import numpy as np

    from relprop import tasks

    rng = np.random.default_rng(2)
    for x in ([], [3.0], [1.0, 2.0], [5.0] * 7 + [1.0], rng.normal(size=2001).round(2).tolist(), rng.integers(0, 3, 500).astype(float).tolist(), rng.normal(size=1000).tolist()):
        df = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "k long, x double")
        assert tasks.median_of(df, "x") == (pytest.approx(float(np.median(x))) if x else None)
        got = {r["k"]: r["r"] for r in tasks.percent_rank_of(df, "k", "x", "r").collect()}
        assert got == {i: pytest.approx(sum(w < v for w in x) / max(1, len(x) - 1)) for i, v in enumerate(x)}


def test_composite_references_are_refused():
    from relprop.schema import Catalog, ForeignKey, TableSpec

    with pytest.raises(ValueError, match="several"):
        Catalog.build([TableSpec("a", ("x", "y")), TableSpec("b", ("z",))], [ForeignKey("b", "r", "a")])


def test_node_keys_are_told_apart(spark):
    from relprop.graph import node_key

    df = spark.createDataFrame([("a/b", "c"), ("a", "b/c"), ("a\\", "b"), (None, "b"), ("\\N", "b"), ("", "b")], "x string, y string")
    assert df.select(node_key(("x", "y")).alias("k")).distinct().count() == 6


def test_range_counts_are_those_of_the_join(spark):
    """Ties at both ends, empty bins, repeated keys, turned intervals, nulls and NaN; no plan pairs the two sides."""
    from relprop.ops import joins

    nan = float("nan")
    left = spark.createDataFrame([(x,) for x in (0.0, 1.0, 1.0, 2.5, 9.5, 10.0, 31.0, -3.0, None, nan)], "v double")
    spans = spark.createDataFrame([(1, 1.0, 2.5), (2, 0.0, 10.0), (2, 9.5, 40.0), (3, 50.0, 60.0), (4, 5.0, 1.0), (5, None, 3.0), (6, -10.0, 1.0), (7, 12.0, nan), (8, 10.0, 10.0)], "k long, lo double, hi double")
    got = joins.range_counts(left, spans, "k", "v", "lo", "hi", 4.0)
    want = left.join(spans, (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi"))).groupBy("k").count()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_block_loops_are_the_join(spark, monkeypatch):
    """Nested loops over many rows go over blocks, whose product is a small part of the rows'."""
    from relprop.ops import joins

    monkeypatch.setattr(joins, "LOOP_PAIRS", 1000)
    left = spark.createDataFrame([(i % 40 if i % 7 else None, i) for i in range(300)], "a int, x long")
    right = spark.createDataFrame([(i % 50, f"r{i}") for i in range(90)], "b long, y string")
    for rows, by_block in ((joins.BROADCAST_ROWS, True), (10, False)):
        got = joins.hinted(left, right, F.col("a") == F.col("b"), "shuffle_replicate_nl", rows=rows, keys=("a", "b"))
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert ("CartesianProduct" in plan and "collect_list" in plan) == by_block
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, left.join(right, F.col("a") == F.col("b")).collect()))


def test_deduplicated_stream_goes_to_files(spark, sf, monkeypatch):
    """Rows of the stream are no table of the driver's memory."""
    from relprop.ops import streaming
    from relprop.queries import QUERIES

    monkeypatch.setattr(streaming, "run_available", None)
    assert QUERIES["stream_dedup"](spark, sf).first()["n"] == spark.read.parquet(f"{sf}/events.parquet").select("event_id").distinct().count()
