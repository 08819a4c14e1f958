"""Tape, blocks, packed models against finite differences and the expression engine; learning; plans; streams; sources."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from relprop import propagate, synth, tape as T
from relprop.aggregate import neighbour_stats, salted_agg
from relprop.blocks import BlockSpec, DeepFmBlock, FmBlock, FtBlock, LinearBlock, MlpBlock, make_block, pairwise, register_block
from relprop.model import Packed, Rep, RowGnn, TableMeta, smoothing
from relprop.params import LatticeParams, ParamStore, load_model, save_model
from relprop.schema import star_catalog
from relprop.tape import Var
from relprop.train import Coder, Fit, Trained, loss_of, packed_batches, rep_model, run

META = {
    "A": TableMeta("A", ["x"], [("k", 3, "d")], [("A.c", "C"), ("A.b", "B")], []),
    "B": TableMeta("B", ["y"], [], [("B.c", "C")], [("A.b", "A")]),
    "C": TableMeta("C", ["z"], [], [], [("A.c", "A"), ("B.c", "B")]),
}


def small_batch(rng=np.random.default_rng(3)):
    a, b, c = 7, 5, 3
    parent = {"A.c": rng.integers(-1, c, a), "A.b": rng.integers(0, b, a), "B.c": rng.integers(0, c, b)}
    degree = {k: np.bincount(v[v >= 0], minlength={"A.c": c, "A.b": b, "B.c": c}[k]).astype(float) for k, v in parent.items()}
    numbers = {"A": rng.random((a, 1)), "B": rng.random((b, 1)), "C": rng.random((c, 1))}
    numbers["A"][0, 0] = np.nan
    return Packed(numbers, {"A": rng.integers(0, 3, (a, 1)), "B": np.zeros((b, 0), int), "C": np.zeros((c, 0), int)}, parent, degree, np.arange(a), rng.integers(0, 2, a).astype(float))


def check_gradient(model, batch, kind="binary", entries=40):
    w = model.init(1)
    _, g = loss_of(model, batch, w, None, kind)
    flat, rng = w.flat(), np.random.default_rng(0)
    for i in rng.choice(len(flat), min(entries, len(flat)), replace=False):
        e = np.zeros_like(flat)
        e[i] = 1e-6
        num = (loss_of(model, batch, w.like(flat + e), None, kind)[0] - loss_of(model, batch, w.like(flat - e), None, kind)[0]) / 2e-6
        assert abs(num - g[i]) <= 1e-5 * max(1.0, abs(num)) + 2e-6, (i, num, g[i])


@pytest.mark.parametrize("block", ["linear", "mlp", "fm", "deepfm", "transformer"])
def test_rep_gradients(block):
    check_gradient(Rep(META, "A", 2, 4, BlockSpec(block, {"widths": (6,)}), BlockSpec(block, {"widths": (6,)}), deltas={"A.c": 0.9}), small_batch())


@pytest.mark.parametrize("backbone", ["rgcn", "gat", "hgt"])
def test_row_network_gradients(backbone):
    check_gradient(RowGnn(META, "A", 2, backbone, 4, 8), small_batch())


def test_multiclass_and_regression_gradients():
    batch = small_batch()
    batch.label = np.array([0, 1, 2, 0, 1, 2, 1], float)
    check_gradient(Rep(META, "A", 1, 4, BlockSpec("linear"), BlockSpec("linear"), out=3), batch, "multiclass")
    check_gradient(Rep(META, "A", 1, 4, BlockSpec("linear"), BlockSpec("linear")), batch, "regression")


def test_pairwise_identity():
    x = np.random.default_rng(0).random((3, 5, 4))
    loops = sum(x[:, i] * x[:, j] for i in range(5) for j in range(i + 1, 5))
    assert np.allclose(pairwise(Var(x)).value, loops)


def test_attention_rows_sum_to_one():
    s = T.segment_softmax(Var(np.random.default_rng(0).random((9, 2))), np.array([0, 0, 1, 1, 1, 2, 2, 2, 2]), 3).value
    assert np.allclose([s[:2].sum(0), s[2:5].sum(0), s[5:].sum(0)], 1)
    assert np.allclose(T.softmax(Var(np.random.default_rng(1).random((4, 3)))).value.sum(-1), 1)


def test_block_shapes_and_plug_in():
    class Mean(LinearBlock):
        pass

    register_block("mean", Mean)
    rng = np.random.default_rng(0)
    for b in (make_block("mean"), MlpBlock((5,)), FmBlock(), DeepFmBlock((5,)), FtBlock()):
        for out in (1, 4):
            p = {k: Var(v) for k, v in b.init(3, 4, out, rng).items()}
            assert b.forward(Var(rng.random((6, 3, 4))), p).shape == (6, out)


def test_parameters_do_not_grow_with_depth_and_rows_skip():
    sizes = {k: Rep(META, "A", k, 4).init(0).nbytes for k in (1, 2, 3)}
    assert len(set(sizes.values())) == 1
    assert Rep(META, "A", 3, 4, shared=False).init(0).nbytes > sizes[3]
    batch, model = small_batch(), Rep(META, "A", 0, 4, deltas={})
    w = model.init(0)
    before = model.forward(batch, {k: Var(v) for k, v in w.items()}).value
    batch.numbers["B"] = batch.numbers["B"] + 1  # depth 0 sees the target alone
    assert np.allclose(before, model.forward(batch, {k: Var(v) for k, v in w.items()}).value)


def test_deep_rows_smooth_out():
    trace = []
    model = RowGnn(META, "A", 3, "rgcn", 4, 8)
    model.forward(small_batch(), {k: Var(v) for k, v in model.init(0).items()}, trace=trace)
    assert len(smoothing(trace, "A")) == 4


def test_edge_order_changes_nothing(spark, sf):
    cat = star_catalog(spark, sf, ["nation", "customer", "orders"])
    p = LatticeParams(2, 4)
    one = propagate.predict(cat, "customer", 2, p)
    two = propagate.predict(cat.permuted([1, 0]), "customer", 2, p)
    diff = one.join(two.select(F.col("c_custkey").alias("k"), F.col("logit").alias("l2")), F.col("c_custkey") == F.col("k")).agg(F.max(F.abs(F.col("logit") - F.col("l2"))), F.count("*")).first()
    assert diff[0] < 1e-9 and diff[1] == cat.frame("customer").count()


def test_expression_engine_by_recursion(spark):
    """Row by row in plain Python, on a few rows with an empty set and a null reference."""
    from relprop.schema import Catalog, ForeignKey, TableSpec

    parents, kids = [(1, 0.0), (2, 4.0), (3, 2.0)], [(1, 1, 1.0), (2, 1, 3.0), (3, None, 2.0), (4, 2, 5.0)]
    cat = Catalog.build([TableSpec("p", ("pid",), ("w",)), TableSpec("k", ("kid",), ("v",))], [ForeignKey("k", "pid", "p")], {"p": spark.createDataFrame(parents, "pid int, w double"), "k": spark.createDataFrame(kids, "kid int, pid int, v double")})
    prm, d = LatticeParams(2, 7), 2
    delta = np.mean([np.log1p(2), np.log1p(1), np.log1p(0)])
    enc = lambda t, c, x, lo, hi: [max(0.0, (x - lo) / (hi - lo) * prm.weight(f"{t}.{c}.w", 0, j) + prm.weight(f"{t}.{c}.b", 0, j)) for j in range(d)]
    own = {"p": {i: enc("p", "w", x, 0, 4) for i, x in parents}, "k": {i: enc("k", "v", x, 1, 5) for i, _, x in kids}}

    def block(fields, name, width, relu):
        out = [prm.weight(f"{name}.bias", 0, j) + sum(v[i] * prm.weight(f"{name}.w{f}", i, j) for f, v in enumerate(fields) for i in range(d)) for j in range(width)]
        return [max(0.0, o) for o in out] if relu else out

    def agg(vs):
        if not vs:
            return [0.0] * d
        s = np.log1p(len(vs)) / delta
        stat = {"mean": np.mean(vs, 0), "max": np.max(vs, 0), "min": np.min(vs, 0)}
        return [sum(stat[n][i] * (prm.weight(f"agg.k.pid.{n}.s0", i, j) + s * prm.weight(f"agg.k.pid.{n}.s1", i, j) + prm.weight(f"agg.k.pid.{n}.s2", i, j) / s) for n in stat for i in range(d)) for j in range(d)]

    def message(t, i, h, name, width, relu):
        if t == "p":
            f = [own["p"][i], agg([h["k"][k] for k, p, _ in kids if p == i]) if h else [0.0] * d]
        else:
            ref = next(p for k, p, _ in kids if k == i)
            f = [own["k"][i], h["p"][ref] if h and ref is not None else [0.0] * d]
        return block(f, name, width, relu)

    for depth in (0, 1, 2, 3):
        h = None
        for _ in range(depth):
            h = {t: {i: message(t, i, h, f"row.{t}", d, True) for i in own[t]} for t in own}
        got = {r["pid"]: r["logit"] for r in propagate.predict(cat, "p", depth, prm).collect()}
        for i in own["p"]:
            assert abs(got[i] - message("p", i, h, "head.p", 1, False)[0]) < 1e-9


def test_first_round_has_no_exchange_and_hubs_are_presummed(spark, sf):
    cat = star_catalog(spark, sf, ["customer", "orders"])
    fitted = propagate.Fitted.of(cat)
    h = propagate.propagate(cat, 1, LatticeParams(2), fitted)["orders"]
    assert "Exchange" not in h._jdf.queryExecution().executedPlan().toString()
    plan = neighbour_stats(cat.frame("orders"), "o_custkey", ["o_totalprice"])._jdf.queryExecution().executedPlan().toString()
    assert "partial_avg" in plan and "ReadSchema: struct<o_custkey" in plan
    assert "CartesianProduct" not in propagate.predict(cat, "customer", 2, LatticeParams(2), fitted)._jdf.queryExecution().executedPlan().toString()
    assert salted_agg(cat.frame("orders").select("o_custkey", "o_totalprice"), "o_custkey", "o_totalprice").count() == cat.frame("orders").select("o_custkey").distinct().count()


@pytest.fixture(scope="module")
def syn1(spark):
    return synth.schema1(spark, 400, 60)


def test_propagation_learns_where_the_misled_roll_up_does_not(spark, syn1):
    from relprop import rollup

    how = Fit(epochs=6, rate=0.01, patience=6, passes=40)
    rep = run(syn1, "rep", 2, how, d=8, batch_size=2000, row="mlp", head="mlp")[1].auc
    flat = rollup.rollup(syn1.catalog, rollup.rollup_plan(syn1.catalog, "A", 2, synth.ORDERS["syn1"][1], ("mean", "sum", "count")))
    bad = run(syn1, "flat", 0, how, flat=flat, d=8, batch_size=2000)[1].auc
    assert rep > 0.95 and rep > bad + 0.2


def test_modes_packing_and_saving(spark, syn1, tmp_path):
    trained, report, packed = run(syn1, "rep", 1, Fit(epochs=2, sync="step"), d=4, batch_size=200)
    assert report.tables_reached == 2 and packed.agg(F.sum("rows")).first()[0] == 400
    save_model(spark, str(tmp_path / "m"), trained.params, {"depth": 1})
    back, spec = load_model(spark, str(tmp_path / "m"))
    assert spec == {"depth": 1} and np.allclose(back.flat(), trained.params.flat())
    assert isinstance(back, ParamStore)
    scores = trained.score(packed)
    assert scores.count() == 400 and scores.filter("prob < 0 or prob > 1").count() == 0
    coder = Coder.fit(syn1)
    whole = packed_batches(syn1, coder, 1, 10_000)
    again = Trained(rep_model(coder, syn1, 1, 4), trained.params).score(whole)
    gap = scores.select("key", "logit").join(again.select("key", F.col("logit").alias("l2")), "key").agg(F.max(F.abs(F.col("logit") - F.col("l2")))).first()[0]
    assert gap < 1e-9  # a batch's size changes nothing: degrees and neighbours are whole


def test_random_search_space():
    from relprop.tune import sample

    t = sample("transformer", 50, 1)
    assert len(t) == 50 and all(1e-7 <= x.rate <= 1e-3 and 0 <= x.dropout <= 0.3 for x in t)


def test_sources_and_table_function(spark, sf, tmp_path):
    from relprop.ops import sources

    df = spark.read.parquet(f"{sf}/nation.parquet")
    for fmt in ("csv", "json", "orc", "parquet"):
        sources.write_any(df, str(tmp_path / fmt), fmt)
        assert sources.read_any(spark, str(tmp_path / fmt), fmt, df.schema).exceptAll(df).count() == 0
    cat = star_catalog(spark, sf, ["region", "nation", "customer"])
    sources.register_sql(spark, cat)
    got = spark.sql(f"SELECT * FROM join_paths('{sources.schema_json(cat)}', 'customer', 2)").collect()
    assert {r["path"] for r in got} == {"customer.c_nationkey>", "customer.c_nationkey> nation.n_regionkey>", "customer.c_nationkey> customer.c_nationkey<"}


def test_streamed_scores_follow_touched_keys(spark, sf, tmp_path):
    from relprop.ops import streaming

    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    seen = []
    q = streaming.score_stream(streaming.stream_table(spark, f"{sf}/events*.parquet", schema), "user_id", lambda k: k.withColumn("score", F.lit(1.0)), lambda df, n: seen.append(df.count()))
    q = q.option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert sum(seen) == spark.read.parquet(f"{sf}/events.parquet").select("user_id").distinct().count()


@pytest.mark.parametrize("call", [lambda e, t: e.aggregator_ablation(t, 1), lambda e, t: e.row_block_ablation(t, 1), lambda e, t: e.base_model_ablation(t, 1), lambda e, t: e.row_networks(t, 1)])
def test_runs_over_the_same_rows_share_their_batches(syn1, monkeypatch, call):
    """Codes are fitted and neighbourhoods packed once, whatever the number of runs."""
    from relprop import experiments, metrics

    made, used = [], []
    monkeypatch.setattr(experiments, "prepare", lambda task, depth: made.append(depth) or "ready")
    monkeypatch.setattr(experiments, "run", lambda *a, ready=None, **k: used.append(ready) or (None, metrics.RunReport("t", "m", 1, 0), None))
    assert len(call(experiments, syn1)) == len(used) and made == [1] and set(used) == {"ready"}


def test_vectors_that_the_target_does_not_need_are_left_out():
    """Scores are those of all tables and rows worked out; only the needed ones are."""
    batch = small_batch()
    batch.target, batch.label = np.array([5, 1, 1]), np.array([1.0, 0.0, 0.0])
    for backbone in ("rgcn", "gat", "hgt"):
        for depth in (0, 1, 2):
            model, done = RowGnn(META, "A", depth, backbone, 4, 8), []
            p = {k: Var(v) for k, v in model.init(0).items()}
            whole = model.forward(batch, p, trace=[]).value
            layer = model.layer
            model.layer = lambda i, b, h, p, t, *only: done.append((i, t, *map(len, only[:1] if only and only[0] is not None else []))) or layer(i, b, h, p, t, *only)
            assert np.allclose(model.forward(batch, p).value, whole)
            assert [x for x in done if x[0] == depth - 1] == ([(depth - 1, "A", 2)] if depth else [])


@pytest.mark.parametrize("depth", [0, 1, 2, 3])
def test_packed_rows_are_those_within_reach(spark, sf, depth):
    from relprop import graph, train

    names = ["customer", "orders", "lineitem", "part"]
    cat = star_catalog(spark, sf, names)
    cat = cat.with_frames({"orders": cat.frame("orders").withColumn("label", (F.col("o_orderkey") % 2).cast("int"))})
    task = train.Task(cat, "orders")
    packed = packed_batches(task, Coder.fit(task), depth, 300).collect()
    got = {r["batch_id"]: {t: train.unpack(r["blob"])[0].rows(t) for t in names} for r in packed}
    batches = spark.createDataFrame([(r["batch_id"], int(k)) for r in packed for k in train.unpack(r["blob"])[1]], "batch_id long, o_orderkey long")
    want = {b: dict.fromkeys(names, 0) for b in got}
    for t, df in graph.khop_subgraph(cat, "orders", batches, depth).items():
        for r in df.join(cat.frame(t), list(cat.key(t))).groupBy("batch_id").count().collect():  # rows that share a key all count
            want[r["batch_id"]][t] = r["count"]
    assert got == want and batches.distinct().count() == cat.frame("orders").count()


def test_packed_batches_are_not_dealt_again(syn1, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    from relprop.train import prepare

    ready = prepare(syn1, 1, 20)
    assert ready.packed.select("worker").distinct().count() == 400 // 20 // 8
    monkeypatch.setattr(DataFrame, "repartition", lambda *a: pytest.fail("batches are shuffled again"))
    assert run(syn1, "rep", 1, Fit(epochs=2), d=4, ready=ready)[0].history


def test_a_dictionary_is_found_once(spark):
    from relprop.features import CategoryCodec

    reads = spark.sparkContext.accumulator(0)
    seen = F.udf(lambda v: reads.add(1) or v)
    df = spark.createDataFrame([("b",), ("a",), (None,), ("Z",)], "k string").coalesce(1)
    codec = CategoryCodec.fit([(df.select(seen("k").alias("k")), "k", "d")])
    before = reads.value
    got = {r["k"]: r["i"] for r in codec.transform(df, "k", "i").collect()}
    assert got == {"Z": 1, "a": 2, "b": 3, None: 0} and reads.value == before


def registered(name, syn1, monkeypatch):
    """What a query asks of its runs, without running them: (method, depth, fit, options) of each."""
    from relprop import experiments, metrics

    asked = []
    monkeypatch.setattr(experiments.tasks, "orders_task", lambda *a: syn1)
    monkeypatch.setattr(experiments, "prepare", lambda task, depth, **k: "ready")
    monkeypatch.setattr(experiments, "run", lambda task, method, depth, how, **k: asked.append((method, depth, how, k)) or (None, metrics.RunReport("t", method, depth, 0), None))
    experiments.QUERY[name](None, None)
    return asked


def test_parameters_of_a_round_take_effect(spark, sf, syn1, monkeypatch):
    """The orders task leads from orders to customers and lines and back, so one table has vectors of two rounds from depth 3 on."""
    star = {"orders": TableMeta("orders", ["x"], [], [("o.c", "customer")], [("l.o", "lineitem")]), "customer": TableMeta("customer", ["x"], [], [], [("o.c", "orders")]), "lineitem": TableMeta("lineitem", ["x"], [], [("l.o", "orders")], [])}
    for _, depth, _, _ in registered("ablation_aggregator", syn1, monkeypatch):
        rounds = [t for tables in Rep(star, "orders", depth, 4)._need().values() for t in tables]
        assert len(rounds) > len(set(rounds))


def test_baselines_have_both_heads_and_the_whole_roll_up(syn1, monkeypatch):
    from relprop import experiments

    plans = []
    plan = experiments.rollup.rollup_plan
    monkeypatch.setattr(experiments.rollup, "rollup_plan", lambda cat, target, depth, *a: plans.append(depth) or plan(cat, target, depth, *a))
    asked = registered("train_baselines_orders", syn1, monkeypatch)
    assert [k["head"] for *_, k in asked] == ["deepfm", "transformer"] * 3 and set(plans) == {2}


def test_row_networks_train_at_full_size(syn1, monkeypatch):
    asked = registered("train_rowgnn_orders", syn1, monkeypatch)
    assert [m for m, *_ in asked] == ["rgcn", "gat", "hgt", "rep"]
    assert all(depth == 2 and how == Fit() and k["d"] == 16 and k.get("width", 64) == 64 for _, depth, how, k in asked)
