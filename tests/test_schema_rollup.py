"""Schema walks, roll-up plans and their coverage, by the traces worked out by hand."""

import pytest
from pyspark.sql import functions as F

from relprop import features, flatten, graph, metrics, rollup, superset, synth
from relprop.schema import Catalog, ForeignKey, TableSpec, Task, infer_catalog, star_catalog


@pytest.fixture(scope="module")
def tri(spark):
    a = spark.createDataFrame([(1, 1, 1, 1.0, 0), (2, 1, 2, 1.0, 1), (3, 2, None, 1.0, 0), (4, 3, 1, 1.0, 1)], "aid int, bID int, cID int, x double, label int")
    b = spark.createDataFrame([(1, 1, 0.5), (2, 1, 0.25), (3, 1, 1.0)], "bID int, cID int, y double")
    c = spark.createDataFrame([(1, 1.0), (2, 3.0)], "cID int, z double")
    specs = [TableSpec("A", ("aid",), ("x",)), TableSpec("B", ("bID",), ("y",)), TableSpec("C", ("cID",), ("z",))]
    return Catalog.build(specs, [ForeignKey("A", "bID", "B"), ForeignKey("A", "cID", "C"), ForeignKey("B", "cID", "C")], {"A": a, "B": b, "C": c})


def labels(cat, depth, order):
    return {f.label for f in rollup.rollup_plan(cat, "A", depth, order, ("mean",)).features}


def test_traversals_of_the_triangle(tri):
    one, two = synth.ORDERS["syn1"]
    assert labels(tri, 2, one) == {"x", "A.cID>z", "A.cID>mean(A.cID<x)", "A.cID>mean(B.cID<y)", "A.bID>y"}
    assert labels(tri, 2, two) == {"x", "A.bID>y", "A.bID>mean(A.bID<x)", "A.bID>B.cID>z", "A.cID>z"}
    assert "A.cID>mean(B.cID<y)" in labels(tri, 3, two)
    assert [len(graph.walks(tri, "A", 2)), len(graph.simple_paths(tri, "A", 2))] == [6, 4]
    assert rollup.path_coverage(tri, rollup.rollup_plan(tri, "A", 2, one), 2) == (3, 4)


def test_second_schema_is_never_repaired(spark):
    cat = synth.schema2(spark, 20, 5, 10).catalog
    first, second = synth.ORDERS["syn2"]
    golden = synth.GOLDEN["syn2"]
    assert golden in rollup.rollup_paths(rollup.rollup_plan(cat, "A", 3, first))
    for depth in (3, 4, 5):
        assert golden not in rollup.rollup_paths(rollup.rollup_plan(cat, "A", depth, second))
    steps = rollup.escalate_depth(cat, "A", second, 3)
    assert [d for d, _ in steps] == [3, 4]


def test_coverage_is_not_monotone_in_depth():
    from relprop import oracle

    cat = oracle.star([s.name for s in oracle.STAR_SPECS])
    order = ["orders.o_custkey", "customer.c_nationkey", "supplier.s_nationkey", "lineitem.l_suppkey"]
    reach = {k: any("lineitem.l_partkey>" in p for p in rollup.rollup_paths(rollup.rollup_plan(cat, "orders", k, order))) for k in (2, 3, 4, 5)}
    assert reach[2] and reach[5]
    assert rollup.order_report(cat, "orders", 3, [["orders.o_custkey", "lineitem.l_orderkey"], ["lineitem.l_orderkey", "orders.o_custkey"]])[0][2:] != (0, 0)


def test_width_is_known_before_running(tri):
    plan = rollup.rollup_plan(tri, "A", 2)
    assert len(rollup.rollup(tri, plan).columns) - 1 == rollup.rollup_width(plan)
    with pytest.raises(ValueError):
        rollup.rollup(tri, plan, max_columns=1)


def test_superset_on_nulls_and_empty_sets(tri):
    for depth in (1, 2):
        r = superset.superset_report(tri, "A", depth).collect()
        assert r and not any(x["missing"] for x in r) and sum(x["differing"] for x in r) == 0


def test_label_is_no_feature(tri):
    spec = TableSpec("A", ("aid",), ("x", "label"))
    task = Task(Catalog.build([spec, *[s for n, s in tri.specs.items() if n != "A"]], list(tri.fks), tri.frames), "A")
    assert "label" not in features.feature_columns(task.catalog, "A")
    assert not any("label" in f.label for f in rollup.rollup_plan(task.catalog, "A", 3).features)


def test_target_only_of_keys_is_not_applicable(tri):
    cat = Catalog.build([TableSpec("K", ("aid",))], [], {"K": tri.frame("A")})
    with pytest.raises(flatten.NotApplicable):
        flatten.target_only(cat, "K")


def test_two_references_and_self_reference(spark):
    trip = spark.createDataFrame([(1, 1, 2, 5.0), (2, 2, 2, 1.0)], "id int, from_city int, to_city int, km double")
    city = spark.createDataFrame([(1, 10.0), (2, 20.0)], "cid int, pop double")
    cat = Catalog.build([TableSpec("trip", ("id",), ("km",)), TableSpec("city", ("cid",), ("pop",))], [ForeignKey("trip", "from_city", "city"), ForeignKey("trip", "to_city", "city")], {"trip": trip, "city": city})
    assert len(cat.forward("trip")) == len(cat.backward("city")) == 2
    assert flatten.simple_join(cat, "trip").filter("id = 1").first()["trip.to_city>pop"] == 20.0
    staff = spark.createDataFrame([(1, None, 9.0), (2, 1, 5.0), (3, 1, 7.0)], "sid int, boss int, pay double")
    cat = Catalog.build([TableSpec("staff", ("sid",), ("pay",))], [ForeignKey("staff", "boss", "staff")], {"staff": staff})
    got = {r["sid"]: r["mean(staff.boss<pay)"] for r in rollup.rollup(cat, rollup.rollup_plan(cat, "staff", 1)).collect()}
    assert got == {1: 6.0, 2: None, 3: None}


def test_validate_and_infer(spark, sf, tri):
    assert star_catalog(spark, sf, ["region", "nation"]).validate() == []
    assert any("B" in p for p in tri.with_frames({"B": tri.frame("B").unionByName(tri.frame("B"))}).validate())
    found = infer_catalog({n: spark.read.parquet(f"{sf}/{n}.parquet") for n in ("region", "nation")}, {"region": "r_regionkey", "nation": "n_nationkey"})
    assert [k.name for k in found.fks] == ["nation.n_regionkey"]


def test_khop_fanout_caps_children(spark, sf):
    cat = star_catalog(spark, sf, ["customer", "orders"])
    t = cat.frame("customer").select(F.lit(0).alias("batch_id"), "c_custkey")
    full, few = (graph.khop_subgraph(cat, "customer", t, 1, f)["orders"].count() for f in (None, 2))
    per = cat.frame("orders").groupBy("o_custkey").count().agg(F.sum(F.least("count", F.lit(2)))).first()[0]
    assert full == cat.frame("orders").count() and few == per


def test_needed_tables():
    from relprop import oracle

    cat = oracle.star(["orders", "customer", "lineitem"])
    assert graph.needed_tables(cat, "orders", 2) == {2: {"customer", "lineitem"}, 1: {"orders"}}


def test_auc_ties_and_missing_class(spark):
    df = spark.createDataFrame([(0.1, 0), (0.5, 1), (0.5, 0), (0.9, 1), (None, 1)], "s double, y int")
    assert metrics.auc(df, "s", "y").first()["auc"] == 0.875
    assert metrics.auc_local([0.1, 0.5, 0.5, 0.9], [0, 1, 0, 1]) == 0.875
    assert metrics.auc(df.filter("y = 1"), "s", "y").first()["auc"] is None
    assert abs(metrics.auc_ml(df.dropna(), "s", "y") - 0.875) < 1e-9
    b = metrics.auc_binned(df.dropna(), "s", "y", 4).first()
    assert abs(b["auc"] - 0.875) <= b["bound"] + 1e-12


def test_category_codec_null_unseen_and_hash(spark):
    df = spark.createDataFrame([("b",), ("a",), (None,)], "v string")
    c = features.CategoryCodec.fit([(df, "v", "d")])
    assert {r["v"]: r["v_id"] for r in c.transform(spark.createDataFrame([("a",), ("b",), ("zz",), (None,)], "v string"), "v").collect()} == {"a": 1, "b": 2, "zz": 0, None: 0}
    h = features.CategoryCodec.fit([(df, "v", "d")], max_size=2)
    h.max_size = 2
    assert {r["v_id"] for r in h.transform(df, "v").collect()} <= {0, 1, 2}


def test_minmax_constant_clamp_null(spark):
    c = features.MinMaxCodec.fit(spark.createDataFrame([(1.0, 5.0), (3.0, 5.0)], "a double, b double"), ["a", "b"])
    got = c.transform(spark.createDataFrame([(9.0, 5.0), (2.0, None), (None, 1.0)], "a double, b double")).collect()
    assert [(r["a_unit"], r["b_unit"]) for r in got] == [(1.0, 0.0), (0.5, None), (None, 0.0)]


def test_reports_on_the_schema_follow_the_rows(spark, sf, tmp_path):
    """A reference that no row has, and a feature without a value, are no part of the reports."""
    import os

    from pyspark.sql import functions as F

    from relprop.queries import QUERIES

    for name in os.listdir(sf):
        df = spark.read.parquet(f"{sf}/{name}")
        if name == "orders.parquet":
            df = df.withColumn("o_custkey", F.lit(None).cast("long")).withColumn("o_totalprice", F.lit(None).cast("double"))
        if name == "lineitem.parquet":
            df = df.withColumn("l_partkey", F.lit(None).cast("long"))
        df.write.parquet(f"{tmp_path}/{name}")
    both = {n: [{tuple(r) for r in QUERIES[n](spark, f).collect()} for f in (sf, str(tmp_path))] for n in ("schema_reach", "dfs_width", "dfs_path_coverage", "rep_walk_coverage", "dfs_order_sensitivity", "table_widths", "rerun_summary", "synthetic_schema1", "synthetic_schema2")}
    assert all(a != b for a, b in both.values()), {n: v for n, v in both.items() if v[0] == v[1]}
    assert max(r[1] for r in both["schema_reach"][1]) < max(r[1] for r in both["schema_reach"][0])


def test_order_sensitivity_is_over_given_tables(spark, sf, monkeypatch):
    from relprop import experiments

    seen = []
    monkeypatch.setattr(experiments, "run", lambda task, *a, **k: seen.append(task) or (None, metrics.RunReport(task.name, "", 0, 0), None))
    assert len(experiments.QUERY["train_order_sensitivity"](spark, sf)) == 8
    assert all(task.catalog.frame("A").inputFiles() for task in seen)
