"""Queries of the library, each with SQL for DuckDB where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import aggregate, features, fixed, flatten, graph, metrics, oracle, propagate, rollup, superset, synth, tasks
from .ops import analytics, joins
from .params import LatticeParams
from .schema import Task, part_of, read_tables, star_catalog

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return put


def tab(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A small result that was worked out on the driver."""
    return spark.createDataFrame(rows, schema)


# Graph view.

CAT_ALL = [s.name for s in oracle.STAR_SPECS]
_CAT = oracle.star(CAT_ALL)
_key = lambda cols: " || '/' || ".join(f"{c}::VARCHAR" for c in cols)

query("graph_nodes", " UNION ALL ".join(f"SELECT '{t}' AS ntype, {_key(s.key)} AS key, {len(s.features)}::BIGINT AS n_feat FROM {t}" for t, s in _CAT.specs.items()))(
    lambda s, d: graph.nodes(star_catalog(s, d)).select("ntype", "key", F.size("feat").cast("long").alias("n_feat"))
)
query(
    "graph_edges",
    " UNION ALL ".join(f"SELECT '{k.name}' AS etype, '{way}' AS dir, {a} AS src, {b} AS dst FROM {k.src}" for k in _CAT.fks for way, a, b in (("forward", _key(_CAT.key(k.src)), f"{k.column}::VARCHAR"), ("backward", f"{k.column}::VARCHAR", _key(_CAT.key(k.src))))),
)(lambda s, d: graph.edges(star_catalog(s, d)))
query("graph_degrees", "SELECT o_orderkey AS key, count(l_orderkey)::BIGINT AS deg FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")(lambda s, d: graph.degrees(star_catalog(s, d), "lineitem.l_orderkey"))
_stat = [f"SELECT 'table' AS kind, '{t}' AS name, count(*)::BIGINT AS n, 0::BIGINT AS max_degree, 0.0::DOUBLE AS mean_degree FROM {t}" for t in _CAT.specs]
_stat += [f"SELECT 'edge' AS kind, '{k.name}' AS name, sum(n)::BIGINT AS n, max(n)::BIGINT AS max_degree, round(avg(n), 6) AS mean_degree FROM (SELECT {_CAT.key(k.dst)[0]}, count({k.column}) AS n FROM {k.dst} LEFT JOIN (SELECT {k.column} FROM {k.src}) ON {k.column} = {_CAT.key(k.dst)[0]} GROUP BY 1)" for k in _CAT.fks]
query("graph_stats", " UNION ALL ".join(_stat))(lambda s, d: graph.graph_stats(star_catalog(s, d)).withColumn("mean_degree", F.round(F.coalesce("mean_degree", F.lit(0.0)), 6)).withColumn("max_degree", F.coalesce("max_degree", F.lit(0))))

_EDGE_ROWS = ", ".join(f"('{k.src}', '{k.dst}'), ('{k.dst}', '{k.src}')" for k in _CAT.fks)
query(
    "schema_reach",
    f"WITH RECURSIVE e(a, b) AS (VALUES {_EDGE_ROWS}), r(t, k) AS (SELECT 'orders', 0 UNION SELECT b, k + 1 FROM r JOIN e ON a = t WHERE k < 5), f AS (SELECT t, min(k) AS k FROM r GROUP BY t) SELECT d.k::BIGINT AS depth, (count(*) - 1)::BIGINT AS tables FROM range(0, 6) AS d(k) JOIN f ON f.k <= d.k GROUP BY 1",
)(lambda s, d: values(s, list(graph.tables_reached(graph.live(star_catalog(s, d)), "orders", 5).items()), "depth long, tables long"))


@query(
    "khop_orders_k2",
    """WITH t AS (SELECT o_orderkey, o_custkey, o_orderkey % 7 AS batch_id FROM orders),
    c AS (SELECT DISTINCT batch_id, o_custkey AS k FROM t WHERE o_custkey IN (SELECT c_custkey FROM customer)),
    l AS (SELECT DISTINCT batch_id, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM t JOIN lineitem ON l_orderkey = o_orderkey),
    o AS (SELECT batch_id, o_orderkey AS k FROM t UNION SELECT batch_id, orders.o_orderkey FROM c JOIN orders ON orders.o_custkey = k)
    SELECT batch_id::BIGINT AS batch_id, 'customer' AS tbl, count(*)::BIGINT AS n FROM c GROUP BY 1 UNION ALL SELECT batch_id::BIGINT, 'lineitem', count(*)::BIGINT FROM l GROUP BY 1 UNION ALL SELECT batch_id::BIGINT, 'orders', count(*)::BIGINT FROM o GROUP BY 1""",
)
def khop_orders_k2(s, d):
    """Every order is a target, as in tasks.orders_task."""
    cat = star_catalog(s, d, ["orders", "customer", "lineitem"])
    reach = graph.khop_subgraph(cat, "orders", cat.frame("orders").select((F.col("o_orderkey") % 7).alias("batch_id"), "o_orderkey"), 2)
    parts = [df.groupBy("batch_id").agg(F.lit(t).alias("tbl"), F.count("*").alias("n")) for t, df in reach.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


# Encoders.

query("encode_dates_orders", "SELECT o_orderkey, year(o_orderdate)::BIGINT AS o_orderdate_year, month(o_orderdate)::BIGINT AS o_orderdate_month, day(o_orderdate)::BIGINT AS o_orderdate_day, (isodow(o_orderdate) - 1)::BIGINT AS o_orderdate_weekday FROM orders")(
    lambda s, d: features.expand_dates(tab(s, d, "orders").select("o_orderkey", "o_orderdate"), ["o_orderdate"]).drop("o_orderdate")
)
_MM = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


@query("encode_minmax_lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, " + ", ".join(f"round(({c} - (SELECT min({c}) FROM lineitem)) / (SELECT max({c}) - min({c}) FROM lineitem), 6) AS {c}_unit" for c in _MM) + " FROM lineitem")
def encode_minmax_lineitem(s, d):
    df = tab(s, d, "lineitem")
    out = features.MinMaxCodec.fit(df, _MM).transform(df)
    return out.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", *[F.round(f"{c}_unit", 6).alias(f"{c}_unit") for c in _MM])


@query(
    "encode_category_orders",
    "WITH v AS (SELECT o_orderstatus AS v FROM orders UNION SELECT l_linestatus FROM lineitem), dict AS (SELECT v, dense_rank() OVER (ORDER BY v) AS id FROM v), pr AS (SELECT o_orderpriority AS v, dense_rank() OVER (ORDER BY o_orderpriority) AS id FROM (SELECT DISTINCT o_orderpriority FROM orders)) SELECT o_orderkey, a.id::BIGINT AS status_id, b.id::BIGINT AS priority_id FROM orders JOIN dict a ON o_orderstatus = a.v JOIN pr b ON o_orderpriority = b.v",
)
def encode_category_orders(s, d):
    o, li = tab(s, d, "orders"), tab(s, d, "lineitem")
    c = features.CategoryCodec.fit([(o, "o_orderstatus", "status"), (li, "l_linestatus", "status"), (o, "o_orderpriority", "priority")])
    df = c.transform(c.transform(o.select("o_orderkey", "o_orderstatus", "o_orderpriority"), "o_orderstatus", "status_id"), "o_orderpriority", "priority_id")
    return df.select("o_orderkey", F.col("status_id").cast("long"), F.col("priority_id").cast("long"))


_P2, _P3 = LatticeParams(2, 1), LatticeParams(2, 2)


@query("encode_affine_part", "SELECT p_partkey, " + ", ".join(f"round(greatest(0.0, (p_retailprice - (SELECT min(p_retailprice) FROM part)) / (SELECT max(p_retailprice) - min(p_retailprice) FROM part) * {oracle.num(_P2.weight('a', 0, j))} + {oracle.num(_P2.weight('b', 0, j))}), 6) AS f_{j}" for j in range(2)) + " FROM part")
def encode_affine_part(s, d):
    df = tab(s, d, "part")
    x = features.MinMaxCodec.fit(df, ["p_retailprice"]).unit("p_retailprice")
    f = features.field_affine(x, [_P2.weight("a", 0, j) for j in range(2)], [_P2.weight("b", 0, j) for j in range(2)])
    return df.select("p_partkey", *[F.round(c, 6).alias(f"f_{j}") for j, c in enumerate(f)])


_SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
_LOOKUP = [[_P2.weight("seg", i, j) for j in range(2)] for i in range(len(_SEGMENTS) + 1)]


@query(
    "encode_lookup_customer",
    "SELECT c_custkey, " + ", ".join("round(CASE c_mktsegment " + " ".join(f"WHEN '{g}' THEN {oracle.num(_LOOKUP[i + 1][j])}" for i, g in enumerate(_SEGMENTS)) + f" ELSE {oracle.num(_LOOKUP[0][j])} END, 6) AS v_{j}" for j in range(2)) + " FROM customer",
)
def encode_lookup_customer(s, d):
    """Rows of a table of vectors by id; id 0 stands for values that have none."""
    ident = F.coalesce(*[F.when(F.col("c_mktsegment") == g, i + 1) for i, g in enumerate(_SEGMENTS)], F.lit(0))
    return tab(s, d, "customer").select("c_custkey", *[F.round(c, 6).alias(f"v_{j}") for j, c in enumerate(features.field_lookup(ident, _LOOKUP))])


query("impute_events", "SELECT event_id, CASE WHEN value > 50 THEN 0.0 ELSE value END AS value, (value > 50)::INT::BIGINT AS value_missing FROM events")(
    lambda s, d: features.impute(tab(s, d, "events").select("event_id", F.when(F.col("value") <= 50, F.col("value")).alias("value")), {"value": 0.0}).withColumn("value_missing", F.col("value_missing").cast("long"))
)

# Propagation.


@query("gather_forward_orders_customer", "SELECT o_orderkey, coalesce(c_acctbal, 0.0) AS p_c_acctbal FROM orders LEFT JOIN customer ON c_custkey = o_custkey")
def gather_forward_q(s, d):
    return propagate.gather_forward(tab(s, d, "orders").select("o_orderkey", "o_custkey"), "o_custkey", tab(s, d, "customer"), "c_custkey", ["c_acctbal"], "p_").drop("o_custkey")


@query("neighbour_stats_orders_lineitem", "SELECT l_orderkey AS key, count(*)::BIGINT AS deg, round(avg(l_quantity), 6) AS mean_l_quantity, max(l_quantity) AS max_l_quantity, min(l_quantity) AS min_l_quantity FROM lineitem GROUP BY 1")
def neighbour_stats_q(s, d):
    return aggregate.neighbour_stats(tab(s, d, "lineitem"), "l_orderkey", ["l_quantity"]).withColumn("mean_l_quantity", F.round("mean_l_quantity", 6))


_SCALED = ", ".join(f"round(coalesce({e} * {f}(l_quantity), 0.0), 6) AS s{i}_{n}_l_quantity" for i, e in enumerate(("1.0", "ln(1 + count(l_orderkey)) / (SELECT v FROM d)", "(SELECT v FROM d) / nullif(ln(1 + count(l_orderkey)), 0)")) for n, f in (("mean", "avg"), ("max", "max"), ("min", "min")))
_SCALED_SQL = f"WITH d AS (SELECT avg(ln(1 + n)) AS v FROM (SELECT count(l_orderkey) AS n FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey)) SELECT o_orderkey AS key, count(l_orderkey)::BIGINT AS deg, {_SCALED} FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1"


def _degree_scaled(s, d):
    o, li = tab(s, d, "orders"), tab(s, d, "lineitem")
    stats = aggregate.with_empty(o, "o_orderkey", aggregate.neighbour_stats(li, "l_orderkey", ["l_quantity"]))
    out = aggregate.degree_scaled(stats, ["l_quantity"], aggregate.delta_of(stats))
    return out.select("key", "deg", *[F.round(c, 6).alias(c) for c in out.columns[2:]])


query("degree_scaled_orders", _SCALED_SQL)(_degree_scaled)
query("degree_scaled_empty_sets", f"SELECT * FROM ({_SCALED_SQL}) WHERE deg = 0")(lambda s, d: _degree_scaled(s, d).filter("deg = 0"))


def _rep(name: str, tables: list[str], target: str, depth: int, p: LatticeParams, kind: str = "relu", head: str = "linear", dates: bool = False):
    @query(name, oracle.rep_sql(oracle.star(tables, dates), target, depth, p, kind, head))
    def run(s, d):
        cat = star_catalog(s, d, tables, dates)
        return propagate.predict(cat, target, depth, p, kind=kind, head=head).select(*cat.key(target), F.round("logit", 6).alias("logit"))


_SMALL = ["nation", "customer", "orders", "lineitem"]
_rep("rep_lattice_k0_customer", _SMALL, "customer", 0, _P2)
_rep("rep_lattice_k1_orders", _SMALL, "orders", 1, _P2)
_rep("rep_lattice_k2_customer", _SMALL, "customer", 2, _P2)
_rep("rep_lattice_k3_customer", ["region", *_SMALL], "customer", 3, _P3)
_rep("rep_predict_orders", ["customer", "orders", "lineitem"], "orders", 2, _P3)
_rep("rep_fm_head_orders", ["customer", "orders", "lineitem"], "orders", 1, _P3, "relu", "fm")
_rep("rep_dates_orders", ["customer", "orders", "lineitem"], "orders", 1, _P2, dates=True)
_rep("rep_linear_customer", _SMALL, "customer", 2, _P3, "linear", "linear")

_ID = """SELECT o_orderkey, o_totalprice, c_acctbal AS fwd, round(avg(l_quantity), 6) AS mean_b, max(l_extendedprice) AS max_b, min(l_tax) AS min_b
FROM orders LEFT JOIN customer ON c_custkey = o_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey, o_totalprice, c_acctbal"""


@query("rep_identity_l2_orders", _ID)
def rep_identity_l2_orders(s, d):
    h = propagate.identity_propagate(star_catalog(s, d, ["orders", "customer", "lineitem"]), 2, target="orders")["orders"]
    pick = {"fwd": "orders.o_custkey>c_acctbal", "max_b": "max(lineitem.l_orderkey<l_extendedprice)", "min_b": "min(lineitem.l_orderkey<l_tax)"}
    return h.select("o_orderkey", "o_totalprice", *[F.col(f"`{c}`").alias(a) for a, c in pick.items()], F.round("`mean(lineitem.l_orderkey<l_quantity)`", 6).alias("mean_b"))


query("superset_violations", "SELECT * FROM (VALUES ('lineitem', 1, 0::BIGINT), ('orders', 1, 0::BIGINT), ('orders', 2, 0::BIGINT)) AS t(target, depth, violations)")(
    lambda s, d: _superset(s, d)
)


def _superset(s, d):
    out = None
    for target, depth, tables in (("lineitem", 1, ["orders", "lineitem"]), ("orders", 1, ["customer", "orders", "lineitem"]), ("orders", 2, ["customer", "orders", "lineitem"])):
        r = superset.superset_report(star_catalog(s, d, tables), target, depth).agg(F.lit(target).alias("target"), F.lit(depth).alias("depth"), F.coalesce(F.sum("differing"), F.lit(0)).cast("long").alias("violations"))
        out = r if out is None else out.unionByName(r)
    return out


# Baselines.

query("tt_orders", "SELECT o_orderkey, o_totalprice, o_orderstatus, o_orderpriority FROM orders")(lambda s, d: flatten.target_only(star_catalog(s, d), "orders"))


query("tt_dates_orders", f"SELECT o_orderkey, o_totalprice, o_orderstatus, o_orderpriority, o_orderdate_year, o_orderdate_month, o_orderdate_day, o_orderdate_weekday FROM {oracle.source('orders', oracle.star(['orders'], True))}")(lambda s, d: flatten.target_only(star_catalog(s, d, dates=True), "orders"))


def _plain(df: DataFrame, names: dict[str, str], keys: list[str]) -> DataFrame:
    """Labels to short names for comparison."""
    return df.select(*keys, *[F.col(f"`{c}`").alias(a) for a, c in names.items()])


_SJ = {"c_acctbal": "orders.o_custkey>c_acctbal", "c_mktsegment": "orders.o_custkey>c_mktsegment", "n_name": "orders.o_custkey>customer.c_nationkey>n_name", "r_name": "orders.o_custkey>customer.c_nationkey>nation.n_regionkey>r_name"}
query("sj_orders", "SELECT o_orderkey, o_totalprice, c_acctbal, c_mktsegment, n_name, r_name FROM orders LEFT JOIN customer ON c_custkey = o_custkey LEFT JOIN nation ON n_nationkey = c_nationkey LEFT JOIN region ON r_regionkey = n_regionkey")(
    lambda s, d: _plain(flatten.simple_join(star_catalog(s, d), "orders"), _SJ, ["o_orderkey", "o_totalprice"])
)
_SJL = {"buyer_nation": "lineitem.l_orderkey>orders.o_custkey>customer.c_nationkey>n_name", "seller_nation": "lineitem.l_suppkey>supplier.s_nationkey>n_name", "price": "lineitem.l_partkey>p_retailprice"}
query(
    "sj_lineitem",
    "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, a.n_name AS buyer_nation, b.n_name AS seller_nation, p_retailprice AS price FROM lineitem LEFT JOIN orders ON o_orderkey = l_orderkey LEFT JOIN customer ON c_custkey = o_custkey LEFT JOIN nation a ON a.n_nationkey = c_nationkey LEFT JOIN supplier ON s_suppkey = l_suppkey LEFT JOIN nation b ON b.n_nationkey = s_nationkey LEFT JOIN part ON p_partkey = l_partkey",
)(lambda s, d: _plain(flatten.simple_join(star_catalog(s, d), "lineitem"), _SJL, ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]))


def _dfs(s, d, tables, target, depth, order=None, aggs=rollup.AGGS):
    cat = star_catalog(s, d, tables)
    return rollup.rollup(cat, rollup.rollup_plan(cat, target, depth, order, aggs))


@query("dfs_orders_d1", "SELECT o_orderkey, o_totalprice, any_value(c_acctbal) AS bal, round(avg(l_quantity), 6) AS mq, max(l_quantity) AS xq, min(l_quantity) AS nq FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey LEFT JOIN customer ON c_custkey = o_custkey GROUP BY 1, 2")
def dfs_orders_d1(s, d):
    df = _dfs(s, d, ["orders", "customer", "lineitem"], "orders", 1)
    b = "lineitem.l_orderkey<l_quantity"
    return _plain(df, {"bal": "orders.o_custkey>c_acctbal", "mq": f"mean({b})", "xq": f"max({b})", "nq": f"min({b})"}, ["o_orderkey", "o_totalprice"]).withColumn("mq", F.round("mq", 6))


@query(
    "dfs_customer_d2",
    "WITH o AS (SELECT o_orderkey, o_custkey, max(l_quantity) AS x, avg(l_extendedprice) AS m FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1, 2) SELECT c_custkey, round(avg(x), 6) AS mx, min(x) AS nx, round(max(m), 6) AS xm FROM customer LEFT JOIN o ON o_custkey = c_custkey GROUP BY 1",
)
def dfs_customer_d2(s, d):
    df = _dfs(s, d, ["customer", "orders", "lineitem"], "customer", 2)
    x, m = "max(lineitem.l_orderkey<l_quantity)", "mean(lineitem.l_orderkey<l_extendedprice)"
    out = _plain(df, {"mx": f"mean(orders.o_custkey<{x})", "nx": f"min(orders.o_custkey<{x})", "xm": f"max(orders.o_custkey<{m})"}, ["c_custkey"])
    return out.withColumn("mx", F.round("mx", 6)).withColumn("xm", F.round("xm", 6))


@query(
    "dfs_mode_orders",
    "WITH c AS (SELECT l_orderkey, l_returnflag, count(*) AS n FROM lineitem GROUP BY 1, 2), r AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY n DESC, l_returnflag) AS rn FROM c) SELECT o_orderkey, l_returnflag AS flag FROM orders LEFT JOIN r ON l_orderkey = o_orderkey AND rn = 1",
)
def dfs_mode_orders(s, d):
    return _plain(_dfs(s, d, ["orders", "lineitem"], "orders", 1), {"flag": "mode(lineitem.l_orderkey<l_returnflag)"}, ["o_orderkey"])


_MODES = ("year", "month", "day", "weekday")
query(
    "dfs_dates_orders",
    "WITH li AS (SELECT * FROM " + oracle.source("lineitem", oracle.star(["lineitem"], True)) + "), " + ", ".join(f"{p}_ AS (SELECT l_orderkey AS k_{p}, l_shipdate_{p} AS ship_{p} FROM (SELECT l_orderkey, l_shipdate_{p}, row_number() OVER (PARTITION BY l_orderkey ORDER BY count(*) DESC, l_shipdate_{p}) AS rn FROM li GROUP BY 1, 2) WHERE rn = 1)" for p in _MODES)
    + " SELECT o_orderkey, " + ", ".join(f"o_orderdate_{p} AS own_{p}, ship_{p}" for p in _MODES) + " FROM " + oracle.source("orders", oracle.star(["orders"], True)) + "".join(f" LEFT JOIN {p}_ ON k_{p} = o_orderkey" for p in _MODES),
)(lambda s, d: (lambda cat: _plain(rollup.rollup(cat, rollup.rollup_plan(cat, "orders", 1)), {f"own_{p}": f"o_orderdate_{p}" for p in _MODES} | {f"ship_{p}": f"mode(lineitem.l_orderkey<l_shipdate_{p})" for p in _MODES}, ["o_orderkey"]))(star_catalog(s, d, ["orders", "lineitem"], dates=True)))

_PK = ["l_orderkey", "l_linenumber", "l_partkey", "bID"]
_PURCHASE = "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"


def _dfs_purchase(order: int, depth: int, names: dict[str, str]):
    def run(s, d):
        t = tasks.purchase(s, d)
        df = rollup.rollup(t.catalog, rollup.rollup_plan(t.catalog, "purchase", depth, tasks.PURCHASE_ORDERS[order]))
        return _plain(df, names, _PK).select(*_PK, *[F.round(a, 6).alias(a) for a in names])

    return run


_GOLD = "(SELECT s_nationkey AS nk, round(avg(s_acctbal), 6) AS gold FROM supplier GROUP BY 1)"
_GOLD_NAME = {"gold": "purchase.cID>mean(supplier.s_nationkey<s_acctbal)", "own": "purchase.bID>s_acctbal"}
query("dfs_purchase_t1_d2", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey AS \"bID\", gold, round(s_acctbal, 6) AS own {_PURCHASE} LEFT JOIN {_GOLD} ON nk = c_nationkey JOIN supplier ON s_suppkey = l_suppkey")(_dfs_purchase(0, 2, _GOLD_NAME))
query("dfs_purchase_t2_d2", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey AS \"bID\", round(s_acctbal, 6) AS own {_PURCHASE} JOIN supplier ON s_suppkey = l_suppkey")(_dfs_purchase(1, 2, {"own": _GOLD_NAME["own"]}))
query("dfs_purchase_t2_d3", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey AS \"bID\", gold, round(s_acctbal, 6) AS own {_PURCHASE} LEFT JOIN {_GOLD} ON nk = c_nationkey JOIN supplier ON s_suppkey = l_suppkey")(_dfs_purchase(1, 3, _GOLD_NAME))


def _dfs_pair(order: int, depth: int, names: dict[str, str]):
    def run(s, d):
        t = tasks.pair(s, d)
        df = rollup.rollup(t.catalog, rollup.rollup_plan(t.catalog, "pair", depth, tasks.PAIR_ORDERS[order]))
        return _plain(df, names, ["cID", "dID"]).select("cID", "dID", *[F.round(a, 6).alias(a) for a in names])

    return run


_PAIR = 'FROM (SELECT DISTINCT l_suppkey AS "cID", l_partkey AS "dID" FROM lineitem)'
query("dfs_pair_t1_d3", f'SELECT "cID", "dID", gold, p_retailprice AS z {_PAIR} JOIN (SELECT l_suppkey, round(avg(p_retailprice), 6) AS gold FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1) ON l_suppkey = "cID" JOIN part ON p_partkey = "dID"')(
    _dfs_pair(0, 3, {"gold": "pair.cID>mean(line.l_suppkey<line.l_partkey>p_retailprice)", "z": "pair.dID>p_retailprice"})
)
query("dfs_pair_t2_d3", f'SELECT "cID", "dID", p_retailprice AS z, one_c {_PAIR} JOIN part ON p_partkey = "dID", (SELECT 1.0::DOUBLE AS one_c)')(_dfs_pair(1, 3, {"z": "pair.dID>p_retailprice", "one_c": "pair.cID>one"}))

_WIDTHS = [(t, k) for t in ("orders", "customer", "lineitem") for k in (1, 2, 3)]
query("dfs_width", "SELECT * FROM (VALUES " + ", ".join(f"('{t}', {k}::BIGINT, {rollup.rollup_width(rollup.rollup_plan(_CAT, t, k))}::BIGINT)" for t, k in _WIDTHS) + ") AS w(target, depth, columns)")(
    lambda s, d: (lambda cat: values(s, [(t, k, len(rollup.rollup(cat, rollup.rollup_plan(cat, t, k)).columns) - len(cat.key(t))) for t, k in _WIDTHS], "target string, depth long, columns long"))(graph.live(star_catalog(s, d)))
)


def _coverage(s, d):
    rows = []
    for name, make in (("syn1", synth.given1), ("syn2", synth.given2)):
        cat = graph.live(make(s, d).catalog)
        depth = len(synth.GOLDEN[name])
        for i, o in enumerate(synth.ORDERS[name], 1):
            plan = rollup.rollup_plan(cat, "A", depth, o)
            got, of = rollup.path_coverage(cat, plan, depth)
            rows.append((name, i, got, of, synth.GOLDEN[name] in rollup.rollup_paths(plan)))
    return values(s, rows, "schema string, traversal long, caught long, paths long, golden boolean")


query("dfs_path_coverage", "SELECT * FROM (VALUES ('syn1', 1::BIGINT, 3::BIGINT, 4::BIGINT, true), ('syn1', 2::BIGINT, 3::BIGINT, 4::BIGINT, false), ('syn2', 1::BIGINT, 3::BIGINT, 6::BIGINT, true), ('syn2', 2::BIGINT, 3::BIGINT, 6::BIGINT, false)) AS t(schema, traversal, caught, paths, golden)")(_coverage)
query("rep_walk_coverage", "SELECT * FROM (VALUES ('syn1', 4::BIGINT, 6::BIGINT), ('syn2', 6::BIGINT, 14::BIGINT)) AS t(schema, simple_paths, walks)")(
    lambda s, d: values(s, [(n, len(set(graph.simple_paths(c := graph.live(m(s, d).catalog), "A", k)) & set(graph.walks(c, "A", k))), len(graph.walks(c, "A", k))) for n, m, k in (("syn1", synth.given1, 2), ("syn2", synth.given2, 3))], "schema string, simple_paths long, walks long")
)


@query("dfs_order_sensitivity")
def dfs_order_sensitivity(s, d):
    orders = [["orders.o_custkey", "lineitem.l_orderkey"], ["lineitem.l_orderkey", "orders.o_custkey"]]
    return values(s, rollup.order_report(graph.live(star_catalog(s, d)), "orders", 3, orders), "first string, second string, only_first long, only_second long")


# Blocks and layers by their own code, with fixed weights.

for _name in ("linear", "mlp", "fm", "deepfm"):
    query(f"block_{_name}_part", fixed.block_sql(_name))(lambda s, d, name=_name: fixed.block_scores(tab(s, d, "part"), name))


def _layer(backbone: str):
    def run(s, d):
        cat = star_catalog(s, d, ["orders", "customer", "lineitem"])
        label = cat.frame("orders").withColumn("label", F.lit(0))
        return fixed.layer_outputs(Task(cat.with_frames({"orders": label}), "orders"), backbone, {"orders": "o_totalprice", "customer": "c_acctbal", "lineitem": "l_quantity"})

    query(f"layer_{backbone}_orders", fixed.layer_sql(backbone))(run)


_layer("rgcn")
_layer("gat")


@query("layerwise_rep_orders")
def layerwise_rep_orders(s, d):
    """Every order scored round by round by a propagation model of depth 2; the tests hold it against packed neighbourhoods."""
    from . import layers, train

    task = tasks.orders_task(s, d)
    coder = train.Coder.fit(task)
    model = train.rep_model(coder, task, 2, 4)
    return layers.transform(task, coder, model, model.init(0))


# Tasks.

_MED = lambda c, t: f"(SELECT quantile_cont({c}, 0.5) FROM {t})"


def _label(make, *keys):
    return lambda s, d: (lambda t: t.catalog.frame(t.target).select(*keys, F.col("label").cast("long").alias("label")))(make(s, d))


query("label_purchase", f'WITH t AS (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey AS "bID", coalesce(total, 0.0) AS total {_PURCHASE} LEFT JOIN (SELECT s_nationkey, sum(s_acctbal) AS total FROM supplier GROUP BY 1) ON s_nationkey = c_nationkey) SELECT l_orderkey, l_linenumber, l_partkey, "bID", (round(total, 4) >= round({_MED("total", "t")}, 4))::INT::BIGINT AS label FROM t')(_label(tasks.purchase, *_PK))
query("label_pair", f'WITH s AS (SELECT l_suppkey, sum(p_retailprice) AS total FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1), t AS (SELECT "cID", "dID", total {_PAIR} JOIN s ON l_suppkey = "cID") SELECT "cID", "dID", (round(total, 4) >= round({_MED("total", "t")}, 4))::INT::BIGINT AS label FROM t')(_label(tasks.pair, "cID", "dID"))
_RANKED = "WITH {base}, r AS (SELECT {key}, percent_rank() OVER (ORDER BY {a}) + percent_rank() OVER (ORDER BY {b}) AS r FROM b) SELECT {key}, (r >= (SELECT quantile_cont(r, 0.5) FROM r))::INT::BIGINT AS label FROM r"
query("label_orders", _RANKED.format(base="b AS (SELECT o_orderkey, round(coalesce(sum(l_extendedprice * (1 - l_discount)), 0.0), 4) AS rev, c_acctbal FROM orders JOIN customer ON c_custkey = o_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey, c_acctbal)", key="o_orderkey", a="rev", b="c_acctbal"))(_label(tasks.orders_task, "o_orderkey"))
query(
    "label_impression",
    f"SELECT md5(l_orderkey || ':' || l_linenumber || ':' || l_partkey || ':' || l_suppkey) AS imp_id, (a.n_regionkey = b.n_regionkey OR p_retailprice > {_MED('p_retailprice', 'part')})::INT::BIGINT AS label FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation a ON a.n_nationkey = c_nationkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation b ON b.n_nationkey = s_nationkey JOIN part ON p_partkey = l_partkey",
)(_label(tasks.impression_task, "imp_id"))
query(
    "label_seen",
    _RANKED.format(base="c AS (SELECT user_id, round(avg((event_type = 'click')::INT::DOUBLE), 9) AS share FROM events GROUP BY 1), p AS (SELECT l_partkey AS pk, count(*) AS lines FROM lineitem GROUP BY 1), b AS (SELECT DISTINCT o_custkey * 100000000 + l_partkey AS seen_id, share, lines FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN c ON user_id = o_custkey JOIN p ON pk = l_partkey)", key="seen_id", a="share", b="lines"),
)(_label(tasks.seen_task, "seen_id"))
query(
    "label_user_day",
    "WITH d AS (SELECT DISTINCT user_id, ts::DATE AS day FROM events) SELECT user_id * 100 + day(a.day) AS ud_id, (NOT EXISTS (SELECT 1 FROM d b WHERE b.user_id = a.user_id AND b.day = a.day + 1))::INT::BIGINT AS label FROM d a WHERE a.day < DATE '2024-01-30'",
)(_label(tasks.user_day_task, "ud_id"))
query("label_buyer", f"WITH t AS (SELECT c_custkey, round(coalesce(sum(l_extendedprice), 0.0), 4) AS total FROM customer LEFT JOIN orders ON o_custkey = c_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1) SELECT c_custkey, (total >= {_MED('total', 't')})::INT::BIGINT AS label FROM t")(_label(tasks.buyer_task, "c_custkey"))
query(
    "splits_orders",
    "SELECT o_orderkey, CASE WHEN b < 600 THEN 'train' WHEN b < 800 THEN 'valid' ELSE 'test' END AS part FROM (SELECT o_orderkey, ('0x' || substr(md5('0:' || o_orderkey), 1, 8))::BIGINT % 1000 AS b FROM orders)",
)(lambda s, d: tab(s, d, "orders").select("o_orderkey", part_of(["o_orderkey"]).alias("part")))
query("label_balance_orders", "SELECT count(*)::BIGINT AS rows, round(avg((o_orderpriority IN ('1-URGENT', '2-HIGH'))::INT), 6) AS share_of_ones FROM orders")(
    lambda s, d: metrics.label_balance(tab(s, d, "orders").select(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").cast("int").alias("label"))).withColumn("share_of_ones", F.round("share_of_ones", 6))
)
_U = "(('0x' || substr(md5({}), 1, 8))::BIGINT / 4294967296.0)"
_SYN_A = "a AS (SELECT s_suppkey AS aid, floor({c} * (SELECT max({ck}) + 1 FROM {ct}))::BIGINT AS \"cID\"{more} FROM supplier)"
query(
    "synthetic_schema1",
    "WITH y AS (SELECT o_custkey AS c, sum(o_totalprice / 100000.0) AS total FROM orders GROUP BY 1), " + _SYN_A.format(c=_U.format("'g1:c:' || s_suppkey"), ck="c_custkey", ct="customer", more="") + ' SELECT aid, "cID", (coalesce(total, 0.0) >= 25)::INT::BIGINT AS label FROM a LEFT JOIN y ON c = "cID"',
)(lambda s, d: synth.given1(s, d).catalog.frame("A").select("aid", "cID", F.col("label").cast("long").alias("label")))
query(
    "synthetic_schema2",
    "WITH z AS (SELECT l_orderkey AS c, sum(p_retailprice / 200.0) AS total FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1), " + _SYN_A.format(c=_U.format("'g2:c:' || s_suppkey"), ck="o_orderkey", ct="orders", more=", floor(" + _U.format("'g2:d:' || s_suppkey") + ' * (SELECT max(p_partkey) + 1 FROM part))::BIGINT AS "dID"') + ' SELECT aid, "cID", "dID", (coalesce(total, 0.0) >= 25)::INT::BIGINT AS label FROM a LEFT JOIN z ON c = "cID"',
)(lambda s, d: synth.given2(s, d).catalog.frame("A").select("aid", "cID", "dID", F.col("label").cast("long").alias("label")))


def _task_counts(name: str, sql: str):
    """Rows of each label of a task, and of each of its tables."""

    def run(s, d):
        t = tasks.TASKS[name](s, d)
        out = t.rows().groupBy(F.concat(F.lit("label "), F.col(t.label).cast("string")).alias("what")).agg(F.count("*").alias("n"))
        for table in t.catalog.specs:
            if table != t.target:
                out = out.unionByName(t.catalog.frame(table).agg(F.lit(table).alias("what"), F.count("*").alias("n")))
        return out

    query(f"task_{name}", sql)(run)


_N = lambda what, frm: f" UNION ALL SELECT '{what}' AS what, count(*)::BIGINT AS n FROM {frm}"
_L = lambda e, frm: f"SELECT 'label ' || ({e})::INT AS what, count(*)::BIGINT AS n FROM {frm} GROUP BY 1"
_DOCS = _N("documents", "documents") + _N("langs", "(SELECT DISTINCT lang FROM documents)") + _N("sources", "(SELECT DISTINCT source FROM documents)") + _N("groups", "(SELECT DISTINCT text FROM documents)")
_LANG = "regexp_extract(html, '<html lang=\"([a-z]+)\"', 1)"
_task_counts("touch", _L("event_type = 'purchase'", "events") + _N("orders", "orders") + _N("customer", "customer"))
_task_counts("quality", _L("quality", "labels") + _DOCS)
_task_counts("toxic", _L("toxic", "labels") + _DOCS + _N("passages", "(SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text))") + _N("benchmark", "benchmark"))
_task_counts("role", _L("role = 'assistant'", "conversations") + _N("convs", "(SELECT DISTINCT conv_id FROM conversations)"))
_task_counts("page", _L(f"{_LANG} = 'en'", "pages") + _N("hosts", "(SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/]+)', 1) FROM pages)"))
_task_counts("page_langs", _L(f"list_position(['de', 'en', 'es', 'fr'], {_LANG}) - 1", f"(SELECT html FROM pages WHERE {_LANG} IN ('de', 'en', 'es', 'fr'))") + _N("hosts", f"(SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/]+)', 1) FROM pages WHERE {_LANG} IN ('de', 'en', 'es', 'fr'))"))
_task_counts("vector", _L("label = 0", "embeddings"))
_task_counts("vector_classes", _L("label", "embeddings"))

# Measures.

_SCORE = "floor(o_totalprice / 1000)"
_AUC_SQL = f"WITH s AS (SELECT {_SCORE} AS s, (o_orderstatus = 'F')::INT AS y FROM orders), c AS (SELECT s, sum(y) AS p, sum(1 - y) AS n FROM s GROUP BY 1), w AS (SELECT *, coalesce(sum(n) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c) SELECT sum(p)::BIGINT AS pos, sum(n)::BIGINT AS neg, round(sum(p * (below + n / 2.0)) / (sum(p) * sum(n)), 6) AS auc FROM w"


def _scored(s, d, rows=None):
    return (lambda o: o if rows is None else o.filter(rows))(tab(s, d, "orders")).select(F.floor(F.col("o_totalprice") / 1000).cast("double").alias("score"), (F.col("o_orderstatus") == "F").cast("int").alias("label"), F.col("o_totalprice"))


query("auc_fixed_score_orders", _AUC_SQL)(lambda s, d: metrics.auc(_scored(s, d), "score", "label").withColumn("auc", F.round("auc", 6)))
query(
    "auc_binned",
    "WITH m AS (SELECT max(o_totalprice) AS hi FROM orders), s AS (SELECT least(floor(o_totalprice / (SELECT hi FROM m) * 100), 99) AS s, (o_orderstatus = 'F')::INT AS y FROM orders), c AS (SELECT s, sum(y) AS p, sum(1 - y) AS n FROM s GROUP BY 1), w AS (SELECT *, coalesce(sum(n) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c) SELECT round(sum(p * (below + n / 2.0)) / (sum(p) * sum(n)), 6) AS auc, round(sum(p * n) / 2.0 / (sum(p) * sum(n)), 6) AS bound FROM w",
)(lambda s, d: (lambda df, hi: metrics.auc_binned(df.withColumn("u", F.col("o_totalprice") / hi), "u", "label", 100).select(F.round("auc", 6).alias("auc"), F.round("bound", 6).alias("bound")))(_scored(s, d), tab(s, d, "orders").agg(F.max("o_totalprice")).first()[0]))
_FOLD_SQL = f"WITH s AS (SELECT o_orderkey % 5 AS k, {_SCORE} AS s, (o_orderstatus = 'F')::INT AS y FROM orders), c AS (SELECT k, s, sum(y) AS p, sum(1 - y) AS n FROM s GROUP BY 1, 2), w AS (SELECT *, coalesce(sum(n) OVER (PARTITION BY k ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c), f AS (SELECT k, sum(p * (below + n / 2.0)) / (sum(p) * sum(n)) AS auc FROM w GROUP BY 1)"


@query("rerun_summary", _FOLD_SQL + " SELECT 'orders' AS task, 'fixed score' AS method, count(*)::BIGINT AS runs, round(avg(auc), 6) AS mean_auc, round(stddev_samp(auc), 6) AS std_auc FROM f")
def rerun_summary(s, d):
    """Five runs of one score, each over a fold of the orders."""
    runs = None
    for k in range(5):
        r = metrics.auc(_scored(s, d, F.col("o_orderkey") % 5 == k), "score", "label").select(F.lit("orders").alias("task"), F.lit("fixed score").alias("method"), "auc")
        runs = r if runs is None else runs.unionByName(r)
    return metrics.summarise(runs).withColumn("mean_auc", F.round("mean_auc", 6)).withColumn("std_auc", F.round("std_auc", 6))


query(
    "cost_model",
    "WITH n AS (SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem) + (SELECT count(*) FROM customer) AS rows), d AS (SELECT greatest((SELECT max(c) FROM (SELECT count(*) AS c FROM lineitem GROUP BY l_orderkey)), (SELECT max(c) FROM (SELECT count(*) AS c FROM orders GROUP BY o_custkey))) AS dd), x AS (SELECT rows::BIGINT AS rows, dd::BIGINT AS max_degree, least(1.0 + dd + dd::DOUBLE * dd, rows) AS bound, least(dd::DOUBLE * dd, rows) AS printed_bound, 8 * 4 + 8 * 4 * 8 + 16 + dd * 4.0 AS per_row FROM n, d) SELECT rows, max_degree, bound::DOUBLE AS bound, printed_bound::DOUBLE AS printed_bound, per_row::DOUBLE AS per_row, (2 * bound * per_row)::DOUBLE AS total FROM x",
)(lambda s, d: metrics.cost_model(star_catalog(s, d, ["orders", "lineitem", "customer"]), "orders", 2, 4))

# Operators around the methods.

_EV = lambda s, d: tab(s, d, "events")
@query("range_join_prices", "SELECT o_orderkey, count(*)::BIGINT AS n FROM orders JOIN lineitem ON l_extendedprice >= o_totalprice AND l_extendedprice < o_totalprice + 500 GROUP BY 1")
def range_join_prices(s, d):
    """All of lineitem with all of orders; the pairs are counted and not laid out."""
    spans = tab(s, d, "orders").select("o_orderkey", F.col("o_totalprice").alias("lo"), (F.col("o_totalprice") + 500).alias("hi"))
    return joins.range_counts(tab(s, d, "lineitem"), spans, "o_orderkey", "l_extendedprice", "lo", "hi", 1000.0)


query("asof_user_day", "SELECT e.event_id, (SELECT v.value FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'view' AND v.ts <= e.ts ORDER BY v.ts DESC, v.event_id DESC LIMIT 1) AS last_view FROM events e WHERE e.event_type = 'purchase'")(
    lambda s, d: joins.asof_join(_EV(s, d).filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), _EV(s, d).filter("event_type = 'view'").select("user_id", "ts", "value", F.col("event_id").alias("tie")), "user_id", "ts", "ts", "value", "last_view", "tie").select("event_id", "last_view")
)
query("interval_join_user_day", "SELECT user_id, strftime(day, '%Y-%m-%d') AS day, count(*)::BIGINT AS n FROM (SELECT e.user_id, d.day FROM events e JOIN (SELECT DISTINCT user_id, ts::DATE AS day FROM events) d ON d.user_id = e.user_id AND e.ts >= d.day AND e.ts < d.day + 1) GROUP BY 1, 2")(
    lambda s, d: joins.interval_join(_EV(s, d).select("event_id", "user_id", "ts"), _EV(s, d).select("user_id", F.to_date("ts").alias("day")).distinct().withColumn("start", F.col("day").cast("timestamp_ntz")).withColumn("end", F.date_add("day", 1).cast("timestamp_ntz")), ["user_id"], "ts", "start", "end").groupBy("user_id", F.date_format("day", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"))
)
query("sibling_orders", "SELECT o_orderkey, (n - 1)::BIGINT AS n_siblings, round(CASE WHEN n > 1 THEN (t - o_totalprice) / (n - 1) END, 6) AS mean_siblings FROM orders JOIN (SELECT o_custkey AS c, count(*) AS n, sum(o_totalprice) AS t FROM orders GROUP BY 1) ON c = o_custkey")(
    lambda s, d: joins.siblings(tab(s, d, "orders"), "o_orderkey", "o_custkey", "o_totalprice").withColumn("mean_siblings", F.round("mean_siblings", 6))
)
query("contains_benchmark", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")(
    lambda s, d: joins.contains_join(tab(s, d, "documents").select("doc_id", "text"), "text", tab(s, d, "benchmark").select("item_id", F.col("text").alias("needle")), "needle").select("doc_id", "item_id")
)
query("orphans_customer_events", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)")(lambda s, d: joins.orphans(tab(s, d, "customer").select("c_custkey"), _EV(s, d), "c_custkey", "user_id"))
query("restrict_to_active", "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT user_id FROM events)")(lambda s, d: joins.restrict_to(tab(s, d, "orders").select("o_orderkey", "o_custkey"), _EV(s, d), "o_custkey", "user_id").select("o_orderkey"))
query("lookup_orders_segment", "SELECT c_mktsegment, count(*)::BIGINT AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 1")(
    lambda s, d: joins.lookup(tab(s, d, "orders").select("o_custkey"), tab(s, d, "customer").select("c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"), "inner").groupBy("c_mktsegment").agg(F.count("*").alias("n"))
)
query("topk_per_customer", "SELECT o_custkey, o_orderkey, rn::BIGINT AS rn FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")(
    lambda s, d: analytics.topk_per(tab(s, d, "orders"), "o_custkey", [F.desc("o_totalprice"), F.asc("o_orderkey")], 3).select("o_custkey", "o_orderkey", F.col("rn").cast("long").alias("rn"))
)
query("topk_orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda s, d: analytics.topk(tab(s, d, "orders").select("o_orderkey", "o_totalprice"), [F.desc("o_totalprice"), F.asc("o_orderkey")], 20))
query("rank_lineitems", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM lineitem WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_quantity, l_linenumber, l_partkey, l_suppkey), v AS (PARTITION BY l_orderkey ORDER BY l_quantity)")(
    lambda s, d: analytics.rank_in_group(tab(s, d, "lineitem"), "l_orderkey", [F.col("l_quantity")], ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"], [F.col(c) for c in ("l_linenumber", "l_partkey", "l_suppkey")])
)
query("join_hints_orders", " UNION ALL ".join(f"SELECT '{h}' AS hint, c_mktsegment, count(*)::BIGINT AS n FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY 2" for h in joins.HINTS))(
    lambda s, d: _hints(s, d)
)


def _hints(s, d):
    o, c, out = tab(s, d, "orders").select("o_custkey"), tab(s, d, "customer").select("c_custkey", "c_mktsegment"), None
    for h in joins.HINTS:
        r = joins.hinted(o, c, F.col("o_custkey") == F.col("c_custkey"), h, keys=("o_custkey", "c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")).select(F.lit(h).alias("hint"), "c_mktsegment", "n")
        out = r if out is None else out.unionByName(r)
    return out


query(
    "cogroup_orders_events",
    "SELECT coalesce(o_custkey, user_id) AS key, coalesce(a, 0)::BIGINT AS n_left, coalesce(b, 0)::BIGINT AS n_right, CASE WHEN b > 0 AND a > 0 THEN round(t / v, 6) END AS ratio FROM (SELECT o_custkey, count(*) AS a, sum(o_totalprice) AS t FROM orders GROUP BY 1) FULL JOIN (SELECT user_id, count(*) AS b, sum(value) AS v FROM events GROUP BY 1) ON o_custkey = user_id",
)(lambda s, d: analytics.cogroup_ratio(tab(s, d, "orders").select(F.col("o_custkey").alias("key"), F.col("o_totalprice").alias("x")), tab(s, d, "events").select(F.col("user_id").alias("key"), F.col("value").alias("x"))))
query(
    "stratified_orders",
    "SELECT o_orderkey, o_orderstatus FROM orders WHERE ('0x' || substr(md5('0:' || o_orderkey), 1, 8))::BIGINT % 10000 < CASE o_orderstatus WHEN 'F' THEN 1000 WHEN 'O' THEN 500 ELSE 10000 END",
)(lambda s, d: analytics.stratified_sample(tab(s, d, "orders").select("o_orderkey", "o_orderstatus"), "o_orderkey", "o_orderstatus", {"F": 0.1, "O": 0.05}, 1.0))
query("cube_segments", "SELECT coalesce(o_orderstatus, '*') AS st, coalesce(o_orderpriority, '*') AS pr, count(*)::BIGINT AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(
    lambda s, d: analytics.cube_report(tab(s, d, "orders"), ["o_orderstatus", "o_orderpriority"], [F.count("*").alias("n")]).select(F.coalesce("o_orderstatus", F.lit("*")).alias("st"), F.coalesce("o_orderpriority", F.lit("*")).alias("pr"), "n")
)
query("pivot_event_types", "SELECT user_id, sum((event_type = 'click')::INT)::BIGINT AS click, sum((event_type = 'view')::INT)::BIGINT AS view, sum((event_type = 'purchase')::INT)::BIGINT AS purchase FROM events GROUP BY 1")(lambda s, d: analytics.pivot_counts(_EV(s, d), "user_id", "event_type", ["click", "view", "purchase"]))
query("filtered_counts_events", "SELECT user_id, sum((event_type = 'click')::INT)::BIGINT AS clicks, sum((value > 50)::INT)::BIGINT AS high FROM events GROUP BY 1")(
    lambda s, d: analytics.agg_where(_EV(s, d), "user_id", {"clicks": F.col("event_type") == "click", "high": F.col("value") > 50})
)
_SET = {"union": "UNION", "intersect": "INTERSECT", "except": "EXCEPT", "union_all": "UNION ALL", "intersect_all": "INTERSECT ALL", "except_all": "EXCEPT ALL"}
query("set_ops_parts", " UNION ALL ".join(f"SELECT '{n}' AS op, count(*)::BIGINT AS n FROM (SELECT l_partkey FROM lineitem WHERE l_quantity < 25 {q} SELECT l_partkey FROM lineitem WHERE l_tax > 0.04)" for n, q in _SET.items()))(lambda s, d: _sets(s, d))


def _sets(s, d):
    li, out = tab(s, d, "lineitem"), None
    for n, df in analytics.set_ops(li.filter("l_quantity < 25").select("l_partkey"), li.filter("l_tax > 0.04").select("l_partkey")).items():
        r = df.agg(F.lit(n).alias("op"), F.count("*").alias("n"))
        out = r if out is None else out.unionByName(r)
    return out


query("nunique_parts", "SELECT l_orderkey, count(DISTINCT l_partkey)::BIGINT AS n_distinct FROM lineitem GROUP BY 1")(lambda s, d: analytics.nunique(tab(s, d, "lineitem"), "l_orderkey", "l_partkey"))
query("quantiles_orders", "SELECT round(quantile_cont(o_totalprice, 0.25), 4) AS q_250, round(quantile_cont(o_totalprice, 0.5), 4) AS q_500 FROM orders")(
    lambda s, d: (lambda q: q.select(*[F.round(c, 4).alias(c) for c in q.columns]))(analytics.quantiles(tab(s, d, "orders"), "o_totalprice", [0.25, 0.5]))
)
query("latest_event", "SELECT user_id, arg_max(event_type, (ts, event_id)) AS latest FROM events GROUP BY 1")(lambda s, d: analytics.latest_value(_EV(s, d), "user_id", "ts", "event_type", "event_id"))
query("event_gaps", "SELECT event_id, user_id, coalesce((epoch_us(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) // 1000000)::BIGINT, -1) AS gap_s FROM events")(lambda s, d: analytics.lag_lead(_EV(s, d), "user_id", "ts", "event_id").withColumn("gap_s", F.coalesce("gap_s", F.lit(-1))))
query("trailing_events", "SELECT event_id, user_id, count(*) OVER w AS n_trailing, round(sum(value) OVER w, 4) AS sum_trailing FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 7 DAYS PRECEDING AND CURRENT ROW)")(
    lambda s, d: analytics.trailing_agg(_EV(s, d), "user_id", "ts", "event_id", 7 * 86400, "value").withColumn("sum_trailing", F.round("sum_trailing", 4))
)
query("props_json", "SELECT event_id, (props->>'k')::BIGINT AS k FROM events")(lambda s, d: analytics.props_fields(_EV(s, d).select("event_id", "props"), "props", "k bigint").drop("props"))
query("text_stats_documents", "SELECT doc_id, length(text)::BIGINT AS n_chars_t, len(regexp_extract_all(text, '[^ \\n\\t]+'))::BIGINT AS n_words, (length(text) - length(replace(text, chr(10), '')) + 1)::BIGINT AS n_lines, round(len(regexp_extract_all(text, '[0-9]')) / greatest(length(text), 1), 6) AS digit_share, round(len(regexp_extract_all(text, '[A-Z]')) / greatest(length(text), 1), 6) AS upper_share FROM documents")(
    lambda s, d: (lambda st: tab(s, d, "documents").select("doc_id", st["n_chars_t"].alias("n_chars_t"), st["n_words"].alias("n_words"), st["n_lines"].alias("n_lines"), F.round(st["digit_share"], 6).alias("digit_share"), F.round(st["upper_share"], 6).alias("upper_share")))(features.text_stats("text"))
)
query("host_stats_pages", "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*)::BIGINT AS n FROM pages GROUP BY 1")(lambda s, d: tab(s, d, "pages").groupBy(F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("n")))
query("vec_norm_embeddings", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, round(list_sum(list_transform(embedding, lambda x: greatest(x, 0)::DOUBLE)), 5) AS relu_sum FROM embeddings")(
    lambda s, d: tab(s, d, "embeddings").select("vec_id", F.round(analytics.vec_dot("embedding", "embedding"), 5).alias("norm2"), F.round(F.aggregate(analytics.vec_relu("embedding"), F.lit(0.0), lambda a, x: a + x), 5).alias("relu_sum"))
)
query("salted_supplier", "SELECT l_suppkey, count(*)::BIGINT AS n, sum(l_quantity) AS total, min(l_quantity) AS low, max(l_quantity) AS high FROM lineitem GROUP BY 1")(lambda s, d: aggregate.salted_agg(tab(s, d, "lineitem"), "l_suppkey", "l_quantity"))
query("sample_orders", "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5('0:' || o_orderkey), 1, 8))::BIGINT % 10000 < 1000")(lambda s, d: analytics.sample_rows(tab(s, d, "orders").select("o_orderkey"), "o_orderkey", 0.1))
query("compare_frames_orders", "SELECT 0::BIGINT AS only_left, (SELECT count(*) FROM orders WHERE o_orderkey % 2 = 1)::BIGINT AS only_right, 0::BIGINT AS differing")(
    lambda s, d: (lambda o: joins.compare_frames(o.filter("o_orderkey % 2 = 0"), o, "o_orderkey", ["o_custkey", "o_totalprice"]))(tab(s, d, "orders"))
)
query("date_diffs_lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::BIGINT AS days FROM lineitem JOIN orders ON o_orderkey = l_orderkey")(
    lambda s, d: tab(s, d, "lineitem").join(tab(s, d, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", analytics.date_diffs("o_orderdate", "l_shipdate")["days"].alias("days"))
)

# Streams: what is there is processed once; the result equals the batch result.


def _stream(build, sql):
    def run(s, d):
        import uuid

        from .ops import streaming

        base = streaming.shared_folder(s)
        schema = _EV(s, d).schema
        df = build(streaming, streaming.stream_table(s, f"{d}/events*.parquet", schema, "ts"))
        return streaming.run_available(df, f"q_{uuid.uuid4().hex}", "complete", f"{base}/stream-{uuid.uuid4().hex}")

    return run, sql


for _name, _build, _sql in (
    ("stream_tumbling", lambda st, df: st.windowed_features(df, "event_type", "ts", "value").select("event_type", F.date_format("start", "yyyy-MM-dd").alias("day"), "n", F.round("total", 4).alias("total")), "SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2"),
    ("stream_sliding", lambda st, df: st.windowed_features(df, "event_type", "ts", "value", "sliding", "2 days", "1 day").select("event_type", F.date_format("start", "yyyy-MM-dd").alias("day"), "n"), "SELECT event_type, strftime(d, '%Y-%m-%d') AS day, count(*)::BIGINT AS n FROM (SELECT event_type, unnest([ts::DATE, (ts::DATE - INTERVAL 1 DAY)::DATE]) AS d FROM events) GROUP BY 1, 2"),
    ("stream_session", lambda st, df: st.windowed_features(df, "user_id", "ts", "value", "session", "12 hours").select("user_id", "n", F.unix_timestamp("start").alias("start_s")), "SELECT user_id, count(*)::BIGINT AS n, floor(epoch(min(ts)))::BIGINT AS start_s FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sess FROM (SELECT user_id, ts, (coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 12 HOURS, true))::INT AS new FROM events)) GROUP BY user_id, sess"),
    ("stream_neighbour_stats", lambda st, df: st.incremental_stats(df, "user_id", "value").select("key", "n", F.round("total", 4).alias("total"), "low", "high"), "SELECT user_id AS key, count(*)::BIGINT AS n, round(sum(value), 4) AS total, min(value) AS low, max(value) AS high FROM events GROUP BY 1"),
):
    _run, _text = _stream(_build, _sql)
    query(_name, _text)(_run)


@query("stream_dedup", "SELECT count(DISTINCT event_id)::BIGINT AS n FROM events")
def stream_dedup(s, d):
    import uuid

    from .ops import streaming

    base = streaming.shared_folder(s)
    df = streaming.stream_table(s, f"{d}/events*.parquet", _EV(s, d).schema, "ts", "400 days")
    run = f"{base}/stream-{uuid.uuid4().hex}"
    got = streaming.run_to_files(streaming.dedup_stream(df, "event_id").select("event_id"), f"{run}/rows", f"{run}/state")
    return got.agg(F.count("*").alias("n"))


# Learned runs: too long for SQL; the tests hold them against bounds.


def _reports(make):
    def run(s, d):
        return values(s, [r.row() for r in make(s, d)], metrics.RunReport.SCHEMA)

    return run


def _experiments(name: str, **more):
    def run(s, d):
        from . import experiments

        return experiments.QUERY[name](s, d, **more)

    return run


for _name in ("train_order_sensitivity", "train_rep_orders", "train_baselines_orders", "train_rowgnn_orders", "ablation_rowblock", "ablation_basemodel", "ablation_aggregator", "train_flat_ml_heads", "train_user_day", "train_seen", "depth_sweep"):
    query(_name)(_reports(_experiments(_name)))
query("table_widths")(lambda s, d: (lambda cat: values(s, [(t, k, *rollup.width_report(cat, t, k, 16)) for t in ("orders", "customer") for k in (1, 2, 3)], "target string, depth long, rollup_columns long, propagation_vectors long"))(graph.live(star_catalog(s, d))))


def tables_of(spark: SparkSession, folder: str) -> dict[str, DataFrame]:
    return read_tables(spark, folder, CAT_ALL)
