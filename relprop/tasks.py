"""Prediction tasks over the given tables: stand-ins for the synthetic and the real databases."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .features import text_stats
from .schema import STAR_FKS, STAR_SPECS, Catalog, ForeignKey, TableSpec, Task, dated, kept, read_dated, read_tables, star_catalog

#: Dates are features of every task, as four categories.
SPEC = {s.name: dated(s) for s in STAR_SPECS}


#: Ranges into which values are cut for ranks and medians; one row a range is collected.
RANGES = 256


def ranged(df: DataFrame, value: str) -> tuple[DataFrame, list]:
    """v, n (rows), part of each distinct value, parts being ranges in order; and (part, rows) of each part, in order.

    The bounds are approximate quantiles, fixed before anything is cut by them, so a part is the same whenever it is read.
    """
    counts = df.filter(F.col(value).isNotNull()).groupBy(F.col(value).alias("v")).agg(F.count("*").alias("n"))
    bounds = counts.agg(F.percentile_approx("v", [i / RANGES for i in range(1, RANGES)], 10_000)).first()[0] or []
    cut = counts.withColumn("part", _part_of(F.col("v"), sorted(set(bounds))))
    sizes = sorted((r["part"], r["s"]) for r in cut.groupBy("part").agg(F.sum("n").alias("s")).collect())
    return cut, sizes


def _part_of(v: Column, bounds: list) -> Column:
    """How many bounds are not above a value, looked for among every 16th bound and then among 16."""
    if not bounds:
        return F.lit(0)
    upto = lambda cuts: F.size(F.filter(cuts, lambda b: b <= v))
    few = [F.array(*[F.lit(b) for b in bounds[i : i + 16]]) for i in range(0, len(bounds), 16)]
    full = upto(F.array(*[F.lit(b) for b in bounds[15::16]])) if len(bounds) > 15 else F.lit(0)
    return full * 16 + F.coalesce(upto(F.get(F.array(*few), full)), F.lit(0))


def median_of(df: DataFrame, column: str) -> float | None:
    """Exact median: the two middle rows lie in one range or two, and only these are put in order."""
    cut, sizes = ranged(df, column)
    total = sum(s for _, s in sizes)
    if not total:
        return None
    middle = ((total - 1) // 2, total // 2)
    found, before = {}, 0
    for part, size in sizes:
        for m in set(middle):
            if before <= m < before + size:
                w = W.orderBy("v").rowsBetween(W.unboundedPreceding, 0)
                inside = cut.filter(F.col("part") == part).withColumn("upto", F.sum("n").over(w))
                found[m] = inside.filter(F.col("upto") > m - before).agg(F.min("v")).first()[0]
        before += size
    return 0.5 * found[middle[0]] + 0.5 * found[middle[1]] if middle[0] != middle[1] else found[middle[0]]


def percent_rank_of(df: DataFrame, key: str, value: str, out: str) -> DataFrame:
    """key, out: percent_rank by value.  Ranks of distinct values are counts below, summed by range."""
    cut, sizes = ranged(df, value)
    before, offset = 0, F.lit(0)
    starts = []
    for part, size in sizes:
        starts.append((part, before))
        before += size
    if starts:
        offset = F.element_at(F.create_map(*[x for p, b in starts for x in (F.lit(p), F.lit(b))]), F.col("part"))
    below = F.coalesce(F.sum("n").over(W.partitionBy("part").orderBy("v").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    ranks = cut.withColumn("below", below).select("v", (F.col("below") + offset).alias("r"))
    return df.join(ranks, F.col(value) == F.col("v")).select(key, (F.col("r") / F.lit(float(max(1, before - 1)))).alias(out))


def purchase(spark: SparkSession, folder: str) -> Task:
    """SYN1 on given tables: a purchase knows its supplier and its buyer's nation; suppliers know theirs."""
    t = read_tables(spark, folder, ["lineitem", "orders", "customer", "supplier", "nation"])
    a = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    a = a.select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_suppkey").alias("bID"), F.col("c_nationkey").alias("cID"), F.lit(1.0).alias("x"))
    sums = t["supplier"].groupBy(F.col("s_nationkey").alias("_n")).agg(F.sum("s_acctbal").alias("total"))
    a = a.join(F.broadcast(sums), F.col("cID") == F.col("_n"), "left").withColumn("total", F.coalesce("total", F.lit(0.0)))  # a row a nation
    tau = median_of(a, "total")
    a = a.withColumn("label", (F.col("total") >= tau).cast("int")).drop("_n", "total")
    specs = [TableSpec("purchase", ("l_orderkey", "l_linenumber", "l_partkey", "bID"), ("x",)), TableSpec("supplier", ("s_suppkey",), ("s_acctbal",)), TableSpec("nation", ("n_nationkey",))]
    fks = [ForeignKey("purchase", "bID", "supplier"), ForeignKey("purchase", "cID", "nation"), ForeignKey("supplier", "s_nationkey", "nation")]
    return Task(Catalog.build(specs, fks, {"purchase": a, "supplier": t["supplier"], "nation": t["nation"]}), "purchase", name="purchase")


PURCHASE_ORDERS = (["purchase.cID", "supplier.s_nationkey", "purchase.bID"], ["purchase.bID", "supplier.s_nationkey", "purchase.cID"])


def pair(spark: SparkSession, folder: str) -> Task:
    """SYN2 on given tables: pairs of supplier and part; lineitems tie the two in another way."""
    t = read_tables(spark, folder, ["lineitem", "supplier", "part"])
    line = t["lineitem"].select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    a = line.select(F.col("l_suppkey").alias("cID"), F.col("l_partkey").alias("dID")).distinct().withColumn("x", F.lit(1.0))
    sums = line.join(t["part"], F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("l_suppkey").alias("_c")).agg(F.sum("p_retailprice").alias("total"))
    a = a.join(sums, F.col("cID") == F.col("_c"))
    tau = median_of(a, "total")
    a = a.withColumn("label", (F.col("total") >= tau).cast("int")).drop("_c", "total")
    specs = [TableSpec("pair", ("cID", "dID"), ("x",)), TableSpec("line", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")), TableSpec("supplier", ("s_suppkey",), ("one",)), TableSpec("part", ("p_partkey",), ("p_retailprice",))]
    fks = [ForeignKey("pair", "cID", "supplier"), ForeignKey("pair", "dID", "part"), ForeignKey("line", "l_suppkey", "supplier"), ForeignKey("line", "l_partkey", "part")]
    return Task(Catalog.build(specs, fks, {"pair": a, "line": line, "supplier": t["supplier"].withColumn("one", F.lit(1.0)), "part": t["part"]}), "pair", name="pair")


PAIR_ORDERS = (["pair.cID", "line.l_suppkey", "line.l_partkey", "pair.dID"], ["pair.dID", "line.l_partkey", "line.l_suppkey", "pair.cID"])


def planted(df: DataFrame, key: str, first: str, second: str) -> DataFrame:
    """key, label: 1 iff the sum of two percent ranks is its median or more.  The rows and their ranks are worked out once."""
    df = df.select(key, first, second).persist()
    a, b = percent_rank_of(df, key, first, "ra"), percent_rank_of(df, key, second, "rb")
    both = kept(a.join(b, key).select(key, (F.col("ra") + F.col("rb")).alias("r")))
    both.count()
    df.unpersist()
    return both.withColumn("label", (F.col("r") >= median_of(both, "r")).cast("int")).select(key, "label")


def orders_task(spark: SparkSession, folder: str) -> Task:
    """Shopper stand-in: an order, its buyer and its lines; the label mixes the order's revenue and the buyer's balance."""
    t = read_dated(spark, folder, ["orders", "customer", "lineitem"])
    revenue = t["lineitem"].groupBy(F.col("l_orderkey").alias("_o")).agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("rev"))
    base = t["orders"].join(revenue, F.col("o_orderkey") == F.col("_o"), "left").join(t["customer"].select("c_custkey", "c_acctbal"), F.col("o_custkey") == F.col("c_custkey"))
    base = base.select("o_orderkey", F.round(F.coalesce("rev", F.lit(0.0)), 4).alias("rev"), "c_acctbal")
    label = planted(base, "o_orderkey", "rev", "c_acctbal").withColumnRenamed("o_orderkey", "_k")
    target = t["orders"].join(label, F.col("o_orderkey") == F.col("_k")).drop("_k")
    specs = [SPEC["orders"], SPEC["customer"], SPEC["lineitem"]]
    fks = [k for k in STAR_FKS if k.name in ("orders.o_custkey", "lineitem.l_orderkey")]
    return Task(Catalog.build(specs, fks, {**t, "orders": target}), "orders", name="orders")


def control_task(spark: SparkSession, folder: str) -> Task:
    """Nothing predicts this label: the priority of an order."""
    task = orders_task(spark, folder)
    df = task.catalog.frame("orders").withColumn("label", F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").cast("int"))
    cat = task.catalog.without("orders", "o_orderpriority").with_frames({"orders": df})
    return Task(cat, "orders", name="control")


def impression_task(spark: SparkSession, folder: str) -> Task:
    """Advert stand-in: keys and label only; the buyer's region is four steps away."""
    cat = star_catalog(spark, folder, dates=True)
    f = cat.frames
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    ident = F.md5(F.concat_ws(":", *[F.col(c).cast("string") for c in key]))
    buyer = f["orders"].join(f["customer"], F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(f["nation"]), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("o_orderkey").alias("_o"), F.col("n_regionkey").alias("br"))
    seller = f["supplier"].join(F.broadcast(f["nation"]), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("_s"), F.col("n_regionkey").alias("sr"))
    mid = median_of(f["part"], "p_retailprice")
    part = f["part"].select(F.col("p_partkey").alias("_p"), (F.col("p_retailprice") > mid).alias("dear"))
    rows = f["lineitem"].join(buyer, F.col("l_orderkey") == F.col("_o")).join(seller, F.col("l_suppkey") == F.col("_s")).join(part, F.col("l_partkey") == F.col("_p"))
    target = rows.select(*key, ident.alias("imp_id"), ((F.col("br") == F.col("sr")) | F.col("dear")).cast("int").alias("label"))
    detail = f["lineitem"].select(ident.alias("imp_id"), *SPEC["lineitem"].features)
    specs = [s for n, s in SPEC.items() if n != "lineitem"] + [TableSpec("impression", ("imp_id",)), TableSpec("line_detail", ("imp_id",), SPEC["lineitem"].numeric, SPEC["lineitem"].categorical, SPEC["lineitem"].domains)]
    fks = [ForeignKey("impression", k.column, k.dst) if k.src == "lineitem" else k for k in STAR_FKS] + [ForeignKey("line_detail", "imp_id", "impression")]
    return Task(Catalog.build(specs, fks, {**f, "impression": target, "line_detail": detail}), "impression", ratios=(0.95, 0.025, 0.025), name="impression")


def seen_task(spark: SparkSession, folder: str) -> Task:
    """Search stand-in: pairs of a buyer with events and a part; the label mixes click share and the part's popularity."""
    t = read_dated(spark, folder, ["customer", "events", "orders", "lineitem", "part"])
    clicks = t["events"].groupBy(F.col("user_id").alias("_u")).agg(F.avg((F.col("event_type") == "click").cast("double")).alias("share"))
    popular = t["lineitem"].groupBy(F.col("l_partkey").alias("_p")).agg(F.count("*").alias("lines"))
    bought = t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(clicks, F.col("o_custkey") == F.col("_u")).select(F.col("o_custkey").alias("user_id"), "l_partkey", F.round("share", 9).alias("share")).distinct()
    rows = bought.join(popular, F.col("l_partkey") == F.col("_p")).drop("_p").withColumn("seen_id", F.col("user_id") * 100_000_000 + F.col("l_partkey"))
    label = planted(rows, "seen_id", "share", "lines").withColumnRenamed("seen_id", "_k")
    target = rows.join(label, F.col("seen_id") == F.col("_k")).select("seen_id", "user_id", "l_partkey", "label")
    specs = [TableSpec("seen", ("seen_id",)), *[SPEC[n] for n in ("customer", "events", "orders", "lineitem", "part")]]
    fks = [ForeignKey("seen", "user_id", "customer"), ForeignKey("seen", "l_partkey", "part"), *[k for k in STAR_FKS if k.name in ("events.user_id", "orders.o_custkey", "lineitem.l_orderkey", "lineitem.l_partkey")]]
    return Task(Catalog.build(specs, fks, {**t, "seen": target}), "seen", ratios=(0.956, 0.022, 0.022), name="seen")


def user_day_task(spark: SparkSession, folder: str, as_of: int | None = None) -> Task:
    """Drop-out stand-in: a user's day with events; the label is 1 iff the next day has none.

    ``as_of`` keeps what is known at the end of that day of the month; days after it would give the label away.
    """
    t = read_dated(spark, folder, ["events", "customer", "nation"])
    ev = t["events"].withColumn("day", F.to_date("ts")).withColumn("ud_id", F.col("user_id") * 100 + F.dayofmonth("ts"))
    days = ev.select("ud_id", "user_id", "day").distinct()
    nxt = days.select(F.col("user_id").alias("_u"), F.date_sub("day", 1).alias("_d"))
    rows = days.join(nxt, (F.col("user_id") == F.col("_u")) & (F.col("day") == F.col("_d")), "left").withColumn("label", F.col("_u").isNull().cast("int")).drop("_u", "_d")
    rows = rows.filter(F.col("day") < F.lit("2024-01-30").cast("date"))
    if as_of is not None:
        rows, ev = rows.filter(F.dayofmonth("day") <= as_of), ev.filter(F.dayofmonth("day") <= as_of)
    specs = [TableSpec("user_day", ("ud_id",)), SPEC["events"], SPEC["customer"], SPEC["nation"]]
    fks = [ForeignKey("user_day", "user_id", "customer"), ForeignKey("events", "ud_id", "user_day"), ForeignKey("customer", "c_nationkey", "nation")]
    return Task(Catalog.build(specs, fks, {**t, "events": ev, "user_day": rows.drop("day")}), "user_day", name="user_day")


def buyer_task(spark: SparkSession, folder: str) -> Task:
    """Big buyers: the total price of a customer's order lines is the median or more; two steps back."""
    cat = star_catalog(spark, folder, ["customer", "orders", "lineitem"], dates=True)
    f = cat.frames
    total = f["orders"].join(f["lineitem"], F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_custkey").alias("_c")).agg(F.sum("l_extendedprice").alias("total"))
    rows = f["customer"].join(total, F.col("c_custkey") == F.col("_c"), "left").withColumn("total", F.round(F.coalesce("total", F.lit(0.0)), 4))
    rows = rows.withColumn("label", (F.col("total") >= median_of(rows, "total")).cast("int")).drop("_c", "total")
    return Task(cat.with_frames({"customer": rows}), "customer", name="buyer")


def touch_task(spark: SparkSession, folder: str) -> Task:
    """Interaction motif: an event refers to a user and to an order whose buyer is another user."""
    t = read_dated(spark, folder, ["events", "orders", "customer"])
    n = t["orders"].count()
    ev = t["events"].withColumn("order_ref", F.col("event_id") % n).withColumn("label", (F.col("event_type") == "purchase").cast("int"))
    specs = [TableSpec("events", ("event_id",), ("value",)), SPEC["orders"], SPEC["customer"]]
    fks = [ForeignKey("events", "user_id", "customer"), ForeignKey("events", "order_ref", "orders"), ForeignKey("orders", "o_custkey", "customer")]
    return Task(Catalog.build(specs, fks, {**t, "events": ev}), "events", name="touch")


def text_columns(df: DataFrame, column: str) -> tuple[DataFrame, list[str]]:
    stats: dict[str, Column] = text_stats(column)
    return df.withColumns(stats), list(stats)


def document_task(spark: SparkSession, folder: str, label: str = "quality", bridge: bool = False) -> Task:
    """Labels of documents, from figures of their text and the rows that share language, source or text.

    ``bridge``: further the passages of the benchmark that a document holds, as rows between the two.
    """
    t = read_tables(spark, folder, ["labels", "documents", *(["benchmark"] if bridge else [])])
    docs, stats = text_columns(t["documents"], "text")
    docs = docs.withColumn("group_id", F.md5("text")).drop("text")
    dims = {n: docs.select(F.col(c).alias(n)).distinct() for n, c in (("lang_key", "lang"), ("source_key", "source"), ("group_key", "group_id"))}
    rows = t["labels"].select(F.col("doc_id").alias("label_id"), "doc_id", F.col(label).alias("label"))
    specs = [TableSpec("labels", ("label_id",)), TableSpec("documents", ("doc_id",), tuple(stats)), TableSpec("langs", ("lang_key",)), TableSpec("sources", ("source_key",)), TableSpec("groups", ("group_key",))]
    fks = [ForeignKey("labels", "doc_id", "documents"), ForeignKey("documents", "lang", "langs"), ForeignKey("documents", "source", "sources"), ForeignKey("documents", "group_id", "groups")]
    frames = {"labels": rows, "documents": docs, "langs": dims["lang_key"], "sources": dims["source_key"], "groups": dims["group_key"]}
    if bridge:
        from .ops.joins import contains_join

        held = contains_join(t["documents"].select(F.col("doc_id").alias("held_doc"), "text"), "text", t["benchmark"].select("item_id", F.col("text").alias("needle")), "needle")
        frames["passages"] = held.select(F.concat_ws(":", "held_doc", "item_id").alias("passage_id"), "held_doc", F.col("item_id").alias("held_item"))
        frames["benchmark"], items = text_columns(t["benchmark"], "text")
        specs += [TableSpec("passages", ("passage_id",)), TableSpec("benchmark", ("item_id",), tuple(items))]
        fks += [ForeignKey("passages", "held_doc", "documents"), ForeignKey("passages", "held_item", "benchmark")]
    return Task(Catalog.build(specs, fks, frames), "labels", name=f"document_{label}")


def role_task(spark: SparkSession, folder: str) -> Task:
    """Turns of conversations: is it the assistant's?  Roles of the other turns are no features."""
    df, stats = text_columns(read_tables(spark, folder, ["conversations"])["conversations"], "text")
    df = df.withColumn("turn_id", F.col("conv_id") * 10_000 + F.col("turn")).withColumn("label", (F.col("role") == "assistant").cast("int")).drop("text")
    df = df.withColumn("place", F.col("turn").cast("double"))
    convs = df.select("conv_id").distinct().withColumnRenamed("conv_id", "conv_key")
    specs = [TableSpec("turns", ("turn_id",), ("place", *stats)), TableSpec("convs", ("conv_key",))]
    return Task(Catalog.build(specs, [ForeignKey("turns", "conv_id", "convs")], {"turns": df, "convs": convs}), "turns", name="role")


PAGE_LANGS = ("de", "en", "es", "fr")


def page_task(spark: SparkSession, folder: str, lang: str | None = "en") -> Task:
    """Language of a page, from its markup with the language attribute taken out, and the pages of its host.

    ``lang``: is it this one?  None: which of PAGE_LANGS is it, pages of others left out.
    """
    df = read_tables(spark, folder, ["pages"])["pages"]
    own = F.regexp_extract("html", r'<html lang="([a-z]+)"', 1)
    label = (own == lang).cast("int") if lang else F.array_position(F.array(*map(F.lit, PAGE_LANGS)), own).cast("int") - 1
    df = df.withColumn("label", label).filter("label >= 0").withColumn("html", F.regexp_replace("html", r'<html lang="[a-z]+"', "<html"))
    df = df.withColumn("host", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1))
    df, stats = text_columns(df, "html")
    df = df.select("page_id", "host", "label", *stats)
    specs = [TableSpec("pages", ("page_id",), tuple(stats)), TableSpec("hosts", ("host_key",))]
    cat = Catalog.build(specs, [ForeignKey("pages", "host", "hosts")], {"pages": df, "hosts": df.select(F.col("host").alias("host_key")).distinct()})
    return Task(cat, "pages", name="page") if lang else Task(cat, "pages", kind="multiclass", classes=len(PAGE_LANGS), name="page_langs")


def vector_task(spark: SparkSession, folder: str, label: int | None = 0, classes: int = 10) -> Task:
    """One table: is this vector of class ``label``?  None: of which of ``classes``?"""
    from .features import vector_fields

    df = vector_fields(read_tables(spark, folder, ["embeddings"])["embeddings"].withColumnRenamed("label", "cls"), "embedding", 64)
    df = df.withColumn("label", (F.col("cls") == label).cast("int") if label is not None else F.col("cls").cast("int")).drop("embedding", "cls")
    cat = Catalog.build([TableSpec("embeddings", ("vec_id",), tuple(f"v_{j}" for j in range(64)))], [], {"embeddings": df})
    return Task(cat, "embeddings", name="vector") if label is not None else Task(cat, "embeddings", kind="multiclass", classes=classes, name="vector_classes")


TASKS = {
    "purchase": purchase, "pair": pair, "orders": orders_task, "control": control_task, "impression": impression_task, "seen": seen_task, "user_day": user_day_task,
    "buyer": buyer_task, "touch": touch_task, "quality": document_task, "toxic": lambda s, f: document_task(s, f, "toxic", True), "page_langs": lambda s, f: page_task(s, f, None), "vector_classes": lambda s, f: vector_task(s, f, None), "role": role_task, "page": page_task, "vector": vector_task,
}
