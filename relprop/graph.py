"""The graph of a catalog: nodes, edges, degrees, statistics, schema walks and K-hop subgraphs."""

from __future__ import annotations

from collections import Counter, deque
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schema import Catalog


def node_key(columns: tuple[str, ...]) -> Column:
    """One string for a key of any width; of several columns, slashes within a value are escaped and null is a sign of its own."""
    if len(columns) == 1:
        return F.col(columns[0]).cast("string")
    parts = [F.coalesce(F.replace(F.replace(F.col(c).cast("string"), F.lit("\\"), F.lit("\\\\")), F.lit("/"), F.lit("\\/")), F.lit("\\N")) for c in columns]
    return F.concat_ws("/", *parts)


def nodes(catalog: Catalog) -> DataFrame:
    """ntype, key, feat (map of the features as text)."""
    parts = []
    for name, spec in catalog.specs.items():
        pairs = [x for c in spec.features for x in (F.lit(c), F.col(c).cast("string"))]
        feat = F.create_map(*pairs) if pairs else F.create_map().cast("map<string,string>")
        parts.append(catalog.frame(name).select(F.lit(name).alias("ntype"), node_key(spec.key).alias("key"), feat.alias("feat")))
    return reduce(DataFrame.unionByName, parts)


def edges(catalog: Catalog, reverse: bool = True) -> DataFrame:
    """etype, dir (forward or backward), src, dst.  Null references give no edge."""
    parts = []
    for fk in catalog.fks:
        df = catalog.frame(fk.src).filter(F.col(fk.column).isNotNull())
        a, b = node_key(catalog.key(fk.src)), F.col(fk.column).cast("string")
        parts.append(df.select(F.lit(fk.name).alias("etype"), F.lit("forward").alias("dir"), a.alias("src"), b.alias("dst")))
        if reverse:
            parts.append(df.select(F.lit(fk.name).alias("etype"), F.lit("backward").alias("dir"), b.alias("src"), a.alias("dst")))
    return reduce(DataFrame.unionByName, parts)


def degrees(catalog: Catalog, fk_name: str) -> DataFrame:
    """key, deg: how many rows refer to each row of the referenced table; zeros are kept."""
    fk = next(k for k in catalog.fks if k.name == fk_name)
    n = catalog.frame(fk.src).groupBy(F.col(fk.column).alias("_fk")).agg(F.count("*").alias("_n"))
    key = catalog.key(fk.dst)[0]
    return catalog.frame(fk.dst).select(F.col(key).alias("key")).join(n, F.col("key") == F.col("_fk"), "left").select("key", F.coalesce("_n", F.lit(0)).cast("long").alias("deg"))


def graph_stats(catalog: Catalog) -> DataFrame:
    """kind, name, n, max_degree, mean_degree: a row for each table and each edge type."""
    parts = [catalog.frame(t).agg(F.lit("table").alias("kind"), F.lit(t).alias("name"), F.count("*").alias("n"), F.lit(None).cast("long").alias("max_degree"), F.lit(None).cast("double").alias("mean_degree")) for t in catalog.specs]
    for fk in catalog.fks:
        parts.append(degrees(catalog, fk.name).agg(F.lit("edge").alias("kind"), F.lit(fk.name).alias("name"), F.sum("deg").alias("n"), F.max("deg").alias("max_degree"), F.avg("deg").alias("mean_degree")))
    return reduce(DataFrame.unionByName, [p.select("kind", "name", "n", "max_degree", "mean_degree") for p in parts])


def live(catalog: Catalog) -> Catalog:
    """The catalog without foreign keys that no row uses and features without a value; each table is read once."""
    specs, used = [], set()
    for name, spec in catalog.specs.items():
        out = {k.column for k in catalog.forward(name)}
        seen = [*spec.features, *(c for c in sorted(out) if c not in spec.features)]
        has = catalog.frame(name).agg(*[F.count(F.col(f"`{c}`")).alias(f"n{i}") for i, c in enumerate(seen)]).first() if seen else ()
        full = {c for c, n in zip(seen, has, strict=True) if n}
        specs.append(replace(spec, numeric=tuple(c for c in spec.numeric if c in full), categorical=tuple(c for c in spec.categorical if c in full)))
        used |= {k.name for k in catalog.forward(name) if k.column in full}
    return Catalog.build(specs, [k for k in catalog.fks if k.name in used], catalog.frames)


def steps(catalog: Catalog, table: str) -> list[tuple[str, str, str]]:
    """(foreign key, direction, table reached) of every schema step from a table."""
    return [(k.name, ">", k.dst) for k in catalog.forward(table)] + [(k.name, "<", k.src) for k in catalog.backward(table)]


def tables_reached(catalog: Catalog, target: str, depth: int) -> dict[int, int]:
    """k -> number of other tables that some path of at most k steps reaches."""
    seen, out, front = {target}, {0: 0}, {target}
    for k in range(1, depth + 1):
        front = {t for s in front for _, _, t in steps(catalog, s)} - seen
        seen |= front
        out[k] = len(seen) - 1
    return out


def walks(catalog: Catalog, target: str, depth: int) -> list[tuple[str, ...]]:
    """All walks of 1 to ``depth`` steps, as step labels; tables may repeat."""
    out, todo = [], deque([((), target)])
    while todo:
        path, at = todo.popleft()
        if path:
            out.append(path)
        if len(path) < depth:
            todo.extend((path + (fk + way,), to) for fk, way, to in steps(catalog, at))
    return out


def simple_paths(catalog: Catalog, target: str, depth: int) -> list[tuple[str, ...]]:
    """The walks that visit no table twice."""
    out, todo = [], deque([((), (target,))])
    while todo:
        path, seen = todo.popleft()
        if path:
            out.append(path)
        if len(path) < depth:
            todo.extend((path + (fk + way,), seen + (to,)) for fk, way, to in steps(catalog, seen[-1]) if to not in seen)
    return out


def khop_subgraph(catalog: Catalog, target: str, targets: DataFrame, depth: int, fanout: int | None = None) -> dict[str, DataFrame]:
    """Rows within ``depth`` hops of each batch: table -> (batch_id, its key columns, distinct).

    ``targets``: batch_id and the target's key columns.  ``fanout`` caps the children taken of a row, edge type and batch,
    by hash order; None takes all.  Each hop is one join an edge type on keys only.
    """
    reach: dict[str, DataFrame] = {target: targets.select("batch_id", *catalog.key(target)).distinct()}
    front = dict(reach)
    for _ in range(depth):
        new: dict[str, DataFrame] = {}
        for table, keys in front.items():
            own = catalog.key(table)
            for fk in catalog.forward(table):
                rows = keys.join(catalog.frame(table).select(*dict.fromkeys([*own, fk.column])), list(own))
                found = rows.filter(F.col(fk.column).isNotNull()).select("batch_id", F.col(fk.column).alias(catalog.key(fk.dst)[0]))
                new[fk.dst] = found if fk.dst not in new else new[fk.dst].unionByName(found)
            for fk in catalog.backward(table):
                kid = catalog.key(fk.src)
                child = catalog.frame(fk.src).select(*[F.col(c).alias(f"k_{c}") for c in kid], F.col(fk.column).alias("_fk"))
                rows = keys.join(child, F.col(own[0]) == F.col("_fk"))
                if fanout is not None:
                    from pyspark.sql import Window as W

                    order = [F.xxhash64(*[F.col(f"k_{c}") for c in kid]), *[F.col(f"k_{c}") for c in kid]]
                    rows = rows.withColumn("_n", F.row_number().over(W.partitionBy("batch_id", "_fk").orderBy(*order))).filter(F.col("_n") <= fanout)
                found = rows.select("batch_id", *[F.col(f"k_{c}").alias(c) for c in kid])
                new[fk.src] = found if fk.src not in new else new[fk.src].unionByName(found)
        front = {}
        for table, rows in new.items():
            rows = rows.distinct()
            cols = ["batch_id", *catalog.key(table)]
            front[table] = rows.join(reach[table], cols, "left_anti") if table in reach else rows
            reach[table] = reach[table].unionByName(front[table]) if table in reach else rows
    return reach


@dataclass
class Arrivals:
    """How the rows of a table come into reach of the batches.

    ``only``: the one foreign key along which they are all found, from the rows they refer to; None if there are others.
    ``parents``: batch_id and _key of those rows, each once.  ``keys``: batch_id and key columns, for other tables.
    """

    only: str | None
    parents: DataFrame | None = None
    keys: DataFrame | None = None


def arrivals(catalog: Catalog, target: str, targets: DataFrame, batch_of: Column, depth: int) -> dict[str, Arrivals]:
    """The rows within ``depth`` hops of each batch as ``khop_subgraph`` has them, by table, but for the targets themselves.

    ``targets``: batch_id, key and references of the target rows.  ``batch_of``: the batch of a target by its key.  Rows that
    refer to rows in reach are found once each, so they need no search for repeats; nor is a reference followed back.
    """
    out: dict[str, Arrivals] = {}
    refs = lambda t: [k.column for k in catalog.forward(t)]
    front: dict[str, tuple[DataFrame, set[str]]] = {target: (targets, set())}  # rows and the references that lead back
    for _ in range(depth):
        forward: dict[str, list[DataFrame]] = {}
        backward: dict[str, list[tuple[str, DataFrame]]] = {}
        for table, (rows, back) in front.items():
            for fk in catalog.forward(table):
                if fk.name not in back:
                    forward.setdefault(fk.dst, []).append(rows.filter(F.col(fk.column).isNotNull()).select("batch_id", F.col(fk.column).alias(catalog.key(fk.dst)[0])))
            for fk in catalog.backward(table):
                backward.setdefault(fk.src, []).append((fk.name, rows.select("batch_id", F.col(catalog.key(table)[0]).alias("_key"))))
        front = {}
        for table in dict.fromkeys([*forward, *backward]):
            own, at = list(catalog.key(table)), {k.name: k.column for k in catalog.forward(table)}
            carried = list(dict.fromkeys([*own, *refs(table)]))
            found = [(name, catalog.frame(table).select(*carried, F.col(at[name]).alias("_fk")).join(parents, F.col("_fk") == F.col("_key")).select("batch_id", *carried)) for name, parents in backward.get(table, [])]
            before = out.get(table)
            names = {name for name, _ in found} | ({before.only} if before else set())
            if table not in forward and len(names) == 1 and None not in names:
                name, rows = found[0][0], reduce(DataFrame.unionByName, [r for _, r in found])
                parents = reduce(DataFrame.unionByName, [q for _, q in backward[table]])
                if table == target:
                    rows = rows.filter(~F.coalesce(batch_of == F.col("batch_id"), F.lit(False)))
                out[table] = Arrivals(name, before.parents.unionByName(parents) if before else parents, before.keys.unionByName(rows.select("batch_id", *own)) if before else rows.select("batch_id", *own))
                front[table] = (rows, {name})
                continue
            keys = reduce(DataFrame.unionByName, [*forward.get(table, []), *[r.select("batch_id", *own) for _, r in found]]).distinct()
            if before:
                keys = keys.join(before.keys, ["batch_id", *own], "left_anti")
            if table == target:
                keys = keys.filter(~F.coalesce(batch_of == F.col("batch_id"), F.lit(False)))
            out[table] = Arrivals(None, None, before.keys.distinct().unionByName(keys) if before else keys)
            front[table] = (keys.join(catalog.frame(table).select(*carried), own) if refs(table) else keys, set())
    return out


def needed_tables(catalog: Catalog, target: str, depth: int) -> dict[int, set[str]]:
    """round -> tables whose vectors of that round are used: those a walk of depth - round + 1 steps from the target ends in."""
    need, now = {}, {target}
    for k in range(depth, 0, -1):
        now = {t for s in now for _, _, t in steps(catalog, s)}
        need[k] = now
    return need


def multiset_difference(a: list, b: list) -> tuple[list, list]:
    x, y = Counter(a), Counter(b)
    return sorted((x - y).elements()), sorted((y - x).elements())
