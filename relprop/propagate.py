"""Row-embedding propagation with column expressions.

A round gives every row of every needed table a new vector: a block over its own field vectors, the vectors of the rows
its foreign keys point to, and one vector for each relation pointing at it, a linear map of mean, maximum and minimum of
the referring rows' vectors under three degree scalers.  Vectors begin as zero, so the first round joins nothing.
Parameters are shared by all rounds, by all rows of a table and by all edges of a type.

This engine keeps everything in JVM expressions; it is meant for small widths.  ``model`` and ``layers`` hold learned models.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .aggregate import STATS, delta_of, neighbour_stats, scalers
from .features import MinMaxCodec, feature_columns
from .graph import degrees, needed_tables
from .params import LatticeParams
from .schema import Catalog


@dataclass
class Fitted:
    """What is learned from data before any round: ranges of numbers, mean log degrees."""

    ranges: dict[str, MinMaxCodec] = field(default_factory=dict)
    deltas: dict[str, float] = field(default_factory=dict)

    @classmethod
    def of(cls, catalog: Catalog, tables: set[str] | None = None) -> Fitted:
        out = cls()
        for t in tables or catalog.specs:
            nums = [c for c in feature_columns(catalog, t) if c in catalog.specs[t].numeric]
            out.ranges[t] = MinMaxCodec.fit(catalog.frame(t), nums)
            for fk in catalog.backward(t):
                out.deltas[fk.name] = delta_of(degrees(catalog, fk.name))
        return out


Vector = list[Column]


def encode_fields(catalog: Catalog, table: str, params: LatticeParams, fitted: Fitted) -> list[Vector]:
    """The d-wide vectors of a table's own features, numbers first."""
    d, spec, out = params.d, catalog.specs[table], []
    for c in feature_columns(catalog, table):
        if c in spec.numeric:
            x, name = fitted.ranges[table].unit(c), f"{table}.{c}"
            x = F.coalesce(x, F.lit(0.0))
            out.append([F.greatest(F.lit(0.0), x * F.lit(params.weight(f"{name}.w", 0, j)) + F.lit(params.weight(f"{name}.b", 0, j))) for j in range(d)])
        else:
            out.append([params.category(spec.domain(c), F.col(c), j) for j in range(d)])
    return out


def block(fields: list[Vector], params: LatticeParams, name: str, width: int, kind: str) -> Vector:
    """A single-table model over a stack of vectors: relu, linear or fm."""
    d, out = params.d, []
    for j in range(width):
        total = F.lit(params.weight(f"{name}.bias", 0, j))
        for f, v in enumerate(fields):
            for i in range(d):
                total = total + v[i] * F.lit(params.weight(f"{name}.w{f}", i, j))
        if kind == "fm" and fields:
            for i in range(d):  # products of all pairs of fields, over every component
                s, q = F.lit(0.0), F.lit(0.0)
                for v in fields:
                    s, q = s + v[i], q + v[i] * v[i]
                total = total + F.lit(0.5) * (s * s - q)
        out.append(F.greatest(F.lit(0.0), total) if kind == "relu" else total)
    return out


def aggregate_vector(params: LatticeParams, fk: str, delta: float, deg: Column, stat: dict[str, Vector]) -> Vector:
    """The nine-to-one map; without children the zero vector.

    It is applied as three d x d maps with scaled weights, so the nine vectors are never laid out.
    """
    s, d = scalers(deg, delta), params.d
    out = []
    for j in range(d):
        total = F.lit(0.0)
        for a, (n, _) in enumerate(STATS):
            for i in range(d):
                w = [params.weight(f"agg.{fk}.{n}.s{k}", i, j) for k in range(3)]
                total = total + stat[n][i] * (F.lit(w[0]) + s[1] * F.lit(w[1]) + s[2] * F.lit(w[2]))
        out.append(F.when(deg > 0, total).otherwise(0.0))
    return out


def gather_forward(df: DataFrame, fk_column: str, parent: DataFrame, parent_key: str, columns: list[str], prefix: str) -> DataFrame:
    """Left join of the referenced row's columns; zero where nothing is referenced."""
    right = parent.select(F.col(parent_key).alias(f"{prefix}k"), *[F.col(c).alias(f"{prefix}{c}") for c in columns])
    joined = df.join(right, F.col(fk_column) == F.col(f"{prefix}k"), "left").drop(f"{prefix}k")
    return joined.withColumns({f"{prefix}{c}": F.coalesce(f"{prefix}{c}", F.lit(0.0)) for c in columns})


def message(catalog: Catalog, table: str, h: dict[str, DataFrame] | None, params: LatticeParams, fitted: Fitted, name: str, width: int, kind: str) -> DataFrame:
    """Key and foreign-key columns, then h_0 .. of the block's output.  ``h`` None stands for zero vectors."""
    spec, d = catalog.specs[table], params.d
    hs = [f"h_{j}" for j in range(d)]
    fk_cols = [k.column for k in catalog.forward(table)]
    keep = list(dict.fromkeys([*spec.key, *fk_cols]))
    df = catalog.frame(table).select(*dict.fromkeys([*keep, *feature_columns(catalog, table)]))
    zero = [F.lit(0.0)] * d
    forward, backward = [], []
    if h is not None:
        for n, fk in enumerate(catalog.forward(table)):
            df = gather_forward(df, fk.column, h[fk.dst], catalog.key(fk.dst)[0], hs, f"f{n}_")
            forward.append([F.col(f"f{n}_{c}") for c in hs])
        for n, fk in enumerate(catalog.backward(table)):
            stats = neighbour_stats(h[fk.src], fk.column, hs, out=f"b{n}_key")
            stats = stats.select(f"b{n}_key", *[F.col(c).alias(f"b{n}_{c}") for c in stats.columns[1:]])
            df = df.join(stats, F.col(spec.key[0]) == F.col(f"b{n}_key"), "left").drop(f"b{n}_key")
            deg = F.coalesce(F.col(f"b{n}_deg"), F.lit(0))
            stat = {s: [F.coalesce(F.col(f"b{n}_{s}_{c}"), F.lit(0.0)) for c in hs] for s, _ in STATS}
            backward.append(aggregate_vector(params, fk.name, fitted.deltas[fk.name], deg, stat))
    else:
        forward, backward = [zero for _ in catalog.forward(table)], [zero for _ in catalog.backward(table)]
    # Fields are ordered by name of their source, not by declaration, so the order of edges changes nothing.
    named = sorted(zip([k.name for k in catalog.forward(table)], forward, strict=True), key=lambda x: x[0])
    named_b = sorted(zip([k.name for k in catalog.backward(table)], backward, strict=True), key=lambda x: x[0])
    fields = [*encode_fields(catalog, table, params, fitted), *[v for _, v in named], *[v for _, v in named_b]]
    out = block(fields, params, name, width, kind)
    return df.select(*keep, *[c.alias(f"h_{j}") for j, c in enumerate(out)])


def propagate(catalog: Catalog, depth: int, params: LatticeParams, fitted: Fitted, target: str | None = None, kind: str = "relu", checkpoint: bool = False) -> dict[str, DataFrame]:
    """Vectors after ``depth`` rounds: of all tables, or of those the target's prediction uses."""
    need = needed_tables(catalog, target, depth) if target else {k: set(catalog.specs) for k in range(1, depth + 1)}
    h: dict[str, DataFrame] | None = None
    for k in range(1, depth + 1):
        h = {t: message(catalog, t, h, params, fitted, f"row.{t}", params.d, kind) for t in sorted(need[k])}
        if checkpoint:  # cuts the plan of deep runs; the files are in the cluster's checkpoint folder
            h = {t: df.checkpoint() for t, df in h.items()}
    return h or {}


def predict(catalog: Catalog, target: str, depth: int, params: LatticeParams, fitted: Fitted | None = None, kind: str = "relu", head: str = "linear", checkpoint: bool = False) -> DataFrame:
    """Key columns, logit, prob.  Depth 0 gives all contexts the zero vector: the target table alone."""
    fitted = fitted or Fitted.of(catalog)
    h = propagate(catalog, depth, params, fitted, target, kind, checkpoint) if depth else None
    out = message(catalog, target, h, params, fitted, f"head.{target}", 1, head)
    return out.select(*catalog.key(target), F.col("h_0").alias("logit"), (1 / (1 + F.exp(-F.col("h_0")))).alias("prob"))


def identity_propagate(catalog: Catalog, rounds: int, aggs: tuple[str, ...] = ("mean", "max", "min"), target: str | None = None) -> dict[str, DataFrame]:
    """The identity parametrisation: vectors are growing sets of labelled numeric columns; used to verify, not to learn.

    A label spells its walk: ``fk>label`` is the referenced row's value, ``agg(fk<label)`` a summary of referring rows.
    """
    need = needed_tables(catalog, target, rounds - 1) | {rounds: {target}} if target else {k: set(catalog.specs) for k in range(1, rounds + 1)}
    h: dict[str, DataFrame] = {}
    funcs = {"mean": F.avg, "max": F.max, "min": F.min}
    for k in range(1, rounds + 1):
        new = {}
        for t in sorted(need[k]):
            spec = catalog.specs[t]
            own = [c for c in feature_columns(catalog, t) if c in spec.numeric]
            keep = list(dict.fromkeys([*spec.key, *(f.column for f in catalog.forward(t))]))
            df = catalog.frame(t).select(*keep, *[F.col(c).cast("double").alias(c) for c in own])
            for fk in catalog.forward(t) if k > 1 else []:
                cols = labels_of(catalog, fk.dst, h[fk.dst])
                right = h[fk.dst].select(F.col(f"`{catalog.key(fk.dst)[0]}`").alias("_k"), *[F.col(f"`{c}`").alias(f"{fk.name}>{c}") for c in cols])
                df = df.join(right, F.col(fk.column) == F.col("_k"), "left").drop("_k")
            for fk in catalog.backward(t) if k > 1 else []:
                cols = labels_of(catalog, fk.src, h[fk.src])
                if not cols:
                    continue
                right = h[fk.src].groupBy(F.col(fk.column).alias("_k")).agg(*[funcs[a](F.col(f"`{c}`")).alias(f"{a}({fk.name}<{c})") for c in cols for a in aggs])
                df = df.join(right, F.col(spec.key[0]) == F.col("_k"), "left").drop("_k")
            new[t] = df
        h = new
    return h


def labels_of(catalog: Catalog, table: str, df: DataFrame) -> list[str]:
    keys = {*catalog.key(table), *(k.column for k in catalog.forward(table))}
    return [c for c in df.columns if c not in keys]
