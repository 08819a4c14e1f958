"""Every roll-up column of depth l is a column of l + 1 identity rounds: count the rows that differ."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .propagate import identity_propagate, labels_of
from .rollup import rollup, rollup_plan
from .schema import Catalog


def superset_report(catalog: Catalog, target: str, depth: int, order: list[str] | None = None) -> DataFrame:
    """label, missing (no such column), rows, differing: one row a numeric roll-up column."""
    plan = rollup_plan(catalog, target, depth, order)
    numeric = [f.label for f in plan.features if f.numeric]
    flat = rollup(catalog, plan)
    ident = identity_propagate(catalog, depth + 1, target=target)[target]
    have = set(labels_of(catalog, target, ident))
    keys = list(catalog.key(target))
    right = ident.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], *[F.col(f"`{c}`").alias(f"i:{c}") for c in numeric if c in have])
    # Rows that repeat a key are told apart by the table's own columns.
    own = [f.label for f in plan.own if f.numeric and f.label in have]
    on = [F.col(k).eqNullSafe(F.col(f"_k{i}")) for i, k in enumerate(keys)] + [F.col(f"`{c}`").cast("double").eqNullSafe(F.col(f"`i:{c}`")) for c in own]
    both = flat.join(right, on, "full")
    same = lambda c: F.col(f"`{c}`").cast("double").eqNullSafe(F.col(f"`i:{c}`")) | (F.abs(F.col(f"`{c}`") - F.col(f"`i:{c}`")) <= 1e-9 * F.greatest(F.lit(1.0), F.abs(F.col(f"`{c}`"))))
    counts = both.agg(F.count("*").alias("n"), *[F.sum(F.when(F.coalesce(same(c), F.lit(False)), 0).otherwise(1)).alias(f"d:{c}") for c in numeric if c in have])
    cells = [F.struct(F.lit(c).alias("label"), F.lit(c not in have).alias("missing"), F.col("n").alias("rows"), (F.col(f"`d:{c}`") if c in have else F.col("n")).alias("differing")) for c in numeric]
    return counts.select(F.explode(F.array(*cells)).alias("x")).select("x.*")
