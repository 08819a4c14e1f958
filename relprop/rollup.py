"""Depth-first roll-up: the rule-based baseline, as a planner over the schema and a compiler to joins.

Planning touches no data.  A call for a table with a budget marks it as visited; with budget zero it gives the table's
own columns.  Otherwise each step, referring tables before referenced ones or in a given order, brings in columns of the
neighbour: a neighbour that was not visited is called with one step less and remembered; a finished one gives what it
has; one that is still open gives its own columns only.  Columns of referring rows are summarised, numbers by each
aggregate and categories by their mode; columns of the referenced row are copied.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .features import feature_columns
from .graph import multiset_difference, simple_paths
from .schema import Catalog

AGGS = ("mean", "max", "min")
NUMERIC = {"mean": F.avg, "max": F.max, "min": F.min, "sum": F.sum, "count": F.count, "stddev": F.stddev_samp, "nunique": F.count_distinct}


@dataclass(frozen=True)
class Feature:
    """A planned column.  ``steps``: the way from the table that has it; ``numeric``: not a category."""

    label: str
    numeric: bool
    steps: tuple[str, ...] = ()


@dataclass
class Plan:
    """What a call gives: its table, own features, and for each step taken the plan it drew on."""

    table: str
    own: list[Feature]
    parts: list[tuple[str, str, Plan]]  # (foreign key, "<" or ">", plan of the neighbour)
    aggs: tuple[str, ...] = AGGS

    @property
    def features(self) -> list[Feature]:
        out = list(self.own)
        for fk, way, sub in self.parts:
            for f in sub.features:
                if way == ">":
                    out.append(Feature(f"{fk}>{f.label}", f.numeric, (fk + ">", *f.steps)))
                elif f.numeric:
                    out.extend(Feature(f"{a}({fk}<{f.label})", True, (fk + "<", *f.steps)) for a in self.aggs)
                else:
                    out.append(Feature(f"mode({fk}<{f.label})", False, (fk + "<", *f.steps)))
        return out


def rollup_plan(catalog: Catalog, target: str, depth: int, order: list[str] | None = None, aggs: tuple[str, ...] = AGGS) -> Plan:
    """``order``: foreign-key names, first come first; None takes referring tables before referenced ones."""
    visited: set[str] = set()
    done: dict[str, Plan] = {}

    def own(table: str) -> list[Feature]:
        return [Feature(c, c in catalog.specs[table].numeric) for c in feature_columns(catalog, table)]

    def ways(table: str) -> list[tuple[str, str, str]]:
        both = [(k.name, "<", k.src) for k in catalog.backward(table)] + [(k.name, ">", k.dst) for k in catalog.forward(table)]
        return sorted(both, key=lambda w: order.index(w[0]) if w[0] in order else len(order)) if order else both

    def call(table: str, budget: int) -> Plan:
        visited.add(table)
        plan = Plan(table, own(table), [], aggs)
        if budget > 0:
            for fk, way, other in ways(table):
                if other not in visited:
                    done[other] = call(other, budget - 1)
                sub = done.get(other) or Plan(other, own(other), [], aggs)
                plan.parts.append((fk, way, sub))
        return plan

    return call(target, depth)


def rollup_width(plan: Plan) -> int:
    """Number of feature columns, without running anything."""
    return len(plan.features)


def rollup_paths(plan: Plan) -> set[tuple[str, ...]]:
    """Ways along which at least one column comes."""
    return {f.steps for f in plan.features if f.steps}


def mode_of(column: Column) -> Column:
    """Most frequent value; of several, the smallest."""
    return F.mode(column, True)


def rollup_backward(child: DataFrame, fk: str, numeric: list[str], categorical: list[str], aggs: tuple[str, ...] = AGGS, name: str | None = None) -> DataFrame:
    """fk, then agg(name<c) of each numeric column and mode(name<c) of each category: one row a referenced key."""
    name = name or fk
    cols = [NUMERIC[a](F.col(f"`{c}`")).cast("double").alias(f"{a}({name}<{c})") for c in numeric for a in aggs]
    cols += [mode_of(F.col(f"`{c}`")).alias(f"mode({name}<{c})") for c in categorical]
    return child.filter(F.col(fk).isNotNull()).groupBy(F.col(fk).alias("_fk")).agg(*(cols or [F.count("*").alias("_n")]))


def rollup(catalog: Catalog, plan: Plan, max_columns: int = 2000) -> DataFrame:
    """Key columns of the plan's table, then a column for each feature label."""
    if (n := rollup_width(plan)) > max_columns:
        raise ValueError(f"the plan has {n} columns, more than {max_columns}")
    built: dict[int, DataFrame] = {}

    def compile_(p: Plan) -> DataFrame:
        if id(p) in built:
            return built[id(p)]
        spec = catalog.specs[p.table]
        keep = dict.fromkeys([*spec.key, *(k.column for k in catalog.forward(p.table)), *(f.label for f in p.own)])
        df = catalog.frame(p.table).select(*keep)
        by_name = {k.name: k for k in catalog.fks}
        for name, way, sub in p.parts:
            fk, feats = by_name[name], sub.features
            if not feats:
                continue
            right = compile_(sub)
            if way == ">":
                right = right.select(F.col(catalog.key(fk.dst)[0]).alias("_fk"), *[F.col(f"`{f.label}`").alias(f"{name}>{f.label}") for f in feats])
                df = df.join(right, F.col(fk.column) == F.col("_fk"), "left").drop("_fk")
            else:
                right = rollup_backward(right, fk.column, [f.label for f in feats if f.numeric], [f.label for f in feats if not f.numeric], p.aggs, name)
                df = df.join(right, F.col(spec.key[0]) == F.col("_fk"), "left").drop("_fk")
        built[id(p)] = df
        return df

    return compile_(plan).select(*catalog.key(plan.table), *[F.col(f"`{f.label}`") for f in plan.features])


def path_coverage(catalog: Catalog, plan: Plan, depth: int) -> tuple[int, int]:
    """(simple paths of at most ``depth`` steps that the plan's columns follow, all such paths)."""
    paths = set(simple_paths(catalog, plan.table, depth))
    # A path to a table without features cannot show in a label.
    return len(paths & rollup_paths(plan)), len(paths)


def order_report(catalog: Catalog, target: str, depth: int, orders: list[list[str]]) -> list[tuple[str, str, int, int]]:
    """(order, order, labels only in the first, only in the second) of each pair of traversal orders."""
    labels = {",".join(o): [f.label for f in rollup_plan(catalog, target, depth, o).features] for o in orders}
    names = list(labels)
    return [(a, b, *map(len, multiset_difference(labels[a], labels[b]))) for i, a in enumerate(names) for b in names[i + 1 :]]


def escalate_depth(catalog: Catalog, target: str, order: list[str] | None, start: int, limit: int = 10, good=lambda plan: False) -> list[tuple[int, int]]:
    """(depth, columns) from ``start`` on, until ``good`` of the plan holds or a depth brings no new label."""
    out: list[tuple[int, int]] = []
    before: list[str] | None = None
    for depth in range(start, limit + 1):
        plan = rollup_plan(catalog, target, depth, order)
        labels = [f.label for f in plan.features]
        if labels == before:
            break
        out.append((depth, len(labels)))
        before = labels
        if good(plan):
            break
    return out


def width_report(catalog: Catalog, target: str, depth: int, d: int) -> tuple[int, int]:
    """(columns the roll-up appends, vectors of width d that propagation appends: one a relation, whatever the depth)."""
    plan = rollup_plan(catalog, target, depth)
    return rollup_width(plan) - len(plan.own), (len(catalog.forward(target)) + len(catalog.backward(target)))
