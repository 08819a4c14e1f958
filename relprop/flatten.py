"""Baselines without aggregation: the target table alone, and recursive joins along foreign keys."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .features import feature_columns
from .schema import Catalog


class NotApplicable(ValueError):
    """The target table has keys and a label only."""


def target_only(catalog: Catalog, target: str) -> DataFrame:
    cols = feature_columns(catalog, target)
    if not cols:
        raise NotApplicable(f"{target} has no feature columns")
    return catalog.frame(target).select(*catalog.key(target), *cols)


def simple_join(catalog: Catalog, target: str, max_depth: int | None = None) -> DataFrame:
    """Left joins of everything that foreign keys lead to; columns are labelled by their path; no table twice on a path."""
    df = catalog.frame(target).select(*dict.fromkeys([*catalog.key(target), *(k.column for k in catalog.forward(target)), *feature_columns(catalog, target)]))
    out = [F.col(c) for c in dict.fromkeys([*catalog.key(target), *feature_columns(catalog, target)])]

    def visit(table: str, prefix: str, seen: tuple[str, ...], depth: int) -> None:
        nonlocal df
        if max_depth is not None and depth >= max_depth:
            return
        for fk in catalog.forward(table):
            if fk.dst in seen:
                continue
            path = f"{prefix}{fk.name}>"
            cols = dict.fromkeys([*(k.column for k in catalog.forward(fk.dst)), *feature_columns(catalog, fk.dst)])
            right = catalog.frame(fk.dst).select(F.col(catalog.key(fk.dst)[0]).alias(f"{path}#"), *[F.col(c).alias(f"{path}{c}") for c in cols])
            df = df.join(right, F.col(f"`{prefix}{fk.column}`") == F.col(f"`{path}#`"), "left")
            out.extend(F.col(f"`{path}{c}`") for c in feature_columns(catalog, fk.dst))
            visit(fk.dst, path, (*seen, fk.dst), depth + 1)

    visit(target, "", (target,), 0)
    return df.select(*out)
