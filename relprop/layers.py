"""Learned propagation over whole tables, a round at a time: every row of a table is worked out once a round.

A round is one left join a reference, one aggregation a relation that points back and one Python pass over the rows.
No neighbourhood is packed, so a row that many targets share costs no more than any other, and a hub's children are
summarised by partial aggregates.  Only parameters are broadcast.  Each round is written to the checkpoint folder: plans
stay short at any depth, and lost executors cost one round.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import tape as T
from .graph import node_key
from .model import Packed, Rep, TableMeta, encode
from .params import ParamStore
from .schema import Task
from .tape import Var

STATS = {"mean": F.avg, "max": F.max, "min": F.min}


def _matrix(column: pd.Series, width: int) -> np.ndarray:
    """Rows of arrays; null is zero."""
    zero = np.zeros(width)
    return np.array([zero if v is None else v for v in column], float).reshape(len(column), width)


def _kernel(model: Rep, t: TableMeta, first: bool, prefix: str, row: bool):
    """The block of one table over a frame of own columns, forward vectors f0 .. and summaries b0_mean .."""
    block = (model.row if row else model.head).make()

    def run(pdf: pd.DataFrame, p: dict[str, Var]) -> np.ndarray:
        n, d = len(pdf), model.d
        numbers = np.array([[np.nan if v is None else v for v in r] for r in pdf.numbers], float).reshape(n, len(t.numeric))
        codes = np.array(pdf.codes.tolist(), int).reshape(n, len(t.categorical))
        own = encode(t, Packed({t.name: numbers}, {t.name: codes}, {}, {}, np.zeros(0, int), np.zeros(0)), p)
        zero = Var(np.zeros((n, d)))
        fields = list(own) if model.skip or first else [zero] * len(own)
        for i in range(len(t.forward)):
            fields.append(zero if first else Var(_matrix(pdf[f"f{i}"], d)))
        for i, (fk, _) in enumerate(t.backward):
            if first:
                fields.append(zero)
                continue
            deg = np.array([x[i] for x in pdf.degs], float)[:, None]
            fields.append(model.relation(fk, [Var(_matrix(pdf[f"b{i}_{s}"], d)) for s in model.stats], deg, p))
        under = {k[len(prefix) :]: v for k, v in p.items() if k.startswith(prefix)}
        z = block.forward(T.stack(fields or [zero], 1), under).value
        return np.tanh(z) if row and model.squash else z

    return run


def transform(task: Task, coder, model: Rep, params: ParamStore, kind: str = "binary") -> DataFrame:
    """key (one string), logit, prob of every row of the target; the same as scoring packed neighbourhoods."""
    cat, meta = task.catalog, model.meta
    spark = cat.frame(task.target).sparkSession
    shared = spark.sparkContext.broadcast(dict(params))  # parameters only
    own: dict[str, DataFrame] = {}

    def rows(table: str) -> DataFrame:
        """Coded rows, laid down once: every round reads them."""
        if table not in own:
            own[table] = _cut(coder.coded(cat, table).select(node_key(cat.key(table)).alias("key"), "numbers", "codes", "refs", "degs"))
        return own[table]

    def joined(table: str, h: dict[str, DataFrame] | None) -> DataFrame:
        df, t = rows(table), meta[table]
        for i, (_, other) in enumerate(t.forward if h is not None else []):
            df = df.join(h[other].select(F.col("key").alias("_k"), F.col("h").alias(f"f{i}")), F.get("refs", F.lit(i)) == F.col("_k"), "left").drop("_k")
        for i, (fk, other) in enumerate(t.backward if h is not None else []):
            place = [name for name, _ in meta[other].forward].index(fk)
            kids = h[other].select(F.get("refs", F.lit(place)).alias("_k"), "h").filter("_k is not null")
            aggs = [STATS[s](F.get("h", F.lit(j))).alias(f"{s}_{j}") for s in model.stats for j in range(model.d)]
            stat = kids.groupBy("_k").agg(*aggs).select("_k", *[F.array(*[F.col(f"{s}_{j}") for j in range(model.d)]).alias(f"b{i}_{s}") for s in model.stats])
            df = df.join(stat, F.col("key") == F.col("_k"), "left").drop("_k")
        return df

    def apply(df: DataFrame, run, schema: str, out) -> DataFrame:
        def go(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            p = {k: Var(v) for k, v in shared.value.items()}
            for pdf in parts:
                if len(pdf):
                    yield out(pdf, run(pdf, p))

        return df.mapInPandas(go, schema)

    h: dict[str, DataFrame] | None = None
    need = model._need()
    for k in range(1, model.depth + 1):
        new = {}
        for table in sorted(need[k]):
            run = _kernel(model, meta[table], h is None, model._names(k, table) + "/", True)
            new[table] = _cut(apply(joined(table, h), run, "key string, refs array<string>, h array<double>", lambda pdf, z: pd.DataFrame({"key": pdf.key, "refs": pdf.refs, "h": list(z)})))
        h = new

    def scored(pdf: pd.DataFrame, z: np.ndarray) -> pd.DataFrame:
        logit = z.argmax(axis=1).astype(float) if kind == "multiclass" else z[:, 0]
        return pd.DataFrame({"key": pdf.key, "logit": logit, "prob": 1 / (1 + np.exp(-np.clip(logit, -60, 60)))})

    return apply(joined(task.target, h), _kernel(model, meta[task.target], h is None, "head/", False), "key string, logit double, prob double", scored)


def _cut(df: DataFrame) -> DataFrame:
    from .ops.streaming import shared_folder

    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()
