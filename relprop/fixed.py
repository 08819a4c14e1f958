"""Learned blocks and row-network layers under fixed weights, so that SQL can repeat what their own code works out."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import make_block
from .features import MinMaxCodec
from .model import RowGnn
from .oracle import num
from .params import LatticeParams
from .schema import Task
from .tape import Var

LATTICE = LatticeParams(2, 11)
COLUMNS = ("p_size", "p_retailprice")
WIDTH = 3


def lattice_arrays(prefix: str, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Arrays of the shapes of ``like``, each weight from its name and place."""
    return {k: np.array([[LATTICE.weight(f"{prefix}.{k}", i, j) for j in range(v.shape[-1])] for i in range(max(1, v.size // v.shape[-1]))]).reshape(v.shape) for k, v in like.items()}


def block_scores(part: DataFrame, name: str) -> DataFrame:
    """p_partkey, z: a block over the two columns' unit values x as field vectors (x, x * x)."""
    codec = MinMaxCodec.fit(part, list(COLUMNS))
    options = {"widths": (WIDTH,)}
    block = make_block(name, **options)
    p = lattice_arrays(name, block.init(2, 2, 1, np.random.default_rng(0)))

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            x = pdf[["a", "b"]].to_numpy(float)
            z = make_block(name, **options).forward(Var(np.stack([x, x * x], 2)), {k: Var(v) for k, v in p.items()}).value
            yield pd.DataFrame({"p_partkey": pdf.p_partkey, "z": z[:, 0].round(6)})

    return part.select("p_partkey", *[codec.unit(c).alias(n) for c, n in zip(COLUMNS, "ab", strict=True)]).mapInPandas(run, "p_partkey long, z double")


def block_sql(name: str) -> str:
    """The same from the formulas: first-order sums, products of pairs of fields, a hidden layer."""
    unit = [f"(({c} - (SELECT min({c}) FROM part)) / (SELECT max({c}) - min({c}) FROM part)::DOUBLE)" for c in COLUMNS]
    x = ["a", "a * a", "b", "b * b"]
    w = lambda k, i, j: num(LATTICE.weight(f"{name}.{k}", i, j))
    dense = lambda k, b, j: " + ".join([w(b, 0, j), *(f"{v} * {w(k, i, j)}" for i, v in enumerate(x))])
    hidden = lambda k, b: [f"greatest(0.0, {dense(k, b, j)})" for j in range(WIDTH)]
    pair = "a * b + a * a * b * b"
    if name == "linear":
        z = dense("w", "b", 0)
    elif name == "mlp":
        z = " + ".join([w("b1", 0, 0), *(f"{h} * {w('w1', i, 0)}" for i, h in enumerate(hidden("w0", "b0")))])
    else:
        z = f"{dense('w', 'b', 0)} + {pair}"
        if name == "deepfm":
            z += "".join(f" + {h} * {w('do', i, 0)}" for i, h in enumerate(hidden("dw0", "db0")))
    return f"SELECT p_partkey, round({z}, 6) AS z FROM (SELECT p_partkey, {unit[0]} AS a, {unit[1]} AS b FROM part)"


def layer_outputs(task: Task, backbone: str, number: dict[str, str]) -> DataFrame:
    """key, z0, z1: the first layer of a row network at every target, from vectors (unit value of one column, 1) of each row."""
    from .train import Coder, packed_batches, unpack

    coder = Coder.fit(task, visible=task.catalog.frame(task.target))
    place = {t: coder.meta[t].numeric.index(c) for t, c in number.items()}
    net = RowGnn(coder.meta, task.target, 1, backbone, 2, 2, 1)
    p = lattice_arrays("net", {k: v for k, v in net.init(0).items() if k.startswith("l0/")})
    target = task.target

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            for blob in pdf.blob:
                batch, keys = unpack(blob)
                h = {t: Var(np.c_[np.nan_to_num(batch.numbers[t][:, place[t]]), np.ones(batch.rows(t))]) for t in place}
                z = net.layer(0, batch, h, {k: Var(v) for k, v in p.items()}, target).value[batch.target]
                yield pd.DataFrame({"key": keys, "z0": z[:, 0].round(6) + 0.0, "z1": z[:, 1].round(6) + 0.0})

    return packed_batches(task, coder, 1).select("blob").mapInPandas(run, "key string, z0 double, z1 double").select(F.col("key").cast("long").alias("key"), "z0", "z1")


def layer_sql(backbone: str) -> str:
    """Orders with their customer and lines: own map, mean or attention over the rows of each relation, relu."""
    u = lambda c, t: f"(({c} - (SELECT min({c}) FROM {t})) / (SELECT max({c}) - min({c}) FROM {t}))"
    w = lambda k, i, j: num(LATTICE.weight(f"net.l0/{k}", i, j))
    lin = lambda k, x, j: f"({x} * {w(k, 0, j)} + {w(k, 1, j)})"
    up, down = "orders.o_custkey>", "lineitem.l_orderkey<"
    base = f"o AS (SELECT o_orderkey, o_custkey, {u('o_totalprice', 'orders')} AS x FROM orders), c AS (SELECT c_custkey, {u('c_acctbal', 'customer')} AS y FROM customer), li AS (SELECT l_orderkey, {u('l_quantity', 'lineitem')} AS q FROM lineitem)"
    if backbone == "rgcn":
        lines = ", ".join(f"avg({lin(f'w/{down}', 'q', j)}) AS m{j}" for j in range(2))
        agg = f"m AS (SELECT l_orderkey, {lines} FROM li GROUP BY 1)"
    else:
        # Of one customer, attention is all on it.
        score = " + ".join(f"{lin(f'w/{down}', 'q', j)} * {w(f'al/{down}', 0, j)} + {lin(f'dst/{down}', 'x', j)} * {w(f'ar/{down}', 0, j)}" for j in range(2))
        agg = f"e AS (SELECT l_orderkey, q, {score} AS s FROM li JOIN o ON o_orderkey = l_orderkey), f AS (SELECT l_orderkey, q, exp(greatest(s, 0.2 * s)) AS a FROM e), m AS (SELECT l_orderkey, " + ", ".join(f"sum(a * {lin(f'w/{down}', 'q', j)}) / sum(a) AS m{j}" for j in range(2)) + " FROM f GROUP BY 1)"
    z = ", ".join(f"round(greatest(0.0, {lin('self/orders', 'x', j)} + CASE WHEN c_custkey IS NULL THEN 0.0 ELSE {lin(f'w/{up}', 'y', j)} END + coalesce(m{j}, 0.0)), 6) AS z{j}" for j in range(2))
    return f"WITH {base}, {agg} SELECT o_orderkey AS key, {z} FROM o LEFT JOIN c ON c_custkey = o_custkey LEFT JOIN m ON l_orderkey = o_orderkey"
