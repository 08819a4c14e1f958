"""The experiment grids, on the given tables and on the two synthetic databases."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import replace

from pyspark.sql import SparkSession

from . import flatten, rollup, synth, tasks
from .metrics import RunReport
from .schema import Task
from .ml import fit_ml
from .train import Coder, Fit, Ready, prepare, run, settled

#: Small enough for one machine; a cluster run passes its own.
QUICK = Fit(epochs=6, rate=0.02, patience=6, passes=4)
WITH_SUMS = ("mean", "max", "min", "sum", "count")


def _report(task: Task, *args, **options) -> RunReport:
    """One run's report; its batches are dropped."""
    _, report, packed = run(task, *args, **options)
    if packed is not None:
        packed.unpersist()
    return report


def _reports(ready: Ready, runs: Iterable[RunReport]) -> list[RunReport]:
    """The reports of runs over the same rows; their batches are dropped behind the last."""
    out = list(runs)
    if isinstance(ready, Ready):
        ready.packed.unpersist()
    return out


def order_sensitivity(spark: SparkSession, folder: str, how: Fit = Fit(epochs=10, rate=0.01, patience=10, passes=40), d: int = 8) -> list[RunReport]:
    """Both synthetic shapes over the given tables: roll-up by two traversals and deeper, and propagation.

    The roll-up gets sums and counts as well, so that only the paths it follows make a difference.
    """
    out = []
    for make, name, depth in ((synth.given1, "syn1", 2), (synth.given2, "syn2", 3)):
        task = settled(make(spark, folder))
        for i, order in enumerate(synth.ORDERS[name], 1):
            for k in (depth,) if i == 1 else (depth, depth + 1):
                flat = rollup.rollup(task.catalog, rollup.rollup_plan(task.catalog, "A", k, order, WITH_SUMS))
                r = _report(task, "flat", 0, how, flat=flat, d=d, batch_size=2000)
                out.append(replace(r, method=f"rollup traversal {i}", depth=k, n_features=len(flat.columns) - 1))
        out.append(replace(_report(task, "rep", depth, how, d=d, batch_size=2000), method="propagation"))
    return out


def baselines(task: Task, how: Fit = QUICK, heads: tuple[str, ...] = ("deepfm", "transformer"), depth: int = 2, d: int = 8) -> list[RunReport]:
    """Target only, joined and rolled-up tables under each flat model; a target of keys alone is marked so."""
    out, task = [], settled(task)
    for name, make in (("target only", lambda: flatten.target_only(task.catalog, task.target)), ("simple join", lambda: flatten.simple_join(task.catalog, task.target)), ("roll-up", lambda: rollup.rollup(task.catalog, rollup.rollup_plan(task.catalog, task.target, depth)))):
        for head in heads:
            try:
                r = _report(task, "flat", 0, how, flat=make(), d=d, head=head)
                out.append(replace(r, method=f"{name} + {head}"))
            except flatten.NotApplicable:
                out.append(RunReport(task.name, f"{name} + {head} (not applicable)", 0, how.seed))
    return out


def row_networks(task: Task, depth: int, how: Fit = QUICK, d: int = 8, width: int = 16) -> list[RunReport]:
    """The three backbones and propagation, with their training times."""
    ready = prepare(task := settled(task), depth)
    ways = {f"row network {b}": (b, {"width": width}) for b in ("rgcn", "gat", "hgt")} | {"propagation": ("rep", {})}
    return _reports(ready, (replace(run(task, m, depth, how, d=d, ready=ready, **more)[1], method=name) for name, (m, more) in ways.items()))


def ml_heads(task: Task, depth: int = 1, heads: tuple[str, ...] = ("logistic", "fm", "gbt")) -> list[RunReport]:
    """The library's own classifiers over the rolled-up table, as a cross-check of the flat models."""
    flat = rollup.rollup(task.catalog, rollup.rollup_plan(task.catalog, task.target, depth))
    return [fit_ml(task, flat, h) for h in heads]


def row_block_ablation(task: Task, depth: int, how: Fit = QUICK, d: int = 8) -> list[RunReport]:
    ready = prepare(task := settled(task), depth)
    return _reports(ready, (replace(run(task, "rep", depth, how, d=d, row=b, head="deepfm", ready=ready)[1], method=f"rows {b}, head deepfm") for b in ("mlp", "deepfm")))


def base_model_ablation(task: Task, depth: int, how: Fit = QUICK, d: int = 8) -> list[RunReport]:
    ready = prepare(task := settled(task), depth)
    return _reports(ready, (replace(run(task, "rep", depth, how, d=d, row=b, head=b, ready=ready)[1], method=f"both {b}") for b in ("deepfm", "transformer")))


def aggregator_ablation(task: Task, depth: int, how: Fit = QUICK, d: int = 8) -> list[RunReport]:
    """What sets propagation apart, taken away one at a time.

    Parameters of a round's own differ from shared ones only where a table has vectors of two rounds that are used.
    """
    ways = {"full": {}, "mean only": {"stats": ("mean",), "scaled": False}, "no scalers": {"scaled": False}, "no skip": {"skip": False}, "own parameters a round": {"shared": False}}
    ready = prepare(task := settled(task), depth)
    return _reports(ready, (replace(run(task, "rep", depth, how, d=d, ready=ready, **w)[1], method=n) for n, w in ways.items()))


def depth_sweep(task: Task, depths: list[int], how: Fit = QUICK, d: int = 8) -> list[RunReport]:
    coder, out = Coder.fit(task := settled(task)), []
    for k in depths:
        ready = prepare(task, k, coder=coder)
        out += _reports(ready, [run(task, "rep", k, how, d=d, ready=ready)[1]])
    return out


def grid(spark: SparkSession, folder: str, names: tuple[str, ...] = ("orders", "impression", "seen", "user_day"), how: Fit = QUICK) -> list[RunReport]:
    """All methods on the stand-ins of the real databases."""
    depth = {"orders": 2, "impression": 4, "seen": 3, "user_day": 2}
    out = []
    for n in names:
        task = tasks.user_day_task(spark, folder, as_of=24) if n == "user_day" else tasks.TASKS[n](spark, folder)
        out += baselines(task, how, depth=depth[n]) + row_networks(task, depth[n], how)
    return out


_SHORT = Fit(epochs=2, rate=0.02, patience=2, passes=2)
QUERY = {
    "train_order_sensitivity": lambda s, d: order_sensitivity(s, d, Fit(epochs=4, rate=0.01, patience=4, passes=50), d=6),
    "train_rep_orders": lambda s, d: [_report(settled(tasks.orders_task(s, d)), "rep", 2, _SHORT, d=4)],
    "train_baselines_orders": lambda s, d: baselines(tasks.orders_task(s, d), _SHORT, depth=2, d=4),
    "train_rowgnn_orders": lambda s, d: row_networks(tasks.orders_task(s, d), 2, Fit(), 16, 64),
    "ablation_rowblock": lambda s, d: row_block_ablation(tasks.orders_task(s, d), 1, _SHORT, 4),
    "ablation_basemodel": lambda s, d: base_model_ablation(tasks.orders_task(s, d), 1, _SHORT, 4),
    "ablation_aggregator": lambda s, d: aggregator_ablation(tasks.orders_task(s, d), 3, _SHORT, 4),
    "train_flat_ml_heads": lambda s, d: ml_heads(tasks.orders_task(s, d), 1, ("logistic", "gbt")),
    "train_user_day": lambda s, d: [replace(_report(tasks.user_day_task(s, d, as_of=24), "rep", 2, _SHORT, d=4), method="propagation")],
    "train_seen": lambda s, d: [replace(_report(settled(tasks.seen_task(s, d)), "rep", 2, _SHORT, d=4), method="propagation")],
    "depth_sweep": lambda s, d: depth_sweep(tasks.orders_task(s, d), [0, 1, 2], _SHORT, 4),
}
