"""Training and scoring over packed K-hop batches.

Targets are dealt into batches by hash; each batch's rows within K hops are packed once into one binary row of local
arrays.  Training passes over packed batches in Python workers: in mode "epoch" every partition takes Adam steps on its
batches and parameters are averaged by rows seen; in mode "step" gradients of a batch round are summed and the driver
takes the step.  What returns to the driver is parameters or gradients, never rows.
"""

from __future__ import annotations

import pickle
import time
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import reduce
from itertools import groupby

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import tape as T
from .blocks import BlockSpec
from .features import CategoryCodec, MinMaxCodec, feature_columns
from .graph import Arrivals, arrivals, degrees, khop_subgraph, node_key
from .metrics import RunReport, auc, auc_local, peak_memory, shuffle_written
from .model import Packed, Rep, RowGnn, TableMeta
from .params import ParamStore, load_model, save_model
from .schema import Catalog, TableSpec, Task, bucket_of, kept, part_of
from .tape import Var


@dataclass
class Coder:
    """Codes fitted once: number ranges, dictionaries, mean log degrees."""

    ranges: dict[str, MinMaxCodec]
    codes: dict[str, CategoryCodec]
    meta: dict[str, TableMeta]
    deltas: dict[str, float]

    @classmethod
    def fit(cls, task: Task, max_size: int = 65_536, visible: DataFrame | None = None) -> Coder:
        """``visible``: the target rows that fitting may see; None takes its training part."""
        cat, ranges, codes, meta, deltas = task.catalog, {}, {}, {}, {}
        sources: dict[str, list] = {}
        for t, spec in cat.specs.items():
            df = cat.frame(t)
            if t == task.target:
                df = visible if visible is not None else df.filter(part_of(list(task.keys), 0, task.ratios) == "train").dropna(subset=list(task.keys))
            cols = feature_columns(cat, t)
            ranges[t] = MinMaxCodec.fit(df, [c for c in cols if c in spec.numeric])
            for c in cols:
                if c in spec.categorical:
                    sources.setdefault(spec.domain(c), []).append((df, c, t))
        by_domain = {d: CategoryCodec.fit([(df, f"{c}", d) for df, c, _ in s], max_size) for d, s in sources.items()}
        for t, spec in cat.specs.items():
            cols = feature_columns(cat, t)
            cats = [(c, by_domain[spec.domain(c)].cardinality(c), spec.domain(c)) for c in cols if c in spec.categorical]
            codes.update({f"{t}.{c}": by_domain[d] for c, _, d in cats})
            meta[t] = TableMeta(t, [c for c in cols if c in spec.numeric], cats, [(k.name, k.dst) for k in cat.forward(t)], [(k.name, k.src) for k in cat.backward(t)])
        for fk in cat.fks:
            deltas[fk.name] = degrees(cat, fk.name).agg(F.avg(F.log1p("deg"))).first()[0] or 1.0
        return cls(ranges, codes, meta, deltas)

    def coded(self, catalog: Catalog, table: str, *more: Column) -> DataFrame:
        """Key columns, numbers array<double>, codes array<int>, refs array<string>, degs array<bigint>, and ``more`` of the table's columns."""
        m, df = self.meta[table], catalog.frame(table)
        numbers = [self.ranges[table].unit(c) for c in m.numeric]
        for c, _, _ in m.categorical:
            df = self.codes[f"{table}.{c}"].transform(df, c, f"_id_{c}")
        key = catalog.key(table)
        for i, fk in enumerate(catalog.backward(table)):
            d = catalog.frame(fk.src).filter(F.col(fk.column).isNotNull()).groupBy(F.col(fk.column).alias(f"_d{i}")).agg(F.count("*").alias(f"_deg{i}"))
            df = df.join(d, F.col(key[0]) == F.col(f"_d{i}"), "left")
        empty = lambda kind: F.array().cast(f"array<{kind}>")
        return df.select(
            *key,
            (F.array(*numbers) if numbers else empty("double")).alias("numbers"),
            (F.array(*[F.col(f"_id_{c}").cast("int") for c, _, _ in m.categorical]) if m.categorical else empty("int")).alias("codes"),
            (F.array(*[F.col(k.column).cast("string") for k in catalog.forward(table)]) if m.forward else empty("string")).alias("refs"),
            (F.array(*[F.coalesce(f"_deg{i}", F.lit(0)).cast("bigint") for i in range(len(m.backward))]) if m.backward else empty("bigint")).alias("degs"),
            *more,
        )


#: Batches that one worker trains on before parameters are averaged; with few each, averaging loses most of what they learn.
BATCHES_A_WORKER = 8


def packed_batches(task: Task, coder: Coder, depth: int, batch_size: int = 512, seed: int = 0, fanout: int | None = None, parts: tuple[str, ...] = ("train", "valid", "test")) -> DataFrame:
    """worker, batch_id, part, rows, blob: one row a batch of targets of one part; a worker's batches lie together in one partition."""
    cat, target = task.catalog, task.target
    keys, part = list(task.keys), part_of(list(task.keys), seed, task.ratios)
    chosen = part.isin(*parts)
    n = cat.frame(target).filter(chosen).count()
    batches = max(1, -(-n // batch_size))
    code = F.when(part == "train", 0).when(part == "valid", 1).otherwise(2)
    batch_of = (bucket_of(keys, seed + 1, batches) * 3 + code).cast("long")
    # Where only some parts are asked for, a row of another part is in no batch of its own.
    own_batch = F.when(chosen, batch_of)
    carried = dict.fromkeys([*keys, *(k.column for k in cat.forward(target))])
    targets = cat.frame(target).filter(chosen).select(batch_of.alias("batch_id"), *carried)
    if fanout is None:
        reach = arrivals(cat, target, targets, own_batch, depth)
    else:
        reach = {t: Arrivals(None, None, df) for t, df in khop_subgraph(cat, target, targets, depth, fanout).items()}
        reach[target].keys = reach[target].keys.filter(~F.coalesce(own_batch == F.col("batch_id"), F.lit(False)))
    place = {t: i for i, t in enumerate(cat.specs)}
    referred = {k.dst for k in cat.fks} | {target}

    def lines(t: str, df: DataFrame, label: Column, part: Column) -> DataFrame:
        # Only rows that something refers to need a key.
        key = node_key(cat.key(t)) if t in referred else F.lit(None).cast("string")
        return df.select("batch_id", F.lit(place[t]).cast("byte").alias("tbl"), key.alias("key"), "numbers", "codes", "refs", "degs", label.alias("label"), part.alias("part"))

    none, other = F.lit(None).cast("double"), F.lit(None).cast("string")
    own = coder.coded(cat, target, F.col(task.label).cast("double").alias("_label"), part.alias("_part"), own_batch.alias("batch_id"))
    union = [lines(target, own.filter("batch_id is not null"), F.col("_label"), F.col("_part"))]
    for t, way in reach.items():
        if way.only:
            column = next(k.column for k in cat.forward(t) if k.name == way.only)
            more = coder.coded(cat, t, F.col(column).alias("_fk"), *([own_batch.alias("_own")] if t == target else [])).join(way.parents, F.col("_fk") == F.col("_key"))
            if t == target:
                more = more.filter(~F.coalesce(F.col("_own") == F.col("batch_id"), F.lit(False)))
        else:
            more = way.keys.join(coder.coded(cat, t), list(cat.key(t)))
        union.append(lines(t, more, none, other))
    meta, tables = coder.meta, {i: t for t, i in place.items()}

    def pack(rows: pa.Table) -> pa.Table:
        numbers, codes, parent, degree, refs = {}, {}, {}, {}, {}
        kind = rows["tbl"].to_numpy()
        of = {t: rows.take(np.flatnonzero(kind == i)).combine_chunks() for i, t in tables.items()}
        flat = lambda column, width, blank: pc.fill_null(pc.list_flatten(column), blank).to_numpy().reshape(len(column), width)
        for t in meta:
            refs[t] = pc.list_flatten(of[t]["refs"])
        for t, m in meta.items():
            g, order = of[t], slice(None)
            found = {fk: _place(refs[t].take(np.arange(i, len(refs[t]), len(m.forward))), of[other]["key"]) for i, (fk, other) in enumerate(m.forward)}
            if m.forward and t not in referred:
                order = np.argsort(found[m.forward[0][0]], kind="stable")  # children of one row stand together
            parent.update({fk: v[order].astype(np.int32) for fk, v in found.items()})
            numbers[t] = flat(g["numbers"], len(m.numeric), np.nan)[order]
            codes[t] = np.asarray(flat(g["codes"], len(m.categorical), 0)[order], np.min_scalar_type(max([c for _, c, _ in m.categorical], default=0)))
            degs = flat(g["degs"], len(m.backward), 0)
            degree.update({fk: degs[:, i][order] for i, (fk, _) in enumerate(m.backward)})
        mine = of[task_target]
        at = np.flatnonzero(mine["part"].is_valid().to_numpy())
        label, names = mine["label"].take(at).to_numpy(), mine["key"].take(at)
        blob = zlib.compress(pickle.dumps((Packed(numbers, codes, parent, degree, at.astype(np.int32), label), names.to_pylist()), protocol=5), 1)
        return pa.table({"worker": rows["worker"][:1], "batch_id": rows["batch_id"][:1], "part": mine["part"].take(at[:1]), "rows": pa.array([len(at)], pa.int64()), "blob": pa.array([blob], pa.binary())})

    task_target = target
    workers = max(1, batches // BATCHES_A_WORKER)
    dealt = reduce(DataFrame.unionByName, union).withColumn("worker", (F.floor(F.col("batch_id") / 3) % workers).cast("long"))
    return dealt.repartition("worker").groupBy("worker", "batch_id").applyInArrow(pack, "worker long, batch_id long, part string, rows long, blob binary")


def _place(refs: pa.ChunkedArray, keys: pa.ChunkedArray) -> np.ndarray:
    """Where each reference stands among the keys; -1 without one."""
    return pc.fill_null(pc.index_in(refs, value_set=keys, skip_nulls=True), -1).to_numpy()


def unpack(blob: bytes) -> tuple[Packed, list[str]]:
    """A batch and the keys of its targets."""
    b, keys = pickle.loads(zlib.decompress(blob))
    wide = lambda d, kind: {k: v.astype(kind) for k, v in d.items()}
    return Packed(b.numbers, wide(b.codes, np.int64), wide(b.parent, np.int64), wide(b.degree, float), b.target.astype(np.int64), b.label), keys


@dataclass
class Adam:
    rate: float = 1e-2
    decay: float = 1e-6
    m: np.ndarray | None = None
    v: np.ndarray | None = None
    t: int = 0

    def step(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        if self.m is None:
            self.m, self.v = np.zeros_like(w), np.zeros_like(w)
        self.t += 1
        self.m = 0.9 * self.m + 0.1 * g
        self.v = 0.999 * self.v + 0.001 * g * g
        hat = (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)
        return w - self.rate * (hat + self.decay * w)


@dataclass
class Fit:
    """How to train."""

    epochs: int = 20
    rate: float = 1e-2
    decay: float = 1e-6
    sync: str = "epoch"  # or "step"
    patience: int = 6
    seed: int = 0
    #: Passes over a partition's batches in one job; averaging comes after all of them.
    passes: int = 1


def loss_of(model, batch: Packed, w: ParamStore, rng=None, kind: str = "binary") -> tuple[float, np.ndarray]:
    """Sum of the loss over the targets, and its gradient as a flat vector."""
    p = {k: Var(v) for k, v in w.items()}
    z = model.forward(batch, p, rng)
    if kind == "multiclass":
        loss = T.softmax_loss(z, batch.label)
    else:
        loss = (T.bce_with_logits if kind == "binary" else T.squared_loss)(T.reshape(z, -1), batch.label)
    T.backward(loss)
    g = ParamStore({k: p[k].grad if p[k].grad is not None else np.zeros_like(w[k]) for k in w})
    return float(loss.value), g.flat()


def predict_batch(model, batch: Packed, w: ParamStore) -> np.ndarray:
    return model.forward(batch, {k: Var(v) for k, v in w.items()}).value


@dataclass
class Trained:
    """A fitted model: scores packed batches, saves its parameters."""

    model: Rep | RowGnn
    params: ParamStore
    history: list[tuple[int, float, float]] = field(default_factory=list)
    seconds: float = 0.0
    kind: str = "binary"

    def score(self, packed: DataFrame) -> DataFrame:
        """key, part, label, logit, prob of every target."""
        model, flat, shape, kind = self.model, self.params.flat(), ParamStore({k: np.zeros_like(v) for k, v in self.params.items()}), self.kind
        shared = packed.sparkSession.sparkContext.broadcast((flat, shape))  # parameters only

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            w = shared.value[1].like(shared.value[0])
            for pdf in batches:
                for part, blob in zip(pdf.part, pdf.blob, strict=True):
                    batch, keys = unpack(blob)
                    z = predict_batch(model, batch, w)
                    logit = z[:, 0] if kind != "multiclass" else z.argmax(axis=1).astype(float)
                    yield pd.DataFrame({"key": keys, "part": part, "label": batch.label, "logit": logit, "prob": 1 / (1 + np.exp(-np.clip(logit, -60, 60)))})

        return packed.select("part", "blob").mapInPandas(run, "key string, part string, label double, logit double, prob double")

    def test_auc(self, packed: DataFrame) -> float:
        return auc(self.score(packed.filter("part = 'test'")), "logit", "label").first()["auc"]

    def save(self, spark, path: str) -> None:
        save_model(spark, path, self.params, {"model": type(self.model).__name__, "depth": self.model.depth, "d": self.model.d, "kind": self.kind})

    def restore(self, spark, path: str) -> Trained:
        return replace(self, params=load_model(spark, path)[0])


def fit(packed: DataFrame, model, how: Fit | None = None, kind: str = "binary") -> Trained:
    """Train on the batches of part train; keep the parameters that do best on part valid (AUC, or loss if not binary)."""
    how, began = how or Fit(), time.time()
    spark = packed.sparkSession
    w = model.init(how.seed)
    shape = ParamStore({k: np.zeros_like(v) for k, v in w.items()})
    train, valid = packed.filter("part = 'train'").select("worker", "blob"), packed.filter("part = 'valid'").select("blob")
    rate, decay, seed, passes = how.rate, how.decay, how.seed, how.passes if how.sync == "epoch" else 1
    opt, best, since, history = Adam(rate, decay), (-np.inf, w), 0, []

    def epoch(shared, number):
        def work(blobs: list[bytes]) -> tuple[int, float, np.ndarray, int]:
            """Targets seen, loss, and by row: parameters and moments times targets, or the gradient; steps taken."""
            p, seen, loss = shape.like(shared.value["w"]), 0, 0.0
            rng = np.random.default_rng((seed, number))
            a = Adam(rate, decay, *(x.copy() for x in shared.value["adam"])) if shared.value["adam"] else Adam(rate, decay)
            a.t = shared.value["t"]
            held = [unpack(b)[0] for b in blobs]
            grad = np.zeros(len(shared.value["w"]))
            for k in [k for _ in range(passes) for k in rng.permutation(len(held))]:
                value, g = loss_of(model, held[k], p, rng, kind)
                loss, n = loss + value, max(1, len(held[k].target))
                seen += n
                if shared.value["sync"] == "epoch":
                    p = p.like(a.step(p.flat(), g / n))
                else:
                    grad += g
            return seen, loss, np.stack([p.flat(), a.m, a.v]) * seen if shared.value["sync"] == "epoch" else grad[None], a.t

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            rows = ((w, b) for pdf in batches for w, b in zip(pdf.worker, pdf.blob, strict=True))
            done = [0, 0.0, 0.0, 0]
            for _, own in groupby(rows, key=lambda r: r[0]):
                seen, loss, state, t = work([b for _, b in own])
                done = [done[0] + seen, done[1] + loss, done[2] + state, max(done[3], t)]
            if done[0]:
                yield pd.DataFrame({"n": [done[0]], "loss": [done[1]], "state": [pickle.dumps((done[2], done[3]))]})

        return train.mapInPandas(run, "n long, loss double, state binary")

    for number in range(how.epochs):
        shared = spark.sparkContext.broadcast({"w": w.flat(), "sync": how.sync, "adam": (opt.m, opt.v) if opt.m is not None else None, "t": opt.t})
        got = [(r["n"], r["loss"], pickle.loads(r["state"])) for r in epoch(shared, number).collect()]  # a row a partition: sums of parameters
        n = sum(g[0] for g in got)
        if not n:
            break
        mean = sum(g[2][0] for g in got) / n
        if how.sync == "epoch":
            w = shape.like(mean[0])
            opt.m, opt.v, opt.t = mean[1], mean[2], max(g[2][1] for g in got)
        else:
            w = shape.like(opt.step(w.flat(), mean[0]))
        shared.unpersist()
        measure = _validate(valid, model, w, kind)
        history.append((number, sum(g[1] for g in got) / n, measure))
        if measure > best[0] or np.isnan(measure):
            best, since = (measure if not np.isnan(measure) else best[0], w), 0
        elif (since := since + 1) >= how.patience:
            break
    return Trained(model, best[1], history, time.time() - began, kind)


def _validate(valid: DataFrame, model, w: ParamStore, kind: str) -> float:
    df = Trained(model, w, kind=kind).score(valid.withColumn("part", F.lit("valid")))
    if kind == "binary":
        got = auc(df, "logit", "label").first()["auc"]
        return float("nan") if got is None else got
    if kind == "multiclass":
        return df.agg(F.avg((F.col("logit") == F.col("label")).cast("double"))).first()[0] or 0.0
    return -(df.agg(F.avg(F.pow(F.col("logit") - F.col("label"), 2))).first()[0] or 0.0)


def rep_model(coder: Coder, task: Task, depth: int, d: int = 16, row: str = "deepfm", head: str = "deepfm", dropout: float = 0.0, **more) -> Rep:
    options = {"widths": (2 * d,), "dropout": dropout}
    return Rep(coder.meta, task.target, depth, d, BlockSpec(row, options), BlockSpec(head, options), task.classes if task.kind == "multiclass" else 1, coder.deltas, **more)


def gnn_model(coder: Coder, task: Task, depth: int, backbone: str, d: int = 16, width: int = 64, dropout: float = 0.0) -> RowGnn:
    return RowGnn(coder.meta, task.target, depth, backbone, d, width, out=task.classes if task.kind == "multiclass" else 1, dropout=dropout)


def flat_task(task: Task, flat: DataFrame, categorical: set[str] | None = None) -> Task:
    """A one-table task over a flat table (target only, joined or rolled up)."""
    keys = list(task.keys)
    kinds = dict(flat.dtypes)
    cols = [c for c in flat.columns if c not in keys and c != task.label]
    safe = {c: f"x{i}" for i, c in enumerate(cols)}
    labels = task.catalog.frame(task.target).select(*[F.col(k).alias(f"_{k}") for k in keys], F.col(task.label))
    df = flat.select(*keys, *[F.col(f"`{c}`").alias(a) for c, a in safe.items()]).join(labels, [F.col(k) == F.col(f"_{k}") for k in keys]).drop(*[f"_{k}" for k in keys])
    text = [safe[c] for c in cols if kinds[c] == "string"]
    spec = TableSpec(task.target, tuple(keys), tuple(safe[c] for c in cols if safe[c] not in text), tuple(text))
    return Task(Catalog.build([spec], [], {task.target: df}), task.target, task.label, task.kind, task.classes, task.ratios, task.name)


def settled(task: Task) -> Task:
    """The task with its target rows and labels written once; what finds the labels is not run again by each use."""
    return Task(task.catalog.with_frames({task.target: kept(task.catalog.frame(task.target))}), task.target, task.label, task.kind, task.classes, task.ratios, task.name)


@dataclass
class Ready:
    """What runs over the same rows share: fitted codes, packed batches and the bytes shuffled for them."""

    coder: Coder
    packed: DataFrame
    shuffled: int


def prepare(task: Task, depth: int, batch_size: int = 512, coder: Coder | None = None) -> Ready:
    coder = coder or Coder.fit(task)
    spark = task.catalog.frame(task.target).sparkSession
    before = shuffle_written(spark)
    # Kept where they are packed: training needs a worker's batches together, and a checkpoint would pack them twice.
    packed = packed_batches(task, coder, depth, batch_size).persist(StorageLevel.DISK_ONLY)
    packed.count()
    return Ready(coder, packed, shuffle_written(spark) - before)


def run(task: Task, method: str, depth: int, how: Fit | None = None, flat: DataFrame | None = None, batch_size: int = 512, d: int = 16, ready: Ready | None = None, **options) -> tuple[Trained, RunReport, DataFrame]:
    """Pack, train, test.  ``method``: rep, rgcn, gat, hgt, or flat (with ``flat``).  ``ready``: of ``prepare`` with the same task and depth."""
    from .graph import tables_reached

    how = how or Fit()
    if method == "flat":
        task, depth = settled(flat_task(task, flat)), 0
    ready = ready or prepare(task, depth, batch_size)
    spark = task.catalog.frame(task.target).sparkSession
    coder, packed, before = ready.coder, ready.packed, shuffle_written(spark) - ready.shuffled
    model = gnn_model(coder, task, depth, method, d, **options) if method in ("rgcn", "gat", "hgt") else rep_model(coder, task, depth, d, **options)
    trained = fit(packed, model, how, task.kind)
    report = RunReport(task.name, method, depth, how.seed, trained.test_auc(packed) if task.kind == "binary" else float("nan"), trained.seconds, trained.seconds / max(1, len(trained.history)))
    report.tables_reached = tables_reached(task.catalog, task.target, depth)[depth]
    report.n_features = coder.meta[task.target].fields
    report.peak_rss, report.shuffle_bytes = peak_memory(), shuffle_written(spark) - before
    return trained, report, packed


def repeat(task: Task, method: str, depth: int, seeds: list[int], how: Fit | None = None, **more) -> list[RunReport]:
    """Reruns over seeds; summarise with ``metrics.summarise``."""
    how = how or Fit()
    return [run(task, method, depth, replace(how, seed=s), **more)[1] for s in seeds]


def local_auc(trained: Trained, batch: Packed) -> float:
    return auc_local(predict_batch(trained.model, batch, trained.params)[:, 0], batch.label)
