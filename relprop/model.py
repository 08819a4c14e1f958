"""Learned models over packed subgraphs: propagation, graph networks over rows, and flat tables.

A ``Packed`` holds, for a batch of targets, the coded features of every row in reach, the edges by local index, and the
targets' labels.  All models read the same packed batches, so only the message differs.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from . import tape as T
from .blocks import BlockSpec, MlpBlock, glorot
from .params import ParamStore
from .tape import Var


@dataclass
class TableMeta:
    """What a model must know of a table: features, sizes of dictionaries, relations."""

    name: str
    numeric: list[str]
    categorical: list[tuple[str, int, str]]  # (column, ids, domain)
    forward: list[tuple[str, str]]  # (foreign key, table referred to)
    backward: list[tuple[str, str]]  # (foreign key, table that refers)

    @property
    def own(self) -> int:
        return len(self.numeric) + len(self.categorical)

    @property
    def fields(self) -> int:
        return self.own + len(self.forward) + len(self.backward)


@dataclass
class Packed:
    numbers: dict[str, np.ndarray]  # table -> rows x numeric, NaN where missing
    codes: dict[str, np.ndarray]  # table -> rows x categorical
    parent: dict[str, np.ndarray]  # foreign key -> local row of the referred table, -1 without
    degree: dict[str, np.ndarray]  # foreign key -> true number of referring rows, by row of the referred table
    target: np.ndarray  # local rows of the target table
    label: np.ndarray
    part: np.ndarray = field(default_factory=lambda: np.zeros(0, dtype=object))

    def rows(self, table: str) -> int:
        return len(self.numbers[table])


def encoder_init(meta: dict[str, TableMeta], d: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
    w = {}
    for t in meta.values():
        for c in t.numeric:
            w |= {f"enc/{t.name}.{c}/w": rng.normal(0, 0.5, d), f"enc/{t.name}.{c}/b": rng.normal(0, 0.1, d), f"enc/{t.name}.{c}/miss": rng.normal(0, 0.1, d)}
        for _, n, domain in t.categorical:
            w.setdefault(f"cat/{domain}", rng.normal(0, 0.3, (n, d)))
    return w


def encode(t: TableMeta, batch: Packed, p: dict[str, Var]) -> list[Var]:
    out = []
    for i, c in enumerate(t.numeric):
        x = batch.numbers[t.name][:, i : i + 1]
        gone = np.isnan(x)
        v = T.relu(p[f"enc/{t.name}.{c}/w"] * np.where(gone, 0, x) + p[f"enc/{t.name}.{c}/b"])
        out.append(v * (~gone).astype(float) + p[f"enc/{t.name}.{c}/miss"] * gone.astype(float) if gone.any() else v)
    for i, (_, _, domain) in enumerate(t.categorical):
        out.append(T.gather(p[f"cat/{domain}"], batch.codes[t.name][:, i]))
    return out


def _rng(seed) -> np.random.Generator:
    return np.random.default_rng(seed)


@dataclass
class Rep:
    """Row-embedding propagation: one block a table, shared by all rounds; raw fields go into every message."""

    meta: dict[str, TableMeta]
    target: str
    depth: int
    d: int = 16
    row: BlockSpec = field(default_factory=lambda: BlockSpec("deepfm"))
    head: BlockSpec = field(default_factory=lambda: BlockSpec("deepfm"))
    out: int = 1
    deltas: dict[str, float] = field(default_factory=dict)
    stats: tuple[str, ...] = ("mean", "max", "min")
    scaled: bool = True
    skip: bool = True
    shared: bool = True
    #: Bounds a row block's output by tanh; the method has no such thing, long runs of quadratic blocks may want it.
    squash: bool = False

    def _names(self, k: int, table: str) -> str:
        return f"row/{table}" if self.shared else f"row{k}/{table}"

    def init(self, seed: int = 0) -> ParamStore:
        rng, w = _rng(seed), ParamStore()
        w.update(encoder_init(self.meta, self.d, rng))
        sides = len(self.stats) * (3 if self.scaled else 1)
        for t in self.meta.values():
            for fk, _ in t.backward:
                w[f"agg/{fk}"] = glorot(rng, sides * self.d, self.d)
            for k in [0] if self.shared else range(1, self.depth + 1):
                w.update({f"{self._names(k, t.name)}/{n}": v for n, v in self.row.make().init(max(1, t.fields), self.d, self.d, rng).items()})
        t = self.meta[self.target]
        w.update({f"head/{n}": v for n, v in self.head.make().init(max(1, t.fields), self.d, self.out, rng).items()})
        return w

    def _message(self, t: TableMeta, batch: Packed, h: dict[str, Var] | None, p: dict[str, Var], own: list[Var], only: np.ndarray | None = None) -> Var:
        """``only``: distinct local rows to which the message goes; None takes all."""
        n = batch.rows(t.name) if only is None else len(only)
        zero, at = Var(np.zeros((n, self.d)), fixed=True), slice(None) if only is None else only
        if only is not None:
            own = [T.gather(v, only) for v in own]
        fields = list(own) if self.skip or h is None else [zero] * len(own)
        for fk, other in t.forward:
            fields.append(T.gather(h[other], batch.parent[fk][at]) if h is not None else zero)
        for fk, other in t.backward:
            if h is None:
                fields.append(zero)
                continue
            seg = _placed(batch.parent[fk], batch.rows(t.name), only)
            have = np.flatnonzero(seg >= 0)
            x, seg, deg = T.gather(h[other], have), seg[have], batch.degree[fk][at][:, None]
            parts = {"mean": lambda: T.segment_mean(x, seg, n), "max": lambda: T.segment_extreme(x, seg, n, 1), "min": lambda: T.segment_extreme(x, seg, n, -1)}  # noqa: B023
            fields.append(self.relation(fk, [parts[s]() for s in self.stats], deg, p))
        return T.stack(fields or [zero], 1)

    def relation(self, fk: str, base: list[Var], deg: np.ndarray, p: dict[str, Var]) -> Var:
        """The vector of one relation from its summaries, scaled by degree."""
        if self.scaled:
            amp = np.log1p(deg) / self.deltas.get(fk, 1.0)
            base = base + [b * amp for b in base] + [b * np.where(deg > 0, 1 / np.maximum(amp, 1e-12), 0.0) for b in base]
        return T.concat(base, 1) @ p[f"agg/{fk}"]

    def forward(self, batch: Packed, p: dict[str, Var], rng: np.random.Generator | None = None) -> Var:
        need = self._need()
        own = {t.name: encode(t, batch, p) for t in self.meta.values() if t.name == self.target or any(t.name in s for s in need.values())}
        h: dict[str, Var] | None = None
        for k in range(1, self.depth + 1):
            new = {}
            for name in need[k]:
                t = self.meta[name]
                prefix = self._names(k, name) + "/"
                out = self.row.make().forward(self._message(t, batch, h, p, own[name]), _under(p, prefix), rng)
                new[name] = T.tanh(out) if self.squash else out
            h = new
        only, place = np.unique(batch.target, return_inverse=True)
        x = T.gather(self._message(self.meta[self.target], batch, h, p, own[self.target], only), place)
        return self.head.make().forward(x, _under(p, "head/"), rng)

    def _need(self) -> dict[int, set[str]]:
        need, now = {}, {self.target}
        for k in range(self.depth, 0, -1):
            now = {o for s in now for _, o in self.meta[s].forward + self.meta[s].backward}
            need[k] = now
        return need


def _placed(parent: np.ndarray, rows: int, only: np.ndarray | None) -> np.ndarray:
    """References to the rows of a table as places in ``only``, below zero for other rows; None leaves them."""
    if only is None:
        return parent
    place = np.full(rows + 1, -1)
    place[only] = np.arange(len(only))
    return place[parent]


def _under(p: dict[str, Var], prefix: str) -> dict[str, Var]:
    return {k[len(prefix) :]: v for k, v in p.items() if k.startswith(prefix)}


@dataclass
class RowGnn:
    """Rows as nodes, foreign keys as edges: an MLP gives first vectors, layers have parameters of their own, an MLP head
    reads the target's last vector.  Raw fields are not seen again."""

    meta: dict[str, TableMeta]
    target: str
    depth: int
    backbone: str = "rgcn"
    d: int = 16
    width: int = 64
    heads: int = 2
    out: int = 1
    dropout: float = 0.0

    def relations(self, table: str) -> list[tuple[str, str, str]]:
        """(name, foreign key, table the messages come from)."""
        t = self.meta[table]
        return [(fk + ">", fk, o) for fk, o in t.forward] + [(fk + "<", fk, o) for fk, o in t.backward]

    def init(self, seed: int = 0) -> ParamStore:
        rng, w, n = _rng(seed), ParamStore(), self.width
        w.update(encoder_init(self.meta, self.d, rng))
        k = n // self.heads
        for t in self.meta.values():
            w.update({f"init/{t.name}/{a}": v for a, v in MlpBlock((n,)).init(max(1, t.own), self.d, n, rng).items()})
            for layer in range(self.depth):
                at = f"l{layer}"
                w[f"{at}/self/{t.name}"] = glorot(rng, n, n)
                if self.backbone == "hgt":
                    w.update({f"{at}/{a}/{t.name}": glorot(rng, n, n) for a in "qkvo"} | {f"{at}/beta/{t.name}": np.zeros(1)})
                for r, _, _ in self.relations(t.name):
                    if self.backbone == "hgt":
                        w.update({f"{at}/att/{r}": rng.normal(0, 1 / np.sqrt(k), (self.heads, k, k)), f"{at}/msg/{r}": rng.normal(0, 1 / np.sqrt(k), (self.heads, k, k)), f"{at}/prior/{r}": np.ones(self.heads)})
                    else:
                        w[f"{at}/w/{r}"] = glorot(rng, n, n)
                    if self.backbone == "gat":
                        w.update({f"{at}/dst/{r}": glorot(rng, n, n), f"{at}/al/{r}": rng.normal(0, 0.3, (self.heads, k)), f"{at}/ar/{r}": rng.normal(0, 0.3, (self.heads, k))})
        w.update({f"head/{a}": v for a, v in MlpBlock((n,)).init(1, n, self.out, rng).items()})
        return w

    def _edges(self, batch: Packed, name: str, fk: str, table: str, only: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(source rows, destination rows), the latter as places in ``only`` where it is given."""
        if name.endswith(">"):
            parent = batch.parent[fk] if only is None else batch.parent[fk][only]
            child = np.flatnonzero(parent >= 0)
            return parent[child], child
        parent = _placed(batch.parent[fk], batch.rows(table), only)
        child = np.flatnonzero(parent >= 0)
        return child, parent[child]

    def layer(self, i: int, batch: Packed, h: dict[str, Var], p: dict[str, Var], table: str, only: np.ndarray | None = None) -> Var:
        """The next vectors of a table's rows; ``only``: distinct local rows, None takes all."""
        at, n, k = f"l{i}", batch.rows(table) if only is None else len(only), self.width // self.heads
        me = h[table] if only is None else T.gather(h[table], only)
        if self.backbone == "hgt":
            return self._hgt(at, batch, h, p, table, me, only)
        out = me @ p[f"{at}/self/{table}"]
        for r, fk, other in self.relations(table):
            src, dst = self._edges(batch, r, fk, table, only)
            z = T.gather(h[other] @ p[f"{at}/w/{r}"], src)
            if self.backbone == "rgcn":
                out = out + T.segment_mean(z, dst, n)
                continue
            z3 = T.reshape(z, len(src), self.heads, k)
            q3 = T.reshape(T.gather(me @ p[f"{at}/dst/{r}"], dst), len(dst), self.heads, k)
            score = T.leaky_relu(T.total(z3 * p[f"{at}/al/{r}"], 2) + T.total(q3 * p[f"{at}/ar/{r}"], 2))
            a = T.reshape(T.segment_softmax(score, dst, n), len(src), self.heads, 1)
            out = out + T.reshape(T.segment_sum(z3 * a, dst, n), n, self.width)
        return T.relu(out)

    def _hgt(self, at: str, batch: Packed, h: dict[str, Var], p: dict[str, Var], table: str, me: Var, only: np.ndarray | None) -> Var:
        n, k = len(me.value), self.width // self.heads
        split = lambda v, m: T.transpose(T.reshape(v, m, self.heads, k), 1, 0, 2)  # noqa: E731  heads x rows x k
        q = me @ p[f"{at}/q/{table}"]
        scores, values, dsts = [], [], []
        for r, fk, other in self.relations(table):
            src, dst = self._edges(batch, r, fk, table, only)
            m = len(src)
            key = split(T.gather(h[other] @ p[f"{at}/k/{other}"], src), m) @ p[f"{at}/att/{r}"]
            val = split(T.gather(h[other] @ p[f"{at}/v/{other}"], src), m) @ p[f"{at}/msg/{r}"]
            s = T.total(key * split(T.gather(q, dst), m), 2) * T.reshape(p[f"{at}/prior/{r}"], self.heads, 1) * (1 / np.sqrt(k))
            scores.append(T.transpose(s, 1, 0))
            values.append(T.transpose(val, 1, 0, 2))
            dsts.append(dst)
        if not scores or not sum(map(len, dsts)):
            return me
        dst = np.concatenate(dsts)
        a = T.segment_softmax(T.concat(scores, 0), dst, n)  # over all incoming edges of a row, whatever their type
        msg = T.segment_sum(T.concat(values, 0) * T.reshape(a, len(dst), self.heads, 1), dst, n)
        new = T.gelu(T.reshape(msg, n, self.width)) @ p[f"{at}/o/{table}"]
        g = T.sigmoid(p[f"{at}/beta/{table}"])
        return new * g + me * (Var(1.0) - g)

    def _need(self) -> list[set[str]]:
        """By layer, the tables whose vectors before it are used: the target and what lies within the layers to come."""
        need = [{self.target}]
        for _ in range(self.depth):
            need.insert(0, need[0] | {o for s in need[0] for _, _, o in self.relations(s)})
        return need

    def forward(self, batch: Packed, p: dict[str, Var], rng: np.random.Generator | None = None, trace: list | None = None) -> Var:
        """``trace``: takes all tables' vectors of all layers, which else are worked out as far as the target's last ones need them."""
        h, need = {}, self._need() if trace is None else [set(self.meta)] * (self.depth + 1)
        only, place = np.unique(batch.target, return_inverse=True)
        for t in [self.meta[name] for name in self.meta if name in need[0]]:
            own = encode(t, batch, p) or [Var(np.zeros((batch.rows(t.name), self.d)))]
            h[t.name] = MlpBlock((self.width,), self.dropout).forward(T.stack(own, 1), _under(p, f"init/{t.name}/"), rng)
        for i in range(self.depth):
            if trace is not None:
                trace.append({t: v.value for t, v in h.items()})
            last = trace is None and i == self.depth - 1
            h = {t: self.layer(i, batch, h, p, t, only if last else None) for t in self.meta if t in need[i + 1]}
        if trace is not None:
            trace.append({t: v.value for t, v in h.items()})
        x = T.gather(h[self.target], place if trace is None and self.depth else batch.target)
        return MlpBlock((self.width,), self.dropout).forward(T.reshape(x, len(batch.target), 1, self.width), _under(p, "head/"), rng)


def smoothing(trace: list[dict[str, np.ndarray]], table: str) -> list[float]:
    """Spread of a table's vectors by layer: variance over second moment."""
    return [float(v[table].var(axis=0).sum() / max(1e-300, (v[table] ** 2).mean(axis=0).sum())) for v in trace]
