"""Single-table models over a stack of field vectors (rows x fields x d), usable for rows and as heads."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .. import tape as T
from ..tape import Var


def glorot(rng: np.random.Generator, a: int, b: int) -> np.ndarray:
    return rng.normal(0, np.sqrt(2 / (a + b)), (a, b))


class Block:
    """Contract of a plug-in: ``init`` names its parameters, ``forward`` is made of tape operations.

    ``out`` is d for a row block and p for a head.  ``p`` maps parameter names to variables.
    """

    def init(self, fields: int, d: int, out: int, rng: np.random.Generator) -> dict[str, np.ndarray]:
        raise NotImplementedError

    def forward(self, x: Var, p: dict[str, Var], rng: np.random.Generator | None = None) -> Var:
        raise NotImplementedError


@dataclass
class LinearBlock(Block):
    def init(self, fields, d, out, rng):
        return {"w": glorot(rng, max(1, fields * d), out)[: fields * d], "b": np.zeros(out)}

    def forward(self, x, p, rng=None):
        return T.reshape(x, x.shape[0], -1) @ p["w"] + p["b"] if x.shape[1] else Var(np.zeros((x.shape[0], 1))) + p["b"]


@dataclass
class MlpBlock(Block):
    widths: tuple[int, ...] = (32,)
    dropout: float = 0.0

    def init(self, fields, d, out, rng):
        sizes = [fields * d, *self.widths, out]
        return {k: v for i, (a, b) in enumerate(zip(sizes, sizes[1:], strict=False)) for k, v in ((f"w{i}", glorot(rng, a, b)), (f"b{i}", np.zeros(b)))}

    def forward(self, x, p, rng=None):
        h = T.reshape(x, x.shape[0], -1)
        for i in range(len(self.widths)):
            h = T.dropout(T.relu(h @ p[f"w{i}"] + p[f"b{i}"]), self.dropout, rng)
        n = len(self.widths)
        return h @ p[f"w{n}"] + p[f"b{n}"]


def pairwise(x: Var) -> Var:
    """Half of (square of the sum less the sum of squares): all products of two fields, summed, by component."""
    s, q = T.total(x, 1), T.total(x * x, 1)
    return (s * s - q) * 0.5


@dataclass
class FmBlock(Block):
    """First-order part and pairwise products; with out = 1 the scalar form, else a linear map of both."""

    def init(self, fields, d, out, rng):
        return {"w": glorot(rng, fields * d, out), "b": np.zeros(out)} | ({} if out == 1 else {"v": glorot(rng, d, out)})

    def forward(self, x, p, rng=None):
        q = pairwise(x)
        second = q @ p["v"] if "v" in p else T.reshape(T.total(q, 1), -1, 1)
        return T.reshape(x, x.shape[0], -1) @ p["w"] + second + p["b"]


@dataclass
class DeepFmBlock(Block):
    """Factorisation part and a deep part over the same vectors.  As a row block: a linear map of first-order part,
    pairwise vector and deep part."""

    widths: tuple[int, ...] = (32,)
    dropout: float = 0.0

    def init(self, fields, d, out, rng):
        w = FmBlock().init(fields, d, out, rng)
        sizes = [fields * d, *self.widths]
        for i, (a, b) in enumerate(zip(sizes, sizes[1:], strict=False)):
            w |= {f"dw{i}": glorot(rng, a, b), f"db{i}": np.zeros(b)}
        return w | {"do": glorot(rng, sizes[-1], out)}

    def forward(self, x, p, rng=None):
        h = T.reshape(x, x.shape[0], -1)
        for i in range(len(self.widths)):
            h = T.dropout(T.relu(h @ p[f"dw{i}"] + p[f"db{i}"]), self.dropout, rng)
        return FmBlock().forward(x, p) + h @ p["do"]


@dataclass
class FtBlock(Block):
    """Tokens of the fields behind a class token; pre-norm attention and gated feed-forward layers; read off the class token."""

    layers: int = 1
    heads: int = 2
    dropout: float = 0.0

    def init(self, fields, d, out, rng):
        w = {"cls": rng.normal(0, 0.1, (1, 1, d)), "og": np.ones(d), "os": np.zeros(d), "ow": glorot(rng, d, out), "ob": np.zeros(out)}
        for i in range(self.layers):
            w |= {f"{n}{i}": glorot(rng, d, d) for n in "qkvz"} | {f"f{i}": glorot(rng, d, 2 * d), f"u{i}": glorot(rng, d, 2 * d), f"e{i}": glorot(rng, 2 * d, d)}
            w |= {f"g{a}{i}": np.ones(d) for a in "ab"} | {f"s{a}{i}": np.zeros(d) for a in "ab"}
        return w

    def forward(self, x, p, rng=None):
        n, m, d = x.shape
        k = d // self.heads
        h = T.concat([p["cls"] * np.ones((n, 1, 1)), x], 1)

        def split(v: Var) -> Var:
            return T.transpose(T.reshape(v, n, m + 1, self.heads, k), 0, 2, 1, 3)

        for i in range(self.layers):
            y = h if i == 0 else T.layer_norm(h, p[f"ga{i}"], p[f"sa{i}"])  # the first norm is left out
            q, key, v = (split(y @ p[f"{c}{i}"]) for c in "qkv")
            a = T.softmax((q @ T.transpose(key, 0, 1, 3, 2)) * (1 / np.sqrt(k)))
            o = T.reshape(T.transpose(a @ v, 0, 2, 1, 3), n, m + 1, d) @ p[f"z{i}"]
            h = h + T.dropout(o, self.dropout, rng)
            y = T.layer_norm(h, p[f"gb{i}"], p[f"sb{i}"])
            h = h + T.dropout((T.relu(y @ p[f"f{i}"]) * (y @ p[f"u{i}"])) @ p[f"e{i}"], self.dropout, rng)
        return T.relu(T.layer_norm(T.pick(h, 0), p["og"], p["os"])) @ p["ow"] + p["ob"]


_REGISTRY: dict[str, type[Block]] = {"linear": LinearBlock, "mlp": MlpBlock, "fm": FmBlock, "deepfm": DeepFmBlock, "transformer": FtBlock}


def register_block(name: str, cls: type[Block]) -> None:
    """Make a user's block available by name."""
    _REGISTRY[name] = cls


def make_block(name: str, **options) -> Block:
    cls = _REGISTRY[name]
    known = getattr(cls, "__dataclass_fields__", {})
    return cls(**{k: v for k, v in options.items() if k in known})


@dataclass
class BlockSpec:
    """A block by name, so that it travels as plain data."""

    name: str
    options: dict = field(default_factory=dict)

    def make(self) -> Block:
        return make_block(self.name, **self.options)
