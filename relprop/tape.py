"""A small reverse-mode tape over numpy arrays."""

from __future__ import annotations

import numpy as np


class Var:
    """A value on a tape, with its gradient once ``backward`` has run."""

    __slots__ = ("value", "grad", "_back", "fixed")

    def __init__(self, value, back=(), fixed: bool = False):
        self.value = np.asarray(value, float)
        self.grad: np.ndarray | None = None
        self.fixed = fixed  # a constant: no gradient is worked out for it
        self._back = tuple(b for b in back if not b[0].fixed)  # pairs (input, gradient of output -> gradient of input)

    @property
    def shape(self):
        return self.value.shape

    def __add__(self, o):
        o = as_var(o)
        return Var(self.value + o.value, ((self, lambda g: _fit(g, self.shape)), (o, lambda g: _fit(g, o.shape))))

    def __sub__(self, o):
        o = as_var(o)
        return Var(self.value - o.value, ((self, lambda g: _fit(g, self.shape)), (o, lambda g: _fit(-g, o.shape))))

    def __mul__(self, o):
        o = as_var(o)
        return Var(self.value * o.value, ((self, lambda g: _fit(g * o.value, self.shape)), (o, lambda g: _fit(g * self.value, o.shape))))

    __radd__, __rmul__ = __add__, __mul__

    def __matmul__(self, o):
        a, b = self.value, o.value
        return Var(a @ b, ((self, lambda g: _fit(g @ np.swapaxes(b, -1, -2), a.shape)), (o, lambda g: _fit(np.swapaxes(a, -1, -2) @ g, b.shape))))


def as_var(x) -> Var:
    return x if isinstance(x, Var) else Var(x, fixed=True)


def _fit(g: np.ndarray, shape: tuple) -> np.ndarray:
    """Undo broadcasting."""
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def backward(out: Var) -> None:
    order, seen, todo = [], set(), [(out, False)]
    while todo:
        v, done = todo.pop()
        if done:
            order.append(v)
        elif id(v) not in seen:
            seen.add(id(v))
            todo.append((v, True))
            todo.extend((i, False) for i, _ in v._back)
    out.grad = np.ones_like(out.value)
    for v in reversed(order):
        if v.grad is None:
            continue
        for i, f in v._back:
            g = f(v.grad)
            i.grad = g if i.grad is None else i.grad + g


def relu(x: Var) -> Var:
    m = x.value > 0
    return Var(x.value * m, ((x, lambda g: g * m),))


def leaky_relu(x: Var, slope: float = 0.2) -> Var:
    m = np.where(x.value > 0, 1.0, slope)
    return Var(x.value * m, ((x, lambda g: g * m),))


def sigmoid(x: Var) -> Var:
    s = 1 / (1 + np.exp(-np.clip(x.value, -60, 60)))
    return Var(s, ((x, lambda g: g * s * (1 - s)),))


def tanh(x: Var) -> Var:
    t = np.tanh(x.value)
    return Var(t, ((x, lambda g: g * (1 - t * t)),))


def gelu(x: Var) -> Var:
    """The tanh form."""
    k, v = np.sqrt(2 / np.pi), x.value
    t = np.tanh(k * (v + 0.044715 * v**3))
    d = 0.5 * (1 + t) + 0.5 * v * (1 - t * t) * k * (1 + 3 * 0.044715 * v * v)
    return Var(0.5 * v * (1 + t), ((x, lambda g: g * d),))


def reshape(x: Var, *shape: int) -> Var:
    return Var(x.value.reshape(shape), ((x, lambda g: g.reshape(x.shape)),))


def transpose(x: Var, *axes: int) -> Var:
    return Var(x.value.transpose(axes), ((x, lambda g: g.transpose(np.argsort(axes))),))


def concat(xs: list[Var], axis: int) -> Var:
    at = np.cumsum([0, *[x.shape[axis] for x in xs]])
    cut = lambda i: (lambda g: np.take(g, np.arange(at[i], at[i + 1]), axis=axis))
    return Var(np.concatenate([x.value for x in xs], axis=axis), tuple((x, cut(i)) for i, x in enumerate(xs)))


def stack(xs: list[Var], axis: int) -> Var:
    return Var(np.stack([x.value for x in xs], axis=axis), tuple((x, (lambda i: lambda g: np.take(g, i, axis=axis))(i)) for i, x in enumerate(xs)))


def pick(x: Var, index, axis: int = 1) -> Var:
    """One slice along an axis."""

    def back(g):
        out = np.zeros_like(x.value)
        at = [slice(None)] * x.value.ndim
        at[axis] = index
        out[tuple(at)] = g
        return out

    return Var(np.take(x.value, index, axis=axis), ((x, back),))


def total(x: Var, axis: int | None = None) -> Var:
    return Var(x.value.sum(axis=axis), ((x, lambda g: np.broadcast_to(g if axis is None else np.expand_dims(g, axis), x.shape).copy()),))


def scatter_sum(x: np.ndarray, seg: np.ndarray, n: int) -> np.ndarray:
    """Rows summed by segment, in their order; counting by weight is several times as fast as adding at indices."""
    shape = x.shape[1:]
    flat = x.reshape(len(x), int(np.prod(shape)))
    c = flat.shape[1]
    if c <= 16:
        out = np.stack([np.bincount(seg, flat[:, j], n) for j in range(c)], 1) if c else np.zeros((n, 0))
    else:
        out = np.bincount((seg[:, None] * c + np.arange(c)).ravel(), flat.ravel(), n * c)
    return out.reshape(n, *shape)


def scatter_max(x: np.ndarray, seg: np.ndarray, n: int) -> np.ndarray:
    """The largest of each segment, minus infinity where there is none."""
    top = np.full((n, *x.shape[1:]), -np.inf)
    if len(seg):
        if (seg[1:] < seg[:-1]).any():
            order = np.argsort(seg, kind="stable")
            x, seg = x[order], seg[order]
        first = np.flatnonzero(np.concatenate([[True], seg[1:] != seg[:-1]]))
        top[seg[first]] = np.maximum.reduceat(x, first, axis=0)
    return top


def gather(x: Var, rows: np.ndarray) -> Var:
    """Rows by index; an index below zero gives a zero row."""
    ok = rows >= 0
    if ok.all():
        if (rows[1:] > rows[:-1]).all():  # no row twice
            if len(rows) == len(x.value):
                return x

            def back(g):
                out = np.zeros_like(x.value)
                out[rows] = g
                return out

            return Var(x.value[rows], ((x, back),))
        return Var(x.value[rows], ((x, lambda g: scatter_sum(g, rows, len(x.value))),))
    value = np.where(ok.reshape(-1, *[1] * (x.value.ndim - 1)), x.value[np.maximum(rows, 0)] if len(x.value) else 0.0, 0.0) if len(x.value) else np.zeros((len(rows), *x.shape[1:]))
    return Var(value, ((x, lambda g: scatter_sum(g[ok], rows[ok], len(x.value))),))


def segment_sum(x: Var, seg: np.ndarray, n: int) -> Var:
    return Var(scatter_sum(x.value, seg, n), ((x, lambda g: g[seg]),))


def segment_mean(x: Var, seg: np.ndarray, n: int) -> Var:
    inv = 1 / np.maximum(np.bincount(seg, minlength=n), 1)
    return segment_sum(x, seg, n) * Var(inv.reshape(-1, *[1] * (x.value.ndim - 1)))


def segment_extreme(x: Var, seg: np.ndarray, n: int, sign: int) -> Var:
    """Element-wise maximum (sign 1) or minimum (sign -1); zero for empty segments; ties share the gradient."""
    v = sign * x.value
    top = scatter_max(v, seg, n)
    hit = v == top[seg]
    share = scatter_sum(hit.astype(float), seg, n)
    return Var(np.where(np.isfinite(top), sign * top, 0.0), ((x, lambda g: np.where(hit, (g / np.maximum(share, 1))[seg], 0.0)),))


def segment_softmax(s: Var, seg: np.ndarray, n: int) -> Var:
    """Softmax of scores within each segment."""
    e = np.exp(s.value - scatter_max(s.value, seg, n)[seg])
    a = e / scatter_sum(e, seg, n)[seg]
    return Var(a, ((s, lambda g: a * (g - scatter_sum(g * a, seg, n)[seg])),))


def softmax(x: Var) -> Var:
    e = np.exp(x.value - x.value.max(axis=-1, keepdims=True))
    a = e / e.sum(axis=-1, keepdims=True)
    return Var(a, ((x, lambda g: a * (g - (g * a).sum(axis=-1, keepdims=True))),))


def layer_norm(x: Var, gain: Var, shift: Var, eps: float = 1e-5) -> Var:
    c = x.value - x.value.mean(axis=-1, keepdims=True)
    inv = 1 / np.sqrt((c * c).mean(axis=-1, keepdims=True) + eps)
    n = c * inv

    def back(g):
        return inv * (g - g.mean(axis=-1, keepdims=True) - n * (g * n).mean(axis=-1, keepdims=True))

    return Var(n, ((x, back),)) * gain + shift


def dropout(x: Var, rate: float, rng: np.random.Generator | None) -> Var:
    if rng is None or rate <= 0:
        return x
    m = (rng.random(x.shape) >= rate) / (1 - rate)
    return Var(x.value * m, ((x, lambda g: g * m),))


def bce_with_logits(z: Var, y: np.ndarray) -> Var:
    """Sum over rows of the binary cross-entropy."""
    v = z.value
    loss = np.maximum(v, 0) - v * y + np.log1p(np.exp(-np.abs(v)))
    s = 1 / (1 + np.exp(-np.clip(v, -60, 60)))
    return Var(loss.sum(), ((z, lambda g: g * (s - y)),))


def softmax_loss(z: Var, y: np.ndarray) -> Var:
    """Sum over rows of the cross-entropy of class numbers."""
    e = z.value - z.value.max(axis=1, keepdims=True)
    p = np.exp(e) / np.exp(e).sum(axis=1, keepdims=True)
    hot = np.eye(z.shape[1])[y.astype(int)]
    return Var(-np.log(np.maximum(p, 1e-300))[np.arange(len(y)), y.astype(int)].sum(), ((z, lambda g: g * (p - hot)),))


def squared_loss(z: Var, y: np.ndarray) -> Var:
    d = z.value - y
    return Var((d * d).sum(), ((z, lambda g: 2 * g * d),))
