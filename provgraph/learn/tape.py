"""A small reverse-mode tape over numpy arrays, enough for the encoders here."""
from __future__ import annotations

import numpy as np


class Var:
    """A value with what it came from; ``fixed`` ones depend on no weight, so no gradient is worked out for them."""

    def __init__(self, value, parents=(), fixed=False):
        self.value = np.asarray(value)
        if self.value.dtype != np.float32:  # single precision stays, all else is double
            self.value = self.value.astype(np.float64, copy=False)
        self.parents = tuple((p, f) for p, f in parents if not p.fixed)
        self.fixed, self.grad = fixed or bool(parents) and not self.parents, None

    def __add__(self, o):
        o = as_var(o, self.value.dtype)
        return Var(self.value + o.value, ((self, lambda g: fit(g, self.value.shape)), (o, lambda g: fit(g, o.value.shape))))

    def __mul__(self, o):
        o = as_var(o, self.value.dtype)
        return Var(self.value * o.value, ((self, lambda g: fit(g * o.value, self.value.shape)), (o, lambda g: fit(g * self.value, o.value.shape))))

    def __sub__(self, o):
        return self + as_var(o, self.value.dtype) * -1.0

    def __matmul__(self, o):
        return Var(self.value @ o.value, ((self, lambda g: g @ o.value.T), (o, lambda g: self.value.T @ g)))

    def backward(self) -> None:
        order, seen = [], set()

        def visit(v):
            if id(v) not in seen:
                seen.add(id(v))
                for p, _ in v.parents:
                    visit(p)
                order.append(v)

        visit(self)
        for v in order:
            v.grad = None
        self.grad = np.ones_like(self.value)
        for v in reversed(order):
            for p, f in v.parents:
                g = f(v.grad)
                p.grad = g if p.grad is None else p.grad + g


def const(x) -> Var:
    return Var(x, fixed=True)


def as_var(x, kind=np.float64) -> Var:
    """A number takes the precision of what it meets."""
    return x if isinstance(x, Var) else const(np.asarray(x, kind) if isinstance(x, (int, float)) else x)


def fit(g: np.ndarray, shape: tuple) -> np.ndarray:
    """Sums out what broadcasting added."""
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def unary(x: Var, value: np.ndarray, slope: np.ndarray) -> Var:
    return Var(value, ((x, lambda g: g * slope),))


def relu(x: Var, leak: float = 0.0) -> Var:
    s = np.where(x.value > 0, 1.0, leak).astype(x.value.dtype) if leak else x.value > 0
    return unary(x, x.value * s if leak else np.maximum(x.value, 0), s)


def tanh(x: Var) -> Var:
    t = np.tanh(x.value)
    return unary(x, t, 1 - t * t)


def exp(x: Var) -> Var:
    e = np.exp(np.minimum(x.value, 50))
    return unary(x, e, e)


def reciprocal(x: Var) -> Var:
    return unary(x, 1 / x.value, -1 / x.value**2)


def _runs(at: np.ndarray) -> tuple[np.ndarray | None, np.ndarray, np.ndarray]:
    """An order that sorts ``at`` (None: it is sorted), the starts of its runs and their numbers."""
    order = None if (at[1:] >= at[:-1]).all() else np.argsort(at, kind="stable")
    at = at if order is None else at[order]
    starts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    return order, starts, at[starts]


class Slots:
    """Segment numbers of rows in an order of their own: the first row of every segment, then every second one, and so on.

    ``order`` takes the rows there, ``at`` are their segments; sums are then additions of whole stretches.  A
    segment of many rows would make as many stretches: beyond MOST the rows are in order of their segments.
    """

    MOST = 64

    def __init__(self, at: np.ndarray, n: int):
        count = np.bincount(at, minlength=n)
        self.order, self.sizes, self.rank = np.argsort(at, kind="stable"), None, None
        if len(at) and count.max() <= self.MOST:
            by_size = np.argsort(-count, kind="stable")
            self.rank = np.empty(n, np.int64)
            self.rank[by_size] = np.arange(n)
            own = at[self.order]
            slot = np.arange(len(at)) - (np.cumsum(count) - count)[own]
            self.order, self.sizes = self.order[np.lexsort((self.rank[own], slot))], np.bincount(slot)
        self.at = at[self.order]


def reduced(how: np.ufunc, x: np.ndarray, at: np.ndarray | Slots, n: int, empty: float = 0.0) -> np.ndarray:
    """``how`` over the rows of ``x`` by segment number; segments without rows are ``empty``, which ``how`` leaves others unchanged by."""
    out = np.full((n, *x.shape[1:]), empty, x.dtype)
    if isinstance(at, Slots):
        if at.sizes is not None:
            i = 0
            for m in at.sizes:
                how(out[:m], x[i : i + m], out=out[:m])
                i += m
            return out.take(at.rank, axis=0)
        at = at.at
    if len(at):
        order, starts, found = _runs(at)
        out[found] = how.reduceat(x if order is None else x[order], starts, axis=0)
    return out


def _numbers(at: np.ndarray | Slots) -> np.ndarray:
    return at.at if isinstance(at, Slots) else at


def spread(x: Var, pick: np.ndarray, back: Slots) -> Var:
    """The rows of x that ``pick`` numbers; ``back``: the same numbers as slots, for the sums back."""
    return Var(x.value.take(pick, axis=0), ((x, lambda g: reduced(np.add, g.take(back.order, axis=0), back, len(x.value))),))


def rows(x: Var, at: np.ndarray | Slots) -> Var:
    return Var(x.value.take(_numbers(at), axis=0), ((x, lambda g: reduced(np.add, g, at, len(x.value))),))


def segments(x: Var, at: np.ndarray | Slots, n: int, share: np.ndarray | None = None) -> Var:
    """Sums of the rows of x, times a constant column ``share``, by segment number."""
    numbers = _numbers(at)
    if share is None:
        return Var(reduced(np.add, x.value, at, n), ((x, lambda g: g.take(numbers, axis=0)),))
    return Var(reduced(np.add, x.value * share, at, n), ((x, lambda g: g.take(numbers, axis=0) * share),))


def stack(parts: list[Var]) -> Var:
    """Matrices one below the other."""
    ends = np.cumsum([0] + [len(p.value) for p in parts])
    return Var(np.vstack([p.value for p in parts]), tuple((p, lambda g, a=a, b=b: g[a:b]) for p, a, b in zip(parts, ends, ends[1:])))


def cut_rows(x: Var, a: int, b: int) -> Var:
    def back(g):
        out = np.zeros_like(x.value)
        out[a:b] = g
        return out

    return Var(x.value[a:b], ((x, back),))


def columns(parts: list[Var]) -> Var:
    ends = np.cumsum([0] + [p.value.shape[1] for p in parts])
    return Var(np.hstack([p.value for p in parts]), tuple((p, lambda g, a=a, b=b: g[:, a:b]) for p, a, b in zip(parts, ends, ends[1:])))


def row_sum(x: Var) -> Var:
    return Var(x.value.sum(axis=1, keepdims=True), ((x, lambda g: np.broadcast_to(g, x.value.shape)),))


def total(x: Var) -> Var:
    return Var(x.value.sum(), ((x, lambda g: np.full_like(x.value, g)),))


def softmax_over(scores: list[Var], ats: list, n: int) -> list[Var]:
    """Softmax of the parts' columns together inside each segment."""
    kind = scores[0].value.dtype
    top = np.full((n, 1), -np.inf, kind)
    for s, at in zip(scores, ats):
        top = np.maximum(top, reduced(np.maximum, s.value, at, n, -np.inf))
    es = [exp(s - const(top.take(_numbers(at), axis=0))) for s, at in zip(scores, ats)]
    whole = const(np.full((n, 1), 1e-12, kind))
    for e, at in zip(es, ats):
        whole = whole + segments(e, at, n)
    share = reciprocal(whole)
    return [e * rows(share, at) for e, at in zip(es, ats)]


def softmax_by(score: Var, at: np.ndarray | Slots, n: int) -> Var:
    """Softmax of a column of scores inside each segment."""
    return softmax_over([score], [at], n)[0]


def squared_error(out: Var, y: np.ndarray) -> Var:
    d = out - const(y[:, None].astype(out.value.dtype))
    return total(d * d)


def cross_entropy(out: Var, y: np.ndarray) -> Var:
    z = out.value - out.value.max(axis=1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(axis=1, keepdims=True)
    hit = p.copy()
    hit[np.arange(len(y)), y] -= 1
    return Var(-np.log(p[np.arange(len(y)), y] + 1e-12).sum(), ((out, lambda g: g * hit),))


def logistic(out: Var, y: np.ndarray) -> Var:
    z = np.clip(out.value[:, 0], -30, 30)
    p = 1 / (1 + np.exp(-z))
    return Var((np.logaddexp(0, z) - y * z).sum(), ((out, lambda g: (g * (p - y)[:, None]).astype(out.value.dtype)),))
