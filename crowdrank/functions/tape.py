"""A small reverse-mode differentiation tape over numpy arrays.

Kernels of the models are written forward only; gradients follow from the operations they used and
are held against central differences in the tests.
"""

from __future__ import annotations

import numpy as np


def _fold(grad: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Sum a gradient over the axes that broadcasting added."""
    while grad.ndim > len(shape):
        grad = grad.sum(0)
    for i, n in enumerate(shape):
        if n == 1 and grad.shape[i] != 1:
            grad = grad.sum(i, keepdims=True)
    return grad


class Var:
    __slots__ = ("back", "data", "grad", "parents")

    def __init__(self, data, parents: tuple = (), back=None) -> None:
        self.data, self.parents, self.back, self.grad = np.asarray(data, np.float64), parents, back, None

    @property
    def shape(self) -> tuple[int, ...]:
        return self.data.shape

    def backward(self) -> None:
        order, seen, todo = [], set(), [(self, False)]
        while todo:
            v, done = todo.pop()
            if done:
                order.append(v)
            elif id(v) not in seen:
                seen.add(id(v))
                todo.append((v, True))
                todo.extend((p, False) for p in v.parents)
        self.grad = np.ones_like(self.data)
        for v in reversed(order):
            if v.back and v.grad is not None:
                for p, g in zip(v.parents, v.back(v.grad), strict=True):
                    if g is not None:
                        g = g if g.shape == p.data.shape else _fold(g, p.data.shape)
                        p.grad = g if p.grad is None else p.grad + g

    def __add__(self, o):
        o = var(o)
        return Var(self.data + o.data, (self, o), lambda g: (g, g))

    def __sub__(self, o):
        o = var(o)
        return Var(self.data - o.data, (self, o), lambda g: (g, -g))

    def __mul__(self, o):
        o = var(o)
        return Var(self.data * o.data, (self, o), lambda g: (g * o.data, g * self.data))

    __radd__, __rmul__ = __add__, __mul__

    def __neg__(self):
        return self * -1.0

    def __matmul__(self, o):
        o = var(o)
        if o.data.ndim == 2 < self.data.ndim:  # one product of all rows, and no matrix a batch on the way back
            flat = self.data.reshape(-1, self.data.shape[-1])

            def whole(g):
                rows = g.reshape(len(flat), -1)
                return (rows @ o.data.T).reshape(self.data.shape), flat.T @ rows

            return Var((flat @ o.data).reshape(*self.data.shape[:-1], o.data.shape[1]), (self, o), whole)

        def back(g):
            return g @ np.swapaxes(o.data, -1, -2), np.swapaxes(self.data, -1, -2) @ g

        return Var(self.data @ o.data, (self, o), back)

    def sum(self, axis=None, keep: bool = False):
        def back(g):
            return (np.broadcast_to(g if keep or axis is None else np.expand_dims(g, axis), self.data.shape),)

        return Var(self.data.sum(axis, keepdims=keep), (self,), back)

    def reshape(self, *shape):
        return Var(self.data.reshape(*shape), (self,), lambda g: (g.reshape(self.data.shape),))

    def swap(self, a: int, b: int):
        return Var(np.swapaxes(self.data, a, b), (self,), lambda g: (np.swapaxes(g, a, b),))

    @property
    def T(self):
        return self.swap(-1, -2)

    def rows(self, index: np.ndarray):
        """Rows of a table, e.g. vectors of ids; gradients add up by row."""

        def back(g):
            out = np.zeros_like(self.data)
            at, total = summed(np.ravel(index), g.reshape(-1, *self.data.shape[1:]))
            out[at] = total
            return (out,)

        return Var(self.data[index], (self,), back)


class Table(Var):
    """A table of which a step touches few rows: gradients are kept for these rows only."""

    __slots__ = ("parts",)

    def __init__(self, data) -> None:
        super().__init__(data)
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []

    def rows(self, index: np.ndarray):
        def back(g):
            self.parts.append((np.ravel(index), g.reshape(-1, *self.data.shape[1:])))
            return (None,)

        return Var(self.data[index], (self,), back)

    def touched(self) -> tuple[np.ndarray, np.ndarray]:
        """The rows that got a gradient, and their gradients."""
        if not self.parts:
            return np.zeros(0, np.int64), np.zeros((0, *self.data.shape[1:]))
        return summed(*(np.concatenate(x) for x in zip(*self.parts, strict=True)))


def summed(index: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different numbers of ``index``, and the sum of ``g`` over each."""
    if len(index) and 0 <= index.min() and index.max() < 1 << 16:  # short numbers are sorted by digits
        order = np.argsort(index.astype(np.uint16), kind="stable")
    else:
        order = np.argsort(index, kind="stable")
    s = index[order]
    start = np.flatnonzero(np.append(True, s[1:] != s[:-1])[: len(s)])
    return s[start], np.add.reduceat(g[order], start) if len(s) else g[order]


def var(x) -> Var:
    return x if isinstance(x, Var) else Var(x)


def relu(x: Var) -> Var:
    return Var(np.maximum(x.data, 0), (x,), lambda g: (g * (x.data > 0),))


def tanh(x: Var) -> Var:
    y = np.tanh(x.data)
    return Var(y, (x,), lambda g: (g * (1 - y**2),))


def exp(x: Var) -> Var:
    y = np.exp(x.data)
    return Var(y, (x,), lambda g: (g * y,))


def log_sigmoid(x: Var) -> Var:
    y = -np.logaddexp(0, -x.data)
    return Var(y, (x,), lambda g: (g * -np.expm1(y),))


def shares(z: np.ndarray, mask: np.ndarray | None = None) -> np.ndarray:
    """Softmax over the last axis; masked places get 0 (a row without places is all 0)."""
    z = z if mask is None else np.where(mask, z, -np.inf)
    top = z.max(-1, keepdims=True)
    e = np.exp(z - np.where(np.isfinite(top), top, 0))
    return e / np.maximum(e.sum(-1, keepdims=True), 1e-300)


def softmax(x: Var, mask: np.ndarray | None = None) -> Var:
    """``shares`` with their gradient."""
    y = shares(x.data, mask)
    return Var(y, (x,), lambda g: (y * (g - (g * y).sum(-1, keepdims=True)),))


def concat(parts: list[Var]) -> Var:
    """Along the last axis."""
    cuts = np.cumsum([p.data.shape[-1] for p in parts])[:-1]
    return Var(np.concatenate([p.data for p in parts], -1), tuple(parts), lambda g: tuple(np.split(g, cuts, -1)))


def stack(parts: list[Var], axis: int = 0) -> Var:
    return Var(np.stack([p.data for p in parts], axis), tuple(parts), lambda g: tuple(np.moveaxis(g, axis, 0)))


def normalise(x: Var) -> Var:
    """To unit length over the last axis; a zero row stays zero."""
    n = np.sqrt((x.data**2).sum(-1, keepdims=True))
    n = np.where(n > 0, n, 1.0)
    y = x.data / n
    return Var(y, (x,), lambda g: ((g - y * (g * y).sum(-1, keepdims=True)) / n,))
