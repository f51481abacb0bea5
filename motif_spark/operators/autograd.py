"""Reverse-mode gradients over numpy arrays, for the operations that the network needs."""

from __future__ import annotations

from contextlib import contextmanager

import numpy as np


#: Training and search use single precision; gradients are checked in double.
DTYPE = np.float64


@contextmanager
def precision(kind):
    """Within it, tensors hold numbers of this kind."""
    global DTYPE
    before, DTYPE = DTYPE, kind
    try:
        yield
    finally:
        DTYPE = before


class Tensor:
    """An array that remembers how it was made."""

    __slots__ = ("value", "grad", "parents", "back", "needs")

    def __init__(self, value, parents=(), back=None, needs=False):
        self.value = np.asarray(value, DTYPE)
        self.needs = needs or any(p.needs for p in parents)
        self.grad, self.parents, self.back = None, parents, back

    def backward(self) -> None:
        order, seen = [], set()
        todo = [(self, False)]
        while todo:
            t, ready = todo.pop()
            if ready:
                order.append(t)
            elif id(t) not in seen:
                seen.add(id(t))
                todo.append((t, True))
                todo.extend((p, False) for p in t.parents if p.needs)
        self.grad = np.ones_like(self.value)
        for t in reversed(order):
            if t.back is not None and t.grad is not None:
                for p, g in zip(t.parents, t.back(t.grad)):
                    if g is not None and p.needs:
                        g = _fit(g, p.value.shape)
                        p.grad = g if p.grad is None else p.grad + g

    def __add__(self, o):
        o = tensor(o)
        return Tensor(self.value + o.value, (self, o), lambda g: (g, g))

    def __sub__(self, o):
        o = tensor(o)
        return Tensor(self.value - o.value, (self, o), lambda g: (g, -g))

    def __mul__(self, o):
        o = tensor(o)
        return Tensor(self.value * o.value, (self, o), lambda g: (g * o.value if self.needs else None, g * self.value if o.needs else None))

    def __matmul__(self, o):
        o = tensor(o)
        if self.value.ndim > 2 and o.value.ndim == 2:
            return self._times_table(o)
        turn = lambda x: np.swapaxes(x, -1, -2)
        return Tensor(self.value @ o.value, (self, o), lambda g: (g @ turn(o.value) if self.needs else None, turn(self.value) @ g if o.needs else None))

    def _times_table(self, o: Tensor) -> Tensor:
        """A stack of matrices times one matrix, as one flat product."""
        lead, flat = self.value.shape[:-1], self.value.reshape(-1, self.value.shape[-1])

        def back(g):
            g = g.reshape(-1, g.shape[-1])
            return (g @ o.value.T).reshape(self.value.shape) if self.needs else None, flat.T @ g if o.needs else None

        return Tensor((flat @ o.value).reshape(*lead, -1), (self, o), back)

    __radd__, __rmul__ = __add__, __mul__

    def __neg__(self):
        return self * -1.0


def tensor(x) -> Tensor:
    return x if isinstance(x, Tensor) else Tensor(x)


def _fit(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Sum a gradient over the axes that were broadcast."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for axis, n in enumerate(shape):
        if n == 1 and g.shape[axis] != 1:
            g = g.sum(axis, keepdims=True)
    return g


def relu(x: Tensor) -> Tensor:
    return Tensor(np.maximum(x.value, 0), (x,), lambda g: (g * (x.value > 0),))


def sigmoid(x: Tensor) -> Tensor:
    s = 1 / (1 + np.exp(-np.clip(x.value, -60, 60)))
    return Tensor(s, (x,), lambda g: (g * s * (1 - s),))


def take(table: Tensor, index: np.ndarray) -> Tensor:
    """Rows of a small table; the gradient is a product with the one-hot index."""

    def back(g):
        hot = np.equal.outer(np.arange(len(table.value)), index.ravel()).astype(g.dtype)
        return (hot @ g.reshape(-1, g.shape[-1]),)

    return Tensor(table.value[index], (table,), back)


def pick(x: Tensor, index: np.ndarray) -> Tensor:
    """x[b, index[b]] for each row b."""
    rows = np.arange(len(index))

    def back(g):
        out = np.zeros_like(x.value)
        out[rows, index] = g
        return (out,)

    return Tensor(x.value[rows, index], (x,), back)


def softmax(x: Tensor) -> Tensor:
    e = np.exp(x.value - x.value.max(-1, keepdims=True))
    p = e / e.sum(-1, keepdims=True)
    return Tensor(p, (x,), lambda g: (p * (g - (g * p).sum(-1, keepdims=True)),))


def log(x: Tensor, least: float = 1e-12) -> Tensor:
    v = np.maximum(x.value, least)
    return Tensor(np.log(v), (x,), lambda g: (g / v,))


def total(x: Tensor, axis=None, keepdims: bool = False) -> Tensor:
    def back(g):
        if axis is not None and not keepdims:
            g = np.expand_dims(g, axis)
        return (np.broadcast_to(g, x.value.shape),)

    return Tensor(x.value.sum(axis=axis, keepdims=keepdims), (x,), back)


def reshape(x: Tensor, *shape: int) -> Tensor:
    return Tensor(x.value.reshape(shape), (x,), lambda g: (g.reshape(x.value.shape),))


def swap(x: Tensor, a: int, b: int) -> Tensor:
    return Tensor(np.swapaxes(x.value, a, b), (x,), lambda g: (np.swapaxes(g, a, b),))


def concat(a: Tensor, b: Tensor) -> Tensor:
    n = a.value.shape[-1]
    return Tensor(np.concatenate([a.value, b.value], -1), (a, b), lambda g: (g[..., :n], g[..., n:]))
