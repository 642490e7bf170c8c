"""Reverse-mode differentiation over NumPy arrays: as much as the three components need."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


def _fit(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Sums a gradient over broadcast axes."""
    while g.ndim > len(shape):
        g = g.sum(0)
    for i, k in enumerate(shape):
        if k == 1 and g.shape[i] != 1:
            g = g.sum(i, keepdims=True)
    return g


class Tensor:
    """A value, and how its gradient reaches what it was made from."""

    __slots__ = ("back", "grad", "parents", "value")

    def __init__(self, value, parents: tuple[Tensor, ...] = (), back: Callable | None = None) -> None:
        self.value, self.parents, self.back, self.grad = np.asarray(value, "float64"), parents, back, None

    def backward(self) -> None:
        order, seen = [], set()
        stack = [(self, False)]
        while stack:
            t, done = stack.pop()
            if done:
                order.append(t)
            elif id(t) not in seen:
                seen.add(id(t))
                stack.append((t, True))
                stack.extend((p, False) for p in t.parents)
        self.grad = np.ones_like(self.value)
        for t in reversed(order):
            if t.back is not None and t.grad is not None:
                for p, g in zip(t.parents, t.back(t.grad), strict=True):
                    if g is not None:
                        g = _fit(g, p.value.shape)
                        p.grad = g if p.grad is None else p.grad + g

    def __add__(self, o) -> Tensor:
        o = lift(o)
        return Tensor(self.value + o.value, (self, o), lambda g: (g, g))

    def __sub__(self, o) -> Tensor:
        o = lift(o)
        return Tensor(self.value - o.value, (self, o), lambda g: (g, -g))

    def __mul__(self, o) -> Tensor:
        o = lift(o)
        return Tensor(self.value * o.value, (self, o), lambda g: (g * o.value, g * self.value))

    def __truediv__(self, o) -> Tensor:
        o = lift(o)
        return Tensor(self.value / o.value, (self, o), lambda g: (g / o.value, -g * self.value / o.value**2))

    def __matmul__(self, o) -> Tensor:
        o = lift(o)
        return Tensor(self.value @ o.value, (self, o), lambda g: (g @ o.value.T, self.value.T @ g))

    def __neg__(self) -> Tensor:
        return Tensor(-self.value, (self,), lambda g: (-g,))

    __radd__, __rmul__ = __add__, __mul__

    def __rsub__(self, o) -> Tensor:
        return lift(o) - self

    def __getitem__(self, at) -> Tensor:
        once = all(isinstance(i, slice | int) for i in (at if isinstance(at, tuple) else (at,)))  # no entry is taken twice

        def back(g):
            out = np.zeros_like(self.value)
            if once:
                out[at] = g
            else:
                np.add.at(out, at, g)
            return (out,)

        return Tensor(self.value[at], (self,), back)

    def sum(self, axis: int | None = None, keepdims: bool = False) -> Tensor:
        def back(g):
            if axis is not None and not keepdims:
                g = np.expand_dims(g, axis)
            return (np.broadcast_to(g, self.value.shape).copy(),)

        return Tensor(self.value.sum(axis=axis, keepdims=keepdims), (self,), back)

    def mean(self) -> Tensor:
        return self.sum() * (1.0 / self.value.size)


def lift(x) -> Tensor:
    return x if isinstance(x, Tensor) else Tensor(x)


def exp(t: Tensor) -> Tensor:
    v = np.exp(t.value)
    return Tensor(v, (t,), lambda g: (g * v,))


def log(t: Tensor) -> Tensor:
    return Tensor(np.log(t.value), (t,), lambda g: (g / t.value,))


def square(t: Tensor) -> Tensor:
    return Tensor(t.value**2, (t,), lambda g: (2 * g * t.value,))


def relu(t: Tensor) -> Tensor:
    on = t.value > 0
    return Tensor(t.value * on, (t,), lambda g: (g * on,))


def tanh(t: Tensor) -> Tensor:
    v = np.tanh(t.value)
    return Tensor(v, (t,), lambda g: (g * (1 - v**2),))


def log_softmax(t: Tensor) -> Tensor:
    """Over the last axis."""
    z = t.value - t.value.max(-1, keepdims=True)
    v = z - np.log(np.exp(z).sum(-1, keepdims=True))
    return Tensor(v, (t,), lambda g: (g - np.exp(v) * g.sum(-1, keepdims=True),))


def log_sum_exp(t: Tensor) -> Tensor:
    """Over the last axis."""
    top = t.value.max(-1, keepdims=True)
    v = top[..., 0] + np.log(np.exp(t.value - top).sum(-1))
    return Tensor(v, (t,), lambda g: (g[..., None] * np.exp(t.value - v[..., None]),))


def cross_entropy(z: Tensor, target: np.ndarray, starts: list[int]) -> Tensor:
    """Sum of -target * log_softmax(z), with a softmax over each group of columns from one start to the next."""
    log_p = np.empty_like(z.value)
    slope = np.empty_like(z.value)
    for a, b in zip(starts, starts[1:], strict=False):
        part = z.value[:, a:b] - z.value[:, a:b].max(1, keepdims=True)
        e = np.exp(part)
        total = e.sum(1, keepdims=True)
        log_p[:, a:b] = part - np.log(total)
        slope[:, a:b] = e * (target[:, a:b].sum(1, keepdims=True) / total)
    slope -= target
    return Tensor(-np.vdot(log_p, target), (z,), lambda g: (g * slope,))


def masked_linear(x: Tensor, w: Tensor, b: Tensor, mask: np.ndarray | None = None) -> Tensor:
    return x @ (w * mask if mask is not None else w) + b
