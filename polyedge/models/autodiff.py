"""A small reverse-mode tape over numpy arrays: enough for the model and the neural baselines."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np


class Var:
    """A value on the tape; ``live`` unless it comes from constants alone, which need no gradient."""

    __slots__ = ("value", "grad", "parents", "back", "live")

    def __init__(self, value, parents: Sequence[Var] = (), back: Callable | None = None, live: bool = True):
        self.value = np.asarray(value, dtype=np.float64)
        self.grad: np.ndarray | None = None
        self.parents, self.back = parents, back
        self.live = any([p.live for p in parents]) if parents else live

    @property
    def shape(self):
        return self.value.shape

    def __add__(self, o):
        o = var(o)
        return Var(self.value + o.value, (self, o), lambda g: (self.live and _fit(g, self.shape), o.live and _fit(g, o.shape)))

    __radd__ = __add__

    def __neg__(self):
        return Var(-self.value, (self,), lambda g: (-g,))

    def __sub__(self, o):
        return self + (-var(o))

    def __rsub__(self, o):
        return var(o) + (-self)

    def __mul__(self, o):
        o = var(o)
        return Var(self.value * o.value, (self, o), lambda g: (self.live and _fit(g * o.value, self.shape), o.live and _fit(g * self.value, o.shape)))

    __rmul__ = __mul__

    def __truediv__(self, o):
        o = var(o)
        return Var(self.value / o.value, (self, o), lambda g: (self.live and _fit(g / o.value, self.shape), o.live and _fit(-g * self.value / o.value**2, o.shape)))

    def __matmul__(self, o):
        o = var(o)

        def back(g):
            ga = self.live and _fit(g @ np.swapaxes(o.value, -1, -2), self.shape)
            return ga, o.live and _fit(np.swapaxes(self.value, -1, -2) @ g, o.shape)

        return Var(self.value @ o.value, (self, o), back)

    def __getitem__(self, key):
        def back(g):
            out = np.zeros_like(self.value)
            np.add.at(out, key, g) if _fancy(key) else out.__setitem__(key, g)
            return (out,)

        return Var(self.value[key], (self,), back)

    def reshape(self, *shape):
        return Var(self.value.reshape(*shape), (self,), lambda g: (g.reshape(self.shape),))

    def swap(self, a=-1, b=-2):
        return Var(np.swapaxes(self.value, a, b), (self,), lambda g: (np.swapaxes(g, a, b),))

    def sum(self, axis=None, keepdims=False):
        def back(g):
            if axis is not None and not keepdims:
                g = np.expand_dims(g, axis)
            return (np.broadcast_to(g, self.shape),)

        return Var(self.value.sum(axis=axis, keepdims=keepdims), (self,), back)

    def mean(self, axis=None, keepdims=False):
        n = self.value.size if axis is None else np.prod([self.shape[a] for a in np.atleast_1d(axis)])
        return self.sum(axis, keepdims) * (1.0 / n)


def _fancy(key) -> bool:
    return any(isinstance(k, (np.ndarray, list)) for k in (key if isinstance(key, tuple) else (key,)))


def _fit(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Sum a gradient back over the axes that broadcasting added."""
    if g.shape == shape:
        return g
    while g.ndim > len(shape):
        g = g.sum(0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(i, keepdims=True)
    return g


def var(x) -> Var:
    return x if isinstance(x, Var) else Var(x, live=False)


def relu(x: Var) -> Var:
    on = x.value > 0
    return Var(x.value * on, (x,), lambda g: (g * on,))


def sigmoid(x: Var) -> Var:
    y = 1 / (1 + np.exp(-np.clip(x.value, -60, 60)))
    return Var(y, (x,), lambda g: (g * y * (1 - y),))


def tanh(x: Var) -> Var:
    y = np.tanh(x.value)
    return Var(y, (x,), lambda g: (g * (1 - y * y),))


def exp(x: Var) -> Var:
    y = np.exp(np.clip(x.value, -60, 60))
    return Var(y, (x,), lambda g: (g * y,))


def log(x: Var, floor: float = 1e-12) -> Var:
    v = np.maximum(x.value, floor)
    return Var(np.log(v), (x,), lambda g: (g / v,))


def square(x: Var) -> Var:
    return Var(x.value**2, (x,), lambda g: (2 * g * x.value,))


def softmax(x: Var, axis: int = -1, mask: np.ndarray | None = None) -> Var:
    """Softmax along an axis; where the mask is 0 the coefficient is 0."""
    v = x.value if mask is None else np.where(mask > 0, x.value, -np.inf)
    top = v.max(axis=axis, keepdims=True)
    y = v - np.where(np.isfinite(top), top, 0)
    # powers of members alone: those of -inf are zero, and slow
    y = np.exp(y) if mask is None else np.exp(y, out=np.zeros_like(y), where=mask > 0)
    total = y.sum(axis=axis, keepdims=True)
    y /= np.where(total > 0, total, 1)

    def back(g):
        out = g * y
        np.subtract(g, out.sum(axis=axis, keepdims=True), out=out)
        out *= y
        return (out,)

    return Var(y, (x,), back)


def concat(xs: Sequence[Var], axis: int = -1) -> Var:
    xs = [var(x) for x in xs]
    cuts = np.cumsum([x.shape[axis] for x in xs])[:-1]
    return Var(np.concatenate([x.value for x in xs], axis), xs, lambda g: tuple(np.split(g, cuts, axis)))


def stack(xs: Sequence[Var], axis: int = 0) -> Var:
    return Var(np.stack([x.value for x in xs], axis), xs, lambda g: tuple(np.moveaxis(g, axis, 0)))


def spread(x: Var, shape: tuple[int, ...]) -> Var:
    return Var(np.broadcast_to(x.value, shape), (x,), lambda g: (_fit(g, x.shape),))


def backward(loss: Var) -> None:
    order: list[Var] = []
    seen: set[int] = set()
    todo: list[tuple[Var, bool]] = [(loss, False)]
    while todo:
        v, done = todo.pop()
        if done:
            order.append(v)
        elif id(v) not in seen:
            seen.add(id(v))
            todo.append((v, True))
            todo += [(p, False) for p in v.parents if p.live and id(p) not in seen]
    loss.grad = np.ones_like(loss.value)
    for v in reversed(order):
        if v.back is None or v.grad is None:
            continue
        for p, g in zip(v.parents, v.back(v.grad), strict=True):
            if p.live:
                p.grad = g if p.grad is None else p.grad + g
        if v.parents:
            v.grad = None


def gradients(f: Callable[[dict[str, Var]], Var], params: dict[str, np.ndarray]) -> tuple[float, dict[str, np.ndarray]]:
    """Value and gradient of a scalar function of named arrays."""
    held = {k: Var(v) for k, v in params.items()}
    loss = f(held)
    backward(loss)
    return float(loss.value), {k: v.grad if v.grad is not None else np.zeros_like(v.value) for k, v in held.items()}
