"""A small reverse-mode tape over arrays, enough to train the boundary controller."""

from __future__ import annotations

import numpy as np


def fit_shape(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for k, n in enumerate(shape):
        if n == 1 and g.shape[k] != 1:
            g = g.sum(axis=k, keepdims=True)
    return g


class Var:
    def __init__(self, value, parents=()):
        self.value, self.parents, self.grad = np.asarray(value, float), parents, None

    def __add__(self, o):
        o = of(o)
        return Var(self.value + o.value, ((self, lambda g: g), (o, lambda g: g)))

    def __mul__(self, o):
        o = of(o)
        return Var(self.value * o.value, ((self, lambda g: g * o.value), (o, lambda g: g * self.value)))

    def __neg__(self):
        return self * -1.0

    def __sub__(self, o):
        return self + -of(o)

    def __truediv__(self, o):
        o = of(o)
        return Var(self.value / o.value, ((self, lambda g: g / o.value), (o, lambda g: -g * self.value / o.value**2)))

    def __matmul__(self, o):
        o = of(o)
        return Var(self.value @ o.value, ((self, lambda g: g @ o.value.T), (o, lambda g: self.value.reshape(-1, self.value.shape[-1]).T @ g.reshape(-1, g.shape[-1]))))

    def __getitem__(self, at):
        def back(g):
            out = np.zeros_like(self.value)
            out[at] = g
            return out

        return Var(self.value[at], ((self, back),))

    def apply(self, value, slope):
        return Var(value, ((self, lambda g: g * slope),))

    def tanh(self):
        t = np.tanh(self.value)
        return self.apply(t, 1 - t * t)

    def atanh(self):
        return self.apply(np.arctanh(self.value), 1 / (1 - self.value**2))

    def sigmoid(self):
        s = 1 / (1 + np.exp(-self.value))
        return self.apply(s, s * (1 - s))

    def abs(self):
        return self.apply(np.abs(self.value), np.sign(self.value))

    def sqrt(self):
        r = np.sqrt(self.value)
        return self.apply(r, 0.5 / np.maximum(r, 1e-9))

    def clip(self, low, high):
        """The gradient passes where nothing is cut."""
        return self.apply(np.clip(self.value, low, high), ((self.value >= low) & (self.value <= high)).astype(float))

    def sum(self, axis=None, keepdims=False):
        def back(g):
            return np.broadcast_to(g if keepdims or axis is None else np.expand_dims(g, axis), self.value.shape).copy()

        return Var(self.value.sum(axis=axis, keepdims=keepdims), ((self, back),))

    def max(self, axis):
        top = self.value.max(axis=axis, keepdims=True)
        hit = self.value == top
        return Var(top.squeeze(axis), ((self, lambda g: np.expand_dims(g, axis) * hit / hit.sum(axis=axis, keepdims=True)),))


def of(x) -> Var:
    return x if isinstance(x, Var) else Var(x)


def concat(parts: list[Var], axis: int = -1) -> Var:
    cuts = np.cumsum([p.value.shape[axis] for p in parts])[:-1]
    return Var(np.concatenate([p.value for p in parts], axis=axis), tuple((p, lambda g, k=k: np.split(g, cuts, axis=axis)[k]) for k, p in enumerate(parts)))


def stack(parts: list[Var]) -> Var:
    return Var(np.stack([p.value for p in parts], axis=-1), tuple((p, lambda g, k=k: g[..., k]) for k, p in enumerate(parts)))


def backward(root: Var) -> None:
    order, seen, todo = [], set(), [(root, False)]
    while todo:
        v, done = todo.pop()
        if done:
            order.append(v)
        elif id(v) not in seen:
            seen.add(id(v))
            todo.append((v, True))
            todo += [(p, False) for p, _ in v.parents]
    root.grad = np.ones_like(root.value)
    for v in reversed(order):
        for p, back in v.parents:
            g = fit_shape(back(v.grad), p.value.shape)
            p.grad = g if p.grad is None else p.grad + g
