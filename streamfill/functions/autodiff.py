"""Reverse-mode differentiation over numpy arrays, as much as the networks here need."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


def _fit(grad: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """A gradient summed back over the axes that broadcasting added or stretched."""
    while grad.ndim > len(shape):
        grad = grad.sum(axis=0)
    for axis, n in enumerate(shape):
        if n == 1 and grad.shape[axis] != 1:
            grad = grad.sum(axis=axis, keepdims=True)
    return grad


class Var:
    """An array and how it came about."""

    __array_priority__ = 100

    def __init__(self, data, parents: tuple = (), back: Callable | None = None) -> None:
        self.data = np.asarray(data, dtype=np.float64)
        self.parents, self.back, self.grad = parents, back, None

    @property
    def shape(self):
        return self.data.shape

    def __add__(self, other):
        other = var(other)
        return Var(self.data + other.data, (self, other), lambda g: (_fit(g, self.shape), _fit(g, other.shape)))

    def __mul__(self, other):
        other = var(other)
        return Var(self.data * other.data, (self, other), lambda g: (_fit(g * other.data, self.shape), _fit(g * self.data, other.shape)))

    def __truediv__(self, other):
        other = var(other)
        return Var(self.data / other.data, (self, other), lambda g: (_fit(g / other.data, self.shape), _fit(-g * self.data / other.data**2, other.shape)))

    def __matmul__(self, other):
        other = var(other)
        turned = lambda a: np.swapaxes(a, -1, -2)
        return Var(self.data @ other.data, (self, other), lambda g: (_fit(g @ turned(other.data), self.shape), _fit(turned(self.data) @ g, other.shape)))

    __radd__, __rmul__ = __add__, __mul__

    def __neg__(self):
        return self * -1.0

    def __sub__(self, other):
        return self + -var(other)

    def __rsub__(self, other):
        return var(other) + -self

    def __getitem__(self, at):
        def back(g):
            out = np.zeros(self.shape)
            np.add.at(out, at, g)
            return (out,)

        return Var(self.data[at], (self,), back)

    def turned(self):
        return Var(np.swapaxes(self.data, -1, -2), (self,), lambda g: (np.swapaxes(g, -1, -2),))

    def sum(self):
        return Var(self.data.sum(), (self,), lambda g: (np.full(self.shape, g),))

    def backward(self) -> None:
        order, seen, stack = [], set(), [(self, False)]
        while stack:
            node, done = stack.pop()
            if done:
                order.append(node)
            elif id(node) not in seen:
                seen.add(id(node))
                stack.append((node, True))
                stack.extend((p, False) for p in node.parents)
        self.grad = np.ones(self.shape)
        for node in reversed(order):
            if node.back and node.grad is not None:
                for parent, g in zip(node.parents, node.back(node.grad), strict=True):
                    parent.grad = g if parent.grad is None else parent.grad + g


def var(x) -> Var:
    return x if isinstance(x, Var) else Var(x)


def _each(x: Var, value: np.ndarray, slope: np.ndarray) -> Var:
    return Var(value, (x,), lambda g: (g * slope,))


def relu(x: Var) -> Var:
    return _each(x, np.maximum(x.data, 0), (x.data > 0).astype(float))


def leaky_relu(x: Var, slope: float = 0.2) -> Var:
    return _each(x, np.where(x.data > 0, x.data, slope * x.data), np.where(x.data > 0, 1.0, slope))


def tanh(x: Var) -> Var:
    y = np.tanh(x.data)
    return _each(x, y, 1 - y * y)


def sigmoid(x: Var) -> Var:
    y = 1 / (1 + np.exp(-np.clip(x.data, -60, 60)))
    return _each(x, y, y * (1 - y))


def exp(x: Var) -> Var:
    y = np.exp(x.data)
    return _each(x, y, y)


def absolute(x: Var) -> Var:
    return _each(x, np.abs(x.data), np.sign(x.data))


def softmax(x: Var) -> Var:
    """Over the last axis."""
    e = np.exp(x.data - x.data.max(axis=-1, keepdims=True))
    y = e / e.sum(axis=-1, keepdims=True)
    return Var(y, (x,), lambda g: (y * (g - (g * y).sum(axis=-1, keepdims=True)),))


def concat(parts: list[Var], axis: int = -1) -> Var:
    ends = np.cumsum([p.shape[axis] for p in parts])[:-1]
    return Var(np.concatenate([p.data for p in parts], axis=axis), tuple(parts), lambda g: tuple(np.split(g, ends, axis=axis)))


def linear_map(x: Var, forward: Callable, transposed: Callable) -> Var:
    """A fixed linear map of x, given with its transpose."""
    return Var(forward(x.data), (x,), lambda g: (transposed(g),))


def edge_softmax(score: Var, starts: np.ndarray, owner: np.ndarray) -> Var:
    """Softmax over the edges of each node; edges are sorted by node, starts holds where each node's begin."""
    top = np.maximum.reduceat(score.data, starts)[owner]
    e = np.exp(score.data - top)
    y = e / np.add.reduceat(e, starts)[owner]
    return Var(y, (score,), lambda g: (y * (g - np.add.reduceat(g * y, starts)[owner]),))


def masked_mse(x: Var, target: np.ndarray, mask: np.ndarray, by: float) -> Var:
    gap = (x - target) * mask
    return (gap * gap).sum() * (1.0 / max(by, 1.0))


def masked_mae(x: Var, target: np.ndarray, mask: np.ndarray, by: float | None = None) -> Var:
    """by: the cells of the whole, where x is a part of it."""
    return (absolute(x - target) * mask).sum() * (1.0 / max(mask.sum() if by is None else by, 1.0))


class Adam:
    """Adam over a dict of arrays; decay is added to the gradient, or (decoupled) taken off the weights."""

    def __init__(self, lr: float = 0.01, decay: float = 0.0, decoupled: bool = False) -> None:
        self.lr, self.decay, self.decoupled, self.step, self.m, self.v = lr, decay, decoupled, 0, {}, {}

    def update(self, theta: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        self.step += 1
        out = dict(theta)
        for k, g in grads.items():
            if not self.decoupled:
                g = g + self.decay * theta[k]
            m = self.m[k] = 0.9 * self.m.get(k, 0.0) + 0.1 * g
            v = self.v[k] = 0.999 * self.v.get(k, 0.0) + 0.001 * g * g
            out[k] = theta[k] - self.lr * (m / (1 - 0.9**self.step)) / (np.sqrt(v / (1 - 0.999**self.step)) + 1e-8)
            if self.decoupled:
                out[k] = out[k] - self.lr * self.decay * theta[k]
        return out
