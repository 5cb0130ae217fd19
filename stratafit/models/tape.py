"""Reverse-mode differentiation of numpy expressions, as much of it as the forecasters need."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class Var:
    """An array, how it was made, and after backward() its derivative."""

    __slots__ = ("value", "grad", "parents")

    def __init__(self, value: np.ndarray, parents: tuple[tuple[Var, Callable[[np.ndarray], np.ndarray]], ...] = ()) -> None:
        self.value, self.parents = np.asarray(value, float), parents
        self.grad: np.ndarray | None = None

    def __add__(self, other: Var | float) -> Var:
        other = lift(other)
        return Var(self.value + other.value, ((self, lambda g: _fit(g, self.value.shape)), (other, lambda g: _fit(g, other.value.shape))))

    __radd__ = __add__

    def __mul__(self, other: Var | float) -> Var:
        other = lift(other)
        return Var(self.value * other.value, ((self, lambda g: _fit(g * other.value, self.value.shape)), (other, lambda g: _fit(g * self.value, other.value.shape))))

    __rmul__ = __mul__

    def __neg__(self) -> Var:
        return self * -1.0

    def __sub__(self, other: Var | float) -> Var:
        return self + -lift(other)

    def __truediv__(self, other: Var | float) -> Var:
        other = lift(other)
        return Var(self.value / other.value, ((self, lambda g: _fit(g / other.value, self.value.shape)), (other, lambda g: _fit(-g * self.value / other.value**2, other.value.shape))))

    def __matmul__(self, other: Var) -> Var:
        return Var(self.value @ other.value, ((self, lambda g: g @ other.value.T), (other, lambda g: self.value.T @ g)))

    def __getitem__(self, key) -> Var:
        def back(g: np.ndarray) -> np.ndarray:
            out = np.zeros_like(self.value)
            out[key] = g
            return out

        return Var(self.value[key], ((self, back),))

    def _unary(self, value: np.ndarray, slope: np.ndarray) -> Var:
        return Var(value, ((self, lambda g: g * slope),))

    def relu(self) -> Var:
        return self._unary(np.maximum(self.value, 0), (self.value > 0).astype(float))

    def tanh(self) -> Var:
        t = np.tanh(self.value)
        return self._unary(t, 1 - t * t)

    def sigmoid(self) -> Var:
        s = 1 / (1 + np.exp(-np.clip(self.value, -500, 500)))
        return self._unary(s, s * (1 - s))

    def softplus(self) -> Var:
        return self._unary(np.logaddexp(0, self.value), 1 / (1 + np.exp(-np.clip(self.value, -500, 500))))

    def log(self) -> Var:
        return self._unary(np.log(self.value), 1 / self.value)

    def log1p(self) -> Var:
        return self._unary(np.log1p(self.value), 1 / (1 + self.value))

    def abs(self) -> Var:
        return self._unary(np.abs(self.value), np.sign(self.value))

    def square(self) -> Var:
        return self._unary(self.value**2, 2 * self.value)

    def mean(self) -> Var:
        n = self.value.size
        return Var(self.value.mean(), ((self, lambda g: np.full(self.value.shape, g / n)),))

    def sum(self) -> Var:
        return Var(self.value.sum(), ((self, lambda g: np.full(self.value.shape, g)),))

    def maximum(self, other: Var) -> Var:
        first = self.value >= other.value
        return Var(np.maximum(self.value, other.value), ((self, lambda g: g * first), (other, lambda g: g * ~first)))

    def backward(self) -> None:
        """Derivatives of this scalar by everything below it."""
        order: list[Var] = []
        seen: set[int] = set()
        stack: list[tuple[Var, bool]] = [(self, False)]
        while stack:
            node, done = stack.pop()
            if done:
                order.append(node)
            elif id(node) not in seen:
                seen.add(id(node))
                stack.append((node, True))
                stack += [(p, False) for p, _ in node.parents]
        for node in order:
            node.grad = None
        self.grad = np.ones_like(self.value)
        for node in reversed(order):
            for parent, back in node.parents:
                g = back(node.grad)
                parent.grad = g if parent.grad is None else parent.grad + g


def lift(x: Var | float | np.ndarray) -> Var:
    return x if isinstance(x, Var) else Var(x)


def _fit(g: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """Sum a derivative over axes that were broadcast."""
    if g.shape == shape:
        return g
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for axis, n in enumerate(shape):
        if n == 1 and g.shape[axis] != 1:
            g = g.sum(axis=axis, keepdims=True)
    return g
