"""Update rules: what to do with a gradient or its control variate. Each keeps its state and returns the new parameters."""

from __future__ import annotations

import numpy as np


class Rule:
    def __init__(self, lr: float) -> None:
        self.lr = lr

    def reset(self) -> None:
        """Forget all state."""

    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        raise NotImplementedError


class SGD(Rule):
    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        return theta - (self.lr if lr is None else lr) * v


class Momentum(Rule):
    def __init__(self, lr: float, decay: float = 0.9) -> None:
        super().__init__(lr)
        self.decay = decay
        self.reset()

    def reset(self) -> None:
        self.velocity = 0.0

    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        self.velocity = self.decay * self.velocity + v
        return theta - (self.lr if lr is None else lr) * self.velocity


class RMSProp(Rule):
    def __init__(self, lr: float, decay: float = 0.9, eps: float = 1e-8) -> None:
        super().__init__(lr)
        self.decay, self.eps = decay, eps
        self.reset()

    def reset(self) -> None:
        self.square = 0.0

    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        self.square = self.decay * self.square + (1 - self.decay) * v * v
        return theta - (self.lr if lr is None else lr) * v / (np.sqrt(self.square) + self.eps)


class Adam(Rule):
    def __init__(self, lr: float, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8) -> None:
        super().__init__(lr)
        self.beta1, self.beta2, self.eps = beta1, beta2, eps
        self.reset()

    def reset(self) -> None:
        self.first, self.second, self.count = 0.0, 0.0, 0

    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        self.count += 1
        self.first = self.beta1 * self.first + (1 - self.beta1) * v
        self.second = self.beta2 * self.second + (1 - self.beta2) * v * v
        m = self.first / (1 - self.beta1**self.count)
        s = self.second / (1 - self.beta2**self.count)
        return theta - (self.lr if lr is None else lr) * m / (np.sqrt(s) + self.eps)


class Adagrad(Rule):
    def __init__(self, lr: float, eps: float = 1e-8) -> None:
        super().__init__(lr)
        self.eps = eps
        self.reset()

    def reset(self) -> None:
        self.square = 0.0

    def step(self, theta: np.ndarray, v: np.ndarray, lr: float | None = None) -> np.ndarray:
        self.square = self.square + v * v
        return theta - (self.lr if lr is None else lr) * v / (np.sqrt(self.square) + self.eps)


RULES = {"sgd": SGD, "momentum": Momentum, "rmsprop": RMSProp, "adam": Adam, "adagrad": Adagrad}


def make_rule(name: str, lr: float, **options: float) -> Rule:
    return RULES[name](lr, **options)
