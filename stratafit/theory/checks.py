"""The theory as functions that can be run: lower-bound instances, estimator moments, preconditions and order calculators."""

from __future__ import annotations

import itertools
from collections.abc import Sequence
from fractions import Fraction

import numpy as np

from stratafit.optim.rules import Rule


def is_zero_respecting(rule: Rule, steps: int = 20, size: int = 4, dead: int = 2, seed: int = 0) -> bool:
    """Whether a coordinate whose gradients were always 0 never moves under the rule."""
    rng = np.random.default_rng(seed)
    theta = start = rng.normal(size=size)
    for _ in range(steps):
        g = rng.normal(size=size)
        g[dead] = 0.0
        theta = rule.step(theta, g)
    return bool(theta[dead] == start[dead])


def heterogeneous_ar(p: int, delta: float) -> tuple[np.ndarray, np.ndarray]:
    """Contexts and targets of two series of p + 1 values, all delta, whose last is plus or minus delta. At any parameters, the gradient variance is 4 delta**4 p."""
    return np.full((2, p), delta), np.array([delta, -delta])


def sparse_ar(p: int, delta: float) -> tuple[np.ndarray, np.ndarray]:
    """p examples; of example j only lag j is other than 0."""
    return np.eye(p) * delta, np.full(p, delta)


def ar_gradients(x: np.ndarray, y: np.ndarray, theta: np.ndarray) -> np.ndarray:
    """A row per example."""
    return 2 * (x @ theta - y)[:, None] * x


def variance(gradients: np.ndarray) -> float:
    return float(((gradients - gradients.mean(axis=0)) ** 2).sum(axis=1).mean())


def stratified_moments(values: Sequence[Sequence[Fraction]], b: int) -> tuple[Fraction, Fraction]:
    """Exact mean and variance of the stratified estimate of scalar values, by going through every way to draw b of each stratum with replacement."""
    n = sum(map(len, values))
    total = square = Fraction(0)
    count = 0
    for draw in itertools.product(*[itertools.product(s, repeat=b) for s in values]):
        g = sum((Fraction(len(s), n) * sum(d) / b for s, d in zip(values, draw, strict=True)), Fraction(0))
        total, square, count = total + g, square + g * g, count + 1
    mean = total / count
    return mean, square / count - mean * mean


def stratified_variance_formula(values: Sequence[Sequence[Fraction]], b: int) -> Fraction:
    n = sum(map(len, values))
    out = Fraction(0)
    for s in values:
        m = sum(s, Fraction(0)) / len(s)
        out += Fraction(len(s), n) ** 2 * (sum(((v - m) ** 2 for v in s), Fraction(0)) / len(s)) / b
    return out


def precondition(weights: Sequence[float], variances: Sequence[float], eps: float) -> tuple[bool, float]:
    """Whether sum of w**2 sigma**2 is at most eps**2, and that sum: the radius of the noise ball where it is not."""
    ball = float(sum(w * w * s for w, s in zip(weights, variances, strict=True)))
    return ball <= eps * eps, ball


def complexity_table(gap: float, smooth: float, eps: float, sigma2: float, weights: Sequence[float], variances: Sequence[float], n: int) -> dict[str, float]:
    """Orders of the number of example gradients, constants taken as 1. The term of one-example strata counts only where there are n strata."""
    b = len(weights)
    dependency = b * sum(w * w * s for w, s in zip(weights, variances, strict=True))
    base = gap * smooth
    return {
        "anchored_stratified": base * dependency ** (2 / 3) * eps ** (-10 / 3) + (base * n ** (2 / 3) * eps**-2 if b == n else 0.0),
        "anchored_equal_strata": base * float(np.mean(variances)) ** (2 / 3) * eps ** (-10 / 3),
        "batch_anchor": base * sigma2 ** (2 / 3) * eps ** (-10 / 3),
        "full_anchor": base * n ** (2 / 3) * eps**-2,
        "lower_bound": base * sigma2 * eps**-4,
    }


def smoothness(x: np.ndarray) -> tuple[float, float]:
    """For squared error: the largest constant of an example, and the objective's."""
    return float(2 * (x * x).sum(axis=1).max()), float(2 * np.linalg.eigvalsh(x.T @ x / len(x)).max())


def initial_gap(a: np.ndarray, c: np.ndarray, yy: float) -> float:
    """The loss at 0 less the least loss, from moments."""
    return float(c @ np.linalg.solve(a, c)) if len(c) else yy * 0
