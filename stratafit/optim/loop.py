"""Training loops: plain minibatches, stratified estimates at every step, and anchored control variates.

A loop asks a problem for gradients by the draws of a schedule; the problem answers from moments, from arrays on the driver, or by a Spark job.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from stratafit.functions.portable import py_uniform
from stratafit.operators.sampling import pick_iterate
from stratafit.optim.rules import Rule


class Problem(Protocol):
    """Gradients by draws. The counts say how many example gradients each call costs."""

    size: int

    def inner(self, outer: int, inner: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        """Mean gradient of the step's minibatch."""

    def anchor(self, outer: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        """The anchor of the outer step: weighted over strata, of a batch, or full."""


@dataclass
class Budget:
    """What ends a run early: seconds, example gradients or updates."""

    seconds: float | None = None
    grad_evals: int | None = None
    updates: int | None = None


@dataclass
class Trace:
    """One row per update, and what the run counted."""

    method: str
    run: str = "0"
    rows: list[dict] = field(default_factory=list)
    grad_evals: int = 0
    anchor_evals: int = 0
    updates: int = 0
    began: float = field(default_factory=time.perf_counter)

    def add(self, outer: int, inner: int, theta: np.ndarray, v: np.ndarray, evaluate: Callable[[np.ndarray], dict] | None) -> None:
        self.updates += 1
        row = {"run": self.run, "method": self.method, "outer": outer, "inner": inner, "grad_evals": self.grad_evals, "seconds": time.perf_counter() - self.began, "v_norm": float(np.sqrt(v @ v)), "theta": theta.tolist() if theta.size <= 64 else None}
        self.rows.append(row | (evaluate(theta) if evaluate else {}))

    def spent(self, budget: Budget | None) -> bool:
        return budget is not None and any(
            limit is not None and used >= limit for limit, used in ((budget.seconds, time.perf_counter() - self.began), (budget.grad_evals, self.grad_evals), (budget.updates, self.updates))
        )

    def overhead(self) -> float:
        """Share of all example gradients that anchors took."""
        return self.anchor_evals / self.grad_evals if self.grad_evals else 0.0

    def to_df(self, spark: SparkSession) -> DataFrame:
        kinds = {"run": "string", "method": "string", "outer": "int", "inner": "int", "grad_evals": "long", "seconds": "double", "v_norm": "double", "theta": "array<double>"}
        names = list(self.rows[0]) if self.rows else list(kinds)
        return spark.createDataFrame([tuple(r[k] for k in names) for r in self.rows], ", ".join(f"{k} {kinds.get(k, 'double')}" for k in names))


@dataclass
class FitResult:
    theta: np.ndarray
    trace: Trace


Schedule = Callable[[int], float] | None


def minibatch_fit(problem: Problem, rule: Rule, steps: Sequence[tuple[int, int]], start: np.ndarray | None = None, budget: Budget | None = None, evaluate: Callable | None = None, method: str = "sgd", run: str = "0", lr: Schedule = None) -> FitResult:
    """One update per minibatch; steps are the (outer, inner) counters whose draws are used."""
    theta = np.zeros(problem.size) if start is None else start.astype(float).copy()
    trace = Trace(method, run)
    for i, (outer, inner) in enumerate(steps):
        if trace.spent(budget):
            break
        v, n = problem.inner(outer, inner, theta)
        trace.grad_evals += n
        theta = rule.step(theta, v, lr(i) if lr else None)
        trace.add(outer, inner, theta, v, evaluate)
    return FitResult(theta, trace)


def stratified_fit(problem: Problem, rule: Rule, steps: int, start: np.ndarray | None = None, budget: Budget | None = None, evaluate: Callable | None = None, method: str = "stratified_sgd", run: str = "0", lr: Schedule = None) -> FitResult:
    """One update per stratified estimate, no control variate."""
    theta = np.zeros(problem.size) if start is None else start.astype(float).copy()
    trace = Trace(method, run)
    for t in range(steps):
        if trace.spent(budget):
            break
        v, n = problem.anchor(t, theta)
        trace.grad_evals += n
        trace.anchor_evals += n
        theta = rule.step(theta, v, lr(t) if lr else None)
        trace.add(t, 0, theta, v, evaluate)
    return FitResult(theta, trace)


def anchored_fit(
    problem: Problem, rule: Rule, lengths: Sequence[int], start: np.ndarray | None = None, gamma: float | None = None, return_policy: str = "last", seed: int = 0, reset_state: bool = False, reuse_first: bool = True,
    budget: Budget | None = None, evaluate: Callable | None = None, method: str = "anchored_stratified", run: str = "0", lr: Schedule = None,
) -> FitResult:
    """Anchored descent: an anchor per outer step, and inner steps along the minibatch's change since the anchor plus the anchor.

    The first inner step moves along the anchor itself, as both minibatch gradients are then equal; reuse_first saves them. gamma leaves the inner loop, before the
    update, once the squared norm of the direction is at most gamma times the anchor's. return_policy: last; sampled among outer points by step size; best by
    train_loss of evaluate at the ends of outer steps.
    """
    theta = np.zeros(problem.size) if start is None else start.astype(float).copy()
    trace = Trace(method, run)
    outer_points: list[np.ndarray] = []
    rates: list[float] = []
    for t, length in enumerate(lengths):
        if trace.spent(budget):
            break
        rate = lr(t) if lr else rule.lr
        outer_points.append(theta.copy())
        rates.append(rate)
        point = theta.copy()
        g, n = problem.anchor(t, point)
        trace.grad_evals += n
        trace.anchor_evals += n
        if reset_state:
            rule.reset()
        for k in range(length):
            if trace.spent(budget):
                break
            if k == 0 and reuse_first:
                v = g
            else:
                here, n = problem.inner(t, k, theta)
                there, m = problem.inner(t, k, point)
                trace.grad_evals += n + m
                v = here - there + g
            if k and gamma is not None and v @ v <= gamma * (g @ g):
                break
            theta = rule.step(theta, v, rate)
            trace.add(t, k, theta, v, evaluate)
    if return_policy == "sampled" and outer_points:
        theta = outer_points[pick_iterate(rates, py_uniform(seed, "return"))]
    elif return_policy == "best" and evaluate is not None:
        theta = min([*outer_points, theta], key=lambda x: evaluate(x)["train_loss"])
    elif return_policy not in ("last", "sampled", "best"):
        raise ValueError(f"unknown return policy {return_policy}")
    return FitResult(theta, trace)
