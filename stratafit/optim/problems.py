"""Problems for the loops: replayed moments, arrays held on the driver, and Spark jobs over all examples."""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stratafit.functions.portable import py_uniform
from stratafit.models.arrow_kernel import weighted_gradient
from stratafit.operators.gradients import matrices, schedule_moments
from stratafit.operators.sampling import build_schedule


class MomentsProblem:
    """Autoregression with squared error, from the moments of a schedule's draws: no Spark job during training."""

    def __init__(self, rows: Sequence[dict], weights: dict[int, float], size: int, full: dict | None = None) -> None:
        self.size = size
        self.inner_parts = {(r["outer"], r["inner"]): (*matrices(r, size)[:2], r["n"]) for r in rows if r["role"] == "inner"}
        self.anchors: dict[int, list[tuple[float, np.ndarray, np.ndarray, int]]] = {}
        for r in rows:
            if r["role"] == "anchor":
                self.anchors.setdefault(r["outer"], []).append((weights.get(r["stratum"], 1.0), *matrices(r, size)[:2], r["n"]))
        self.full = (*matrices(full, size)[:2], full["n"]) if full else None

    @classmethod
    def collect(cls, positioned: DataFrame, strata: DataFrame, schedule: DataFrame, size: int, full: dict | None = None, weighted: bool = True) -> MomentsProblem:
        """Rows are as many as updates and anchors' strata, whatever the number of examples."""
        weights = {r["stratum"]: r["w"] for r in strata.collect()} if weighted else {}
        rows = schedule_moments(positioned, schedule, size).orderBy("outer", "inner", "stratum").toLocalIterator()
        return cls([r.asDict() for r in rows], weights, size, full)

    def inner(self, outer: int, inner: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        a, c, n = self.inner_parts[outer, inner]
        return 2 * (a @ theta - c), n

    def anchor(self, outer: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        if self.full is not None:
            a, c, n = self.full
            return 2 * (a @ theta - c), n
        parts = self.anchors[outer]
        return sum(w * 2 * (a @ theta - c) for w, a, c, _ in parts), sum(p[3] for p in parts)


class ArrayProblem:
    """Any model over arrays in memory: for small data and for many seeds. Drawn by numpy or, with shared_draws, as build_schedule draws from rows in order of (series_id, t0)."""

    def __init__(self, gradient, n: int, size: int, strata: np.ndarray | None, minibatch: int = 1, per_stratum: int = 1, seed: int = 0, anchor: str = "stratified", batch: int | None = None, shared_draws: bool = False) -> None:
        self.gradient, self.n, self.size, self.minibatch, self.per_stratum, self.kind = gradient, n, size, minibatch, per_stratum, anchor
        self.seed, self.shared_draws = seed, shared_draws
        self.groups = [np.flatnonzero(strata == s) for s in np.unique(strata)] if strata is not None else []
        self.batch = batch or max(1, len(self.groups) * per_stratum)

    def _shared(self, n: int, size: int, *tag: object) -> np.ndarray:
        return np.array([min(int(py_uniform(self.seed, *tag, k) * n), n - 1) for k in range(size)])

    def inner(self, outer: int, inner: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        if self.shared_draws:
            return self.gradient(self._shared(self.n, self.minibatch, "inner", outer, inner), theta), self.minibatch
        rng = np.random.default_rng((self.seed, 1, outer, inner))
        return self.gradient(rng.integers(0, self.n, self.minibatch), theta), self.minibatch

    def anchor(self, outer: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        if self.kind == "full":
            return self.gradient(np.arange(self.n), theta), self.n
        if self.shared_draws and self.kind == "batch":
            return self.gradient(self._shared(self.n, self.batch, "anchor", outer, 0), theta), self.batch
        if self.shared_draws:
            picks = [g[self._shared(len(g), self.per_stratum, "anchor", outer, k)] for k, g in enumerate(self.groups)]
            return sum(len(g) / self.n * self.gradient(own, theta) for g, own in zip(self.groups, picks, strict=True)), len(self.groups) * self.per_stratum
        rng = np.random.default_rng((self.seed, 2, outer))
        if self.kind == "batch":
            return self.gradient(rng.choice(self.n, min(self.batch, self.n), replace=False), theta), self.batch
        total = sum(len(g) / self.n * self.gradient(g[rng.integers(0, len(g), self.per_stratum)], theta) for g in self.groups)
        return total, len(self.groups) * self.per_stratum


class SegmentProblem:
    """Any model over any number of examples: anchors are Spark jobs over the drawn examples or all, an outer step's minibatches come to the driver together.

    positioned has stratum, pos, gpos, context and target; or, with segments, keys instead of the last two: segments(rows, few) then adds them to rows of it. Draws are those
    of build_schedule, so a run is that of ArrayProblem with shared_draws. The driver holds one outer step's minibatches (its length times minibatch segments) and single
    gradient vectors. Draws up to FEW are broadcast, so that positioned is read in place and never shuffled for them.
    """

    #: Draws of a job that are broadcast.
    FEW = 1 << 20

    def __init__(self, model, positioned: DataFrame, strata: DataFrame, lengths: Sequence[int], minibatch: int = 1, per_stratum: int = 1, seed: int = 0, anchor: str = "stratified", batch: int | None = None, segments: Callable[[DataFrame, bool], DataFrame] | None = None) -> None:
        self.segments = segments or (lambda rows, few: rows)
        self.model, self.size, self.positioned, self.strata, self.lengths = model, model.size, positioned, strata, lengths
        self.minibatch, self.per_stratum, self.seed, self.kind = minibatch, per_stratum, seed, anchor
        sums = strata.agg(F.sum("n").alias("total"), F.count(F.lit(1)).alias("strata")).first()
        self.total, self.batch = sums["total"], batch or sums["strata"] * per_stratum
        self.anchor_draws = self.batch if anchor == "batch" else sums["strata"] * per_stratum
        self.held: tuple[int, dict[int, tuple[np.ndarray, np.ndarray]]] = (-1, {})

    def _draws(self, outer: int, role: str) -> DataFrame:
        length = {outer: self.lengths[outer] if outer < len(self.lengths) else 0}
        kind = self.kind if role == "anchor" else "none"
        return build_schedule(self.positioned.sparkSession, length, self.strata, self.total, self.per_stratum, self.minibatch, self.seed, kind, self.batch).filter(F.col("role") == role)

    def _examples(self, draws: DataFrame, keys: list[str], count: int) -> DataFrame:
        """draws with context and target of the examples that their keys name."""
        few = count <= self.FEW
        others = [c for c in self.positioned.columns if c not in ("stratum", "pos", "gpos")]
        return self.segments((F.broadcast(draws) if few else draws).join(self.positioned.select(*keys, *others), keys), few)

    def inner(self, outer: int, inner: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        if self.held[0] != outer:
            drawn: dict[int, list] = {}
            count = (self.lengths[outer] if outer < len(self.lengths) else 0) * self.minibatch
            rows = self._examples(self._draws(outer, "inner").select("inner", "draw", "gpos"), ["gpos"], count).collect()
            for r in sorted(rows, key=lambda r: (r["inner"], r["draw"])):
                drawn.setdefault(r["inner"], []).append((r["context"], r["target"]))
            self.held = outer, {k: (np.array([c for c, _ in v]), np.array([t for _, t in v])) for k, v in drawn.items()}
        x, y = self.held[1][inner]
        return self.model.loss_grad(theta, x, y)[1], len(x)

    def anchor(self, outer: int, theta: np.ndarray) -> tuple[np.ndarray, int]:
        rows = self.positioned
        if self.kind == "full":
            return weighted_gradient(self.segments(rows, False).withColumn("weight", F.lit(1.0 / self.total)), self.model, theta)
        draws = self._draws(outer, "anchor")
        if self.kind == "batch":
            examples = self._examples(draws.select("gpos"), ["gpos"], self.anchor_draws).withColumn("weight", F.lit(1.0 / self.batch))
        else:
            weighed = draws.select("stratum", "pos").join(self.strata.select("stratum", (F.col("w") / self.per_stratum).alias("weight")), "stratum")
            examples = self._examples(weighed, ["stratum", "pos"], self.anchor_draws)
        return weighted_gradient(examples, self.model, theta)


def tune(fit, grid: Sequence[float], top: int = 3) -> list[tuple[float, float]]:
    """(step size, final training loss), best first, at most top; fit(step size) gives a loss. Losses that are not finite come last."""
    found = [(lr, fit(lr)) for lr in grid]
    return sorted(found, key=lambda x: (not np.isfinite(x[1]), x[1]))[:top]
