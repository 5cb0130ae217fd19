"""Gradients of autoregressions with squared error as SQL expressions, and the moments from which a whole run is replayed."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Above this order the pairwise sums would be too many columns for one generated method.
MAX_COLUMNS_ORDER = 64


def with_gradient(examples: DataFrame, theta: Sequence[float]) -> DataFrame:
    """examples with r (forecast less value), loss and g1 .. gp at theta."""
    p = len(theta)
    r = sum((F.lit(float(theta[j])) * F.col(f"x{j + 1}") for j in range(p)), F.lit(0.0)) - F.col("y")
    return examples.withColumn("r", r).withColumns({"loss": F.col("r") * F.col("r"), **{f"g{j}": F.lit(2.0) * F.col(f"x{j}") * F.col("r") for j in range(1, p + 1)}})


def full_gradient(examples: DataFrame, theta: Sequence[float]) -> DataFrame:
    """n, loss, g1 .. gp: means over all examples."""
    p = len(theta)
    return with_gradient(examples, theta).agg(F.count(F.lit(1)).alias("n"), F.avg("loss").alias("loss"), *[F.avg(f"g{j}").alias(f"g{j}") for j in range(1, p + 1)])


def stratified_gradient(examples: DataFrame, draws: DataFrame, theta: Sequence[float]) -> DataFrame:
    """g1 .. gp: the weighted mean over draws (stratum, pos, w) of a layout; draws of a stratum are averaged first."""
    p = len(theta)
    at = with_gradient(examples.join(F.broadcast(draws), ["stratum", "pos"]), theta)
    per = at.groupBy("stratum", "w").agg(*[F.avg(f"g{j}").alias(f"g{j}") for j in range(1, p + 1)])
    return per.agg(*[F.sum(F.col("w") * F.col(f"g{j}")).alias(f"g{j}") for j in range(1, p + 1)])


def moment_columns(p: int) -> list[tuple[str, int, int]]:
    return [(f"a{i}{j}", i, j) for i in range(1, p + 1) for j in range(i, p + 1)]


def _moments(rows: DataFrame, keys: Sequence[str], p: int) -> DataFrame:
    if p > MAX_COLUMNS_ORDER:
        raise ValueError(f"order {p} is above {MAX_COLUMNS_ORDER}; use the Arrow gradient")
    sums = [F.sum(F.col(f"x{i}") * F.col(f"x{j}")).alias(name) for name, i, j in moment_columns(p)]
    cross = [F.sum(F.col(f"x{j}") * F.col("y")).alias(f"c{j}") for j in range(1, p + 1)]
    out = rows.groupBy(*keys) if keys else rows.groupBy()
    return out.agg(F.count(F.lit(1)).alias("n"), *sums, *cross, F.sum(F.col("y") * F.col("y")).alias("yy"))


def moments(examples: DataFrame, keys: Sequence[str], p: int) -> DataFrame:
    """Sums of products per key: with A = mean x x', c = mean x y the gradient at any theta is 2 (A theta - c)."""
    return _moments(examples, keys, p)


def schedule_moments(positioned: DataFrame, schedule: DataFrame, p: int) -> DataFrame:
    """One row of moments per (outer, inner, role, stratum) of a schedule: all that a run with this schedule needs, in one job.

    Anchor rows find their example by (stratum, pos), or by gpos where pos is null; inner rows by gpos.
    """
    cols = ["y", *[f"x{j}" for j in range(1, p + 1)]]
    by_pos = schedule.filter("pos is not null").drop("gpos").join(positioned.select("stratum", "pos", *cols), ["stratum", "pos"])
    by_all = schedule.filter("pos is null").drop("pos").join(positioned.select("gpos", *cols), "gpos")
    keep = ["outer", "inner", "role", "stratum", *cols]
    return _moments(by_pos.select(keep).unionByName(by_all.select(keep)), ["outer", "inner", "role", "stratum"], p)


def matrices(row: dict, p: int) -> tuple[np.ndarray, np.ndarray, float]:
    """A, c and mean y**2 of a row of moments."""
    a = np.zeros((p, p))
    for name, i, j in moment_columns(p):
        a[i - 1, j - 1] = a[j - 1, i - 1] = row[name]
    n = row["n"]
    return a / n, np.array([row[f"c{j}"] for j in range(1, p + 1)]) / n, row["yy"] / n


def least_squares(examples: DataFrame, p: int) -> tuple[np.ndarray, float]:
    """The minimum of the mean squared error and its place, by normal equations of one pass."""
    a, c, yy = matrices(_moments(examples, [], p).first().asDict(), p)
    theta = np.linalg.solve(a, c)
    return theta, float(yy - c @ theta)


def vector_examples(points: DataFrame, p: int, series: Sequence[str]) -> DataFrame:
    """t and, for N series side by side, y_k and x_k_j (series k, j steps back); an example is a tick."""
    wide = points.groupBy("t").pivot("series_id", list(series)).agg(F.first("z"))
    from pyspark.sql import window as W

    order = W.Window.orderBy("t")
    names = {s: k for k, s in enumerate(series)}
    cols = [F.col(f"`{s}`").cast("double").alias(f"y_{k}") for s, k in names.items()]
    lags = [F.lag(F.col(f"`{s}`").cast("double"), j).over(order).alias(f"x_{k}_{j}") for s, k in names.items() for j in range(1, p + 1)]
    return wide.select("t", *cols, *lags).filter(F.col(f"x_0_{p}").isNotNull())


def var_full_gradient(examples: DataFrame, p: int, n: int, theta: np.ndarray) -> DataFrame:
    """output, series, lag, g: the mean gradient of the squared error of all outputs; theta[o, k, j] multiplies series k, j + 1 steps back."""
    rows = examples
    parts = []
    for o in range(n):
        r = sum((F.lit(float(theta[o, k, j])) * F.col(f"x_{k}_{j + 1}") for k in range(n) for j in range(p)), F.lit(0.0)) - F.col(f"y_{o}")
        rows = rows.withColumn(f"r_{o}", r)
        parts += [F.struct(F.lit(o).alias("output"), F.lit(k).alias("series"), F.lit(j + 1).alias("lag"), F.avg(F.lit(2.0) * F.col(f"r_{o}") * F.col(f"x_{k}_{j + 1}")).alias("g")) for k in range(n) for j in range(p)]
    return rows.agg(F.array(*parts).alias("parts")).select(F.explode("parts").alias("part")).select("part.*")
