"""Samplers and whole training schedules, made ahead of training: draws depend on a seed and counters, never on parameters."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.functions import portable
from stratafit.functions.portable import py_uniform
from stratafit.operators.spans import CELLS, span_join


def _position(u: Column, n: Column) -> Column:
    return F.least(F.floor(u * n), n - 1).cast("long")


def uniform_draws(spark: SparkSession, total: int, size: int, seed: int, tag: str = "uniform", replacement: bool = True, examples: DataFrame | None = None) -> DataFrame:
    """draw, gpos: size draws from all examples. Without replacement the rows (gpos) of examples are needed: those with the smallest random numbers."""
    if not replacement:
        u = portable.uniform(seed, tag, F.col("gpos"))
        bound = min(1.0, (size + 10 * math.sqrt(size) + 10) / max(1, total))
        picked = examples.select("gpos", u.alias("u")).filter((F.col("u") <= bound) | F.lit(bound >= 1))
        return picked.orderBy("u", "gpos").limit(size).select((F.row_number().over(W.Window.orderBy("u", "gpos")) - 1).cast("long").alias("draw"), "gpos")
    return spark.range(size).select(F.col("id").alias("draw"), _position(portable.uniform(seed, tag, F.col("id")), F.lit(total)).alias("gpos"))


def series_then_time_draws(index: DataFrame, size: int, seed: int, correct: bool = False) -> DataFrame:
    """draw, series_id, i (number of the example in its series), weight: a series first, then an example of it.

    index has series_id and n_examples. With correct, weight is series * n_examples / total, which makes means over draws unbiased for the mean
    over examples; otherwise 1.
    """
    used = index.filter("n_examples > 0")
    ranked = used.select("series_id", "n_examples", (F.row_number().over(W.Window.orderBy("series_id")) - 1).alias("rank"))
    sums = used.agg(F.count(F.lit(1)).alias("series"), F.sum("n_examples").alias("total"))
    draws = index.sparkSession.range(size).select(F.col("id").alias("draw"), portable.uniform(seed, "series", F.col("id")).alias("u"), portable.uniform(seed, "time", F.col("id")).alias("v"))
    draws = draws.join(F.broadcast(sums)).withColumn("rank", _position(F.col("u"), F.col("series")))
    weight = F.col("series") * F.col("n_examples") / F.col("total") if correct else F.lit(1.0)
    return draws.join(ranked, "rank").select("draw", "series_id", _position(F.col("v"), F.col("n_examples")).alias("i"), weight.alias("weight"))


def stratified_draws(strata: DataFrame, per_stratum: int, seed: int, tag: str = "stratified") -> DataFrame:
    """stratum, draw, pos, w: per_stratum draws from each stratum, with replacement."""
    draws = strata.select("stratum", "n", "w", F.explode(F.sequence(F.lit(0), F.lit(per_stratum - 1))).alias("draw"))
    return draws.select("stratum", "draw", _position(portable.uniform(seed, tag, F.col("stratum"), F.col("draw")), F.col("n")).alias("pos"), "w")


def stratified_without_replacement(positioned: DataFrame, strata: DataFrame, per_stratum: int, seed: int) -> DataFrame:
    """stratum, draw, pos: distinct examples of each stratum, those with the smallest random numbers.

    A threshold that keeps ten standard deviations more than wanted goes first, so what is ordered is small.
    """
    bound = (F.lit(float(per_stratum)) + 10 * math.sqrt(per_stratum) + 10) / F.col("n")
    u = portable.uniform(seed, "without", F.col("stratum"), F.col("pos"))
    near = positioned.select("stratum", "pos", u.alias("u")).join(F.broadcast(strata), "stratum").filter(F.col("u") <= bound)
    rank = F.row_number().over(W.Window.partitionBy("stratum").orderBy("u", "pos")) - 1
    return near.withColumn("draw", rank).filter(F.col("draw") < per_stratum).select("stratum", "draw", "pos")


def bernoulli_strata(assigned: DataFrame, fractions: dict[int, float], seed: int) -> DataFrame:
    """Spark's own stratified sampling: of random size, so for looking around only."""
    return assigned.sampleBy("stratum", fractions, seed)


def weighted_draws(weights: DataFrame, size: int, seed: int) -> DataFrame:
    """draw, stratum, weight: strata drawn with probability proportional to mass; weight = 1 / (strata * probability) keeps the mean over strata unbiased."""
    total = F.sum("mass").over(W.Window.partitionBy())
    running = F.sum("mass").over(W.Window.orderBy("stratum"))
    spans = weights.select("stratum", ((running - F.col("mass")) / total).alias("lo"), (running / total).alias("hi"), (total / (F.count(F.lit(1)).over(W.Window.partitionBy()) * F.col("mass"))).alias("weight"))
    width = F.broadcast(weights.agg((F.lit(1.0) / F.greatest(F.lit(CELLS), F.count(F.lit(1)))).alias("_width")))
    draws = weights.sparkSession.range(size).select(F.col("id").alias("draw"), portable.uniform(seed, "weighted", F.col("id")).alias("u"))
    return span_join(draws.join(width), spans.join(width), "u", "_width").select("draw", "stratum", "weight")


def geometric_length(strata: int, u: float, cap: int | None = None) -> int:
    """Geometric from 0 with mean strata: P(K = k) = p**k * (1 - p), p = strata / (strata + 1)."""
    k = math.floor(math.log(1 - u) / math.log(strata / (strata + 1)))
    return k if cap is None else min(k, cap)


def geometric_lengths(outer: Column, strata: Column, seed: int) -> Column:
    """The same length of each row's outer step, with its strata as mean, from the random numbers of inner_lengths."""
    return F.floor(F.log(F.lit(1.0) - portable.uniform(seed, "length", outer)) / F.log(strata / (strata + 1))).cast("long")


def inner_lengths(outer: int, strata: int, seed: int, law: str = "geometric", fixed: int = 1, cap: int | None = None) -> list[int]:
    if law == "fixed":
        return [fixed] * outer
    return [geometric_length(strata, py_uniform(seed, "length", t), cap) for t in range(outer)]


def pick_iterate(step_sizes: list[float], u: float) -> int:
    """An outer step, with probability proportional to its step size."""
    target, run = u * sum(step_sizes), 0.0
    for t, a in enumerate(step_sizes):
        run += a
        if target < run:
            return t
    return len(step_sizes) - 1


def build_schedule(spark: SparkSession, lengths: list[int] | dict[int, int], strata: DataFrame, total: int, per_stratum: int, minibatch: int, seed: int, anchor: str = "stratified", batch: int | None = None) -> DataFrame:
    """All draws of a run: outer, inner, role, stratum, draw, pos, gpos. Anchor rows have inner -1.

    lengths are those of outer steps 0, 1, .. or, as a dict, of some of them: a step's draws don't depend on the others.
    anchor: stratified (a row per stratum and draw, pos in the stratum), batch (batch uniform draws, gpos), none, full (no rows: the optimizer reads everything).
    """
    rounds = spark.createDataFrame(list(lengths.items() if isinstance(lengths, dict) else enumerate(lengths)), "outer int, length int")
    steps = rounds.filter("length > 0").select("outer", F.explode(F.sequence(F.lit(0), F.col("length") - 1)).alias("inner"))
    inner = steps.select("outer", "inner", F.lit("inner").alias("role"), F.lit(None).cast("int").alias("stratum"), F.explode(F.sequence(F.lit(0), F.lit(minibatch - 1))).alias("draw"))
    inner = inner.select("*", F.lit(None).cast("long").alias("pos"), _position(portable.uniform(seed, "inner", F.col("outer"), F.col("inner"), F.col("draw")), F.lit(total)).alias("gpos"))
    if anchor == "stratified":
        first = rounds.join(F.broadcast(strata)).select("outer", F.lit(-1).alias("inner"), F.lit("anchor").alias("role"), "stratum", F.explode(F.sequence(F.lit(0), F.lit(per_stratum - 1))).alias("draw"), "n")
        u = portable.uniform(seed, "anchor", F.col("outer"), F.col("stratum"), F.col("draw"))
        first = first.select("outer", "inner", "role", "stratum", "draw", _position(u, F.col("n")).alias("pos"), F.lit(None).cast("long").alias("gpos"))
    elif anchor == "batch":
        first = rounds.select("outer", F.lit(-1).alias("inner"), F.lit("anchor").alias("role"), F.lit(0).alias("stratum"), F.explode(F.sequence(F.lit(0), F.lit((batch or 1) - 1))).alias("draw"))
        u = portable.uniform(seed, "anchor", F.col("outer"), F.col("stratum"), F.col("draw"))
        first = first.select("*", F.lit(None).cast("long").alias("pos"), _position(u, F.lit(total)).alias("gpos"))
    else:
        return inner
    return first.unionByName(inner)
