"""Cost and accuracy measures: gradient variance overall, inside strata and of samplers; losses, stationarity, comparison of runs."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.functions import portable
from stratafit.operators.gradients import with_gradient
from stratafit.operators.prepared import prepared
from stratafit.operators.spans import cell_width, span_join
from stratafit.operators.strata import Policy, layout, stratum_table

#: Ranges of random numbers, as bits, in which examples are ordered at once: their counts are that many rows.
RANGE_BITS = 12


def _total(p: int, f=F.var_pop):
    return sum((f(f"g{j}") for j in range(1, p + 1)), F.lit(0.0))


def gradient_variance(examples: DataFrame, theta: Sequence[float], batch: int = 1) -> DataFrame:
    """n, variance: mean squared distance of an example's gradient from the mean gradient, over the batch size."""
    return with_gradient(examples, theta).agg(F.count(F.lit(1)).alias("n"), (_total(len(theta)) / batch).alias("variance"))


def stratum_variance(assigned: DataFrame, theta: Sequence[float], per_stratum: int = 1) -> DataFrame:
    """stratum, n, w, variance: the same inside each stratum."""
    inside = with_gradient(assigned, theta).groupBy("stratum").agg((_total(len(theta)) / per_stratum).alias("variance"))
    return stratum_table(assigned).join(inside, "stratum")


def variance_dependency(assigned: DataFrame, theta: Sequence[float], per_stratum: int = 1) -> DataFrame:
    """One row: strata, total (uniform, one draw), within, between, stratified (sum of w**2 times inside variance), dependency (strata times that),
    mean_inside, within_share; and worse, whether the dependency is above the total, as unequal strata can make it."""
    # One pass over the examples: strata keep their size, inside variance and mean gradient; the total follows from them.
    p = range(1, len(theta) + 1)
    inside = with_gradient(assigned, theta).groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), _total(len(theta)).alias("v"), *[F.avg(f"g{j}").alias(f"m{j}") for j in p])
    n = F.sum("n")
    between = sum((F.sum(F.col("n") * F.col(f"m{j}") * F.col(f"m{j}")) / n - F.pow(F.sum(F.col("n") * F.col(f"m{j}")) / n, F.lit(2)) for j in p), F.lit(0.0))
    b = inside.agg(
        F.count(F.lit(1)).alias("strata"), (F.sum(F.col("n") * F.col("v")) / n).alias("within"), between.alias("between"),
        (F.sum(F.col("n") * F.col("n") * F.col("v")) / (n * n) / per_stratum).alias("stratified"), (F.avg("v") / per_stratum).alias("mean_inside"),
    )
    return b.withColumn("total", F.col("within") + F.col("between")).select(
        "strata", "total", "within", "between", "stratified", (F.col("strata") * F.col("stratified")).alias("dependency"), "mean_inside",
        (F.col("within") / F.nullif("total", F.lit(0.0))).alias("within_share"), (F.col("strata") * F.col("stratified") > F.col("total")).alias("worse"),
    )


def relabelled(assigned: DataFrame, seed: int = 3) -> DataFrame:
    """The same strata sizes, dealt to examples at random: what any policy is judged against.

    Examples are ordered by random numbers of 52 bits: within ranges of their first bits, and counts of the ranges place these. Their rank finds its stratum
    by cells of ranks.
    """
    strata = stratum_table(assigned)
    ends = strata.select("stratum", "n", F.sum("n").over(W.Window.orderBy("stratum")).alias("hi"))
    total = F.broadcast(strata.agg(cell_width(F.sum("n"), F.count(F.lit(1))).alias("_width")))
    rows = assigned.drop("stratum").withColumn("_bits", portable.bits(seed, "relabel", F.col("series_id"), F.col("t0"))).withColumn("_range", F.shiftright("_bits", 52 - RANGE_BITS))
    before = W.Window.orderBy("_range").rowsBetween(W.Window.unboundedPreceding, -1)
    starts = rows.groupBy("_range").agg(F.count(F.lit(1)).alias("_c")).select("_range", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_start"))
    inside = F.row_number().over(W.Window.partitionBy("_range").orderBy("_bits", "series_id", "t0")) - 1
    ranked = rows.withColumn("_i", inside).join(F.broadcast(starts), "_range").withColumn("_r", F.col("_i") + F.col("_start")).drop("_bits", "_range", "_i", "_start")
    spans = ends.select("stratum", (F.col("hi") - F.col("n")).alias("lo"), "hi")
    return span_join(ranked.join(total), spans.join(total), "_r", "_width").drop("_r")


def policy_comparison(examples: DataFrame, policies: dict[str, Policy], theta: Sequence[float], control: bool = True) -> DataFrame:
    """policy, strata, total, within_share, dependency, random_share (of the relabelled control)."""
    examples, rows = prepared(examples), None
    for name, policy in policies.items():
        assigned = policy.assign(examples)
        one = variance_dependency(assigned, theta).select(F.lit(name).alias("policy"), "strata", "total", "within_share", "dependency")
        if control:
            one = one.join(F.broadcast(variance_dependency(relabelled(assigned), theta).select(F.col("within_share").alias("random_share"))))
        rows = one if rows is None else rows.unionByName(one)
    return rows


def sampler_variance(assigned: DataFrame, theta: Sequence[float], repeats: int, per_stratum: int, seed: int) -> DataFrame:
    """sampler, draws, empirical: mean squared distance from the full gradient of repeated estimates, uniform and stratified, at equal draws."""
    p = len(theta)
    g = [f"g{j}" for j in range(1, p + 1)]
    positioned, strata = layout(assigned)
    at = with_gradient(positioned, theta).select("stratum", "pos", "gpos", *g)
    sums = strata.agg(F.sum("n").alias("total"), F.count(F.lit(1)).alias("strata"))
    reps = strata.sparkSession.range(repeats).withColumnRenamed("id", "rep")
    drawn = reps.join(F.broadcast(strata)).select("rep", "stratum", "n", "w", F.explode(F.sequence(F.lit(0), F.lit(per_stratum - 1))).alias("draw"))
    strat = drawn.withColumn("pos", F.floor(portable.uniform(seed, "rep", F.col("rep"), F.col("stratum"), F.col("draw")) * F.col("n")).cast("long")).join(at.drop("gpos"), ["stratum", "pos"])
    strat = strat.groupBy("rep").agg(*[F.sum(F.col("w") * F.col(c) / per_stratum).alias(c) for c in g]).withColumn("sampler", F.lit("stratified"))
    plain = reps.join(F.broadcast(sums)).select("rep", "total", F.explode(F.sequence(F.lit(0).cast("long"), F.col("strata") * per_stratum - 1)).alias("draw"))
    plain = plain.withColumn("gpos", F.floor(portable.uniform(seed, "rep", F.col("rep"), F.lit("u"), F.col("draw")) * F.col("total")).cast("long")).join(at.drop("pos", "stratum"), "gpos")
    plain = plain.groupBy("rep").agg(*[F.avg(c).alias(c) for c in g]).withColumn("sampler", F.lit("uniform"))
    mean = at.agg(*[F.avg(c).alias(f"m_{c}") for c in g])
    both = strat.select("sampler", *g).unionByName(plain.select("sampler", *g)).join(F.broadcast(mean))
    spread = sum(((F.col(c) - F.col(f"m_{c}")) * (F.col(c) - F.col(f"m_{c}")) for c in g), F.lit(0.0))
    return both.groupBy("sampler").agg(F.avg(spread).alias("empirical")).join(F.broadcast(sums)).select("sampler", (F.col("strata") * per_stratum).alias("draws"), "empirical")


def comparison(trace: DataFrame, metric: str = "train_loss") -> DataFrame:
    """method, runs, mean, deviation of the last metric of each run."""
    last = trace.groupBy("method", "run").agg(F.max_by(metric, "grad_evals").alias("value"))
    return last.groupBy("method").agg(F.count(F.lit(1)).alias("runs"), F.avg("value").alias("mean"), F.stddev_samp("value").alias("deviation"))


def first_hit(trace: DataFrame, epsilon: float) -> DataFrame:
    """method, run, grad_evals at which the gradient norm first is at most epsilon; runs that never get there give no row."""
    return trace.filter(F.col("grad_norm") <= epsilon).groupBy("method", "run").agg(F.min("grad_evals").alias("grad_evals"))
