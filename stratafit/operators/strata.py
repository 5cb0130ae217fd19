"""Stratification policies over examples, and the layout of strata.

A policy is a column expression wherever it can be, so a stratum costs no pass of its own and is found again the same way on a stream.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.ml.clustering import BisectingKMeans, KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.functions import portable
from stratafit.operators.prepared import prepared
from stratafit.operators.series import calendar


#: Runs of series, by which blocks of examples are numbered.
RUNS = 256


class Policy:
    """assign() adds a column stratum, dense from 0; every example is in exactly one."""

    def key(self) -> Column | None:
        """A value per stratum as a column expression; None if the policy needs more than the row."""
        return None

    def assign(self, examples: DataFrame) -> DataFrame:
        key = self.key()
        if key is None:
            raise NotImplementedError(type(self).__name__)
        return dense(examples.withColumn("_key", key))

    def describe(self) -> str:
        return str(self)


def dense(examples: DataFrame, few: bool = False) -> DataFrame:
    """Number the distinct values of _key from 0 in their order; only strata that occur get a number.

    Distinct keys are as many as strata. The numbering is joined back, broadcast by Spark while it is small, or anyway where the policy bounds the keys (few): then the
    examples stay where they are.
    """
    keys = examples.select("_key").distinct()
    numbered = keys.select("_key", (F.row_number().over(W.Window.orderBy("_key")) - 1).alias("stratum"))
    return examples.join(F.broadcast(numbered) if few else numbered, "_key").drop("_key")


@dataclass
class ModPeriod(Policy):
    period: int = 8

    def key(self) -> Column:
        return F.pmod(F.col("t0"), F.lit(self.period))


@dataclass
class CalendarHash(Policy):
    """Levels of the calendar, coarse to fine, of the tick that is forecast first."""

    levels: Sequence[str]
    freq: str = "hour"

    def key(self) -> Column:
        found = calendar(F.col("bucket"), self.freq)
        return F.struct(*[found[x].cast("long").alias(x) for x in self.levels])


@dataclass
class WeekdaySeason(Policy):
    """Weekday with a season: a calendar field, or that many equal ranges of the data's span."""

    season: str | int = "year"
    freq: str = "day"

    def assign(self, examples: DataFrame) -> DataFrame:
        found = calendar(F.col("bucket"), self.freq)
        if isinstance(self.season, str):
            return dense(examples.withColumn("_key", F.struct(found["weekday"].alias("a"), found[self.season].cast("long").alias("b"))))
        span = examples.agg(F.min("bucket").alias("_lo"), F.max("bucket").alias("_hi"))
        bucket = F.floor((F.col("bucket") - F.col("_lo")) * self.season / (F.col("_hi") - F.col("_lo") + 1)).cast("long")
        return dense(examples.join(F.broadcast(span)).withColumn("_key", F.struct(found["weekday"].alias("a"), bucket.alias("b"))).drop("_lo", "_hi"), few=True)


@dataclass
class RangeThenSeries(Policy):
    ranges: int = 6

    def assign(self, examples: DataFrame) -> DataFrame:
        span = examples.agg(F.min("bucket").alias("_lo"), F.max("bucket").alias("_hi"))
        bucket = F.floor((F.col("bucket") - F.col("_lo")) * self.ranges / (F.col("_hi") - F.col("_lo") + 1)).cast("long")
        return dense(examples.join(F.broadcast(span)).withColumn("_key", F.struct(bucket.alias("a"), F.col("series_id").alias("b"))).drop("_lo", "_hi"))


@dataclass
class PerSeries(Policy):
    def key(self) -> Column:
        return F.col("series_id")


@dataclass
class RandomHash(Policy):
    strata: int
    seed: int = 7

    def key(self) -> Column:
        return F.pmod(portable.bits(self.seed, "stratum", F.col("series_id"), F.col("t0")), F.lit(self.strata))


@dataclass
class Cyclic(Policy):
    """Examples in order of (series_id, t0), dealt in turn; numbered by counts of series first, so no task orders all examples."""

    strata: int

    def assign(self, examples: DataFrame) -> DataFrame:
        return numbered(examples, "_n").withColumn("stratum", F.pmod("_n", F.lit(self.strata)).cast("int")).drop("_n")


@dataclass
class EqualSize(Policy):
    """Strata of sizes at most one apart, along the order of (series_id, t0)."""

    strata: int

    def assign(self, examples: DataFrame) -> DataFrame:
        total = examples.agg(F.count(F.lit(1)).alias("_total"))
        return numbered(examples, "_n").join(F.broadcast(total)).withColumn("stratum", F.floor(F.col("_n") * self.strata / F.col("_total")).cast("int")).drop("_n", "_total")


@dataclass
class Finest(Policy):
    """One example per stratum; optimizers take its anchor as the full gradient and never make the table."""

    def assign(self, examples: DataFrame) -> DataFrame:
        return numbered(examples, "stratum")


@dataclass
class GivenStratum(Policy):
    column: str

    def key(self) -> Column:
        return F.col(self.column)


@dataclass
class FeatureBins(Policy):
    """Equal-width bins of a bounded feature, such as the density of a context."""

    column: str
    bins: int
    low: float = 0.0
    high: float = 1.0

    def key(self) -> Column:
        width = (self.high - self.low) / self.bins
        return F.least(F.lit(self.bins - 1), F.greatest(F.lit(0), F.floor((F.col(self.column) - self.low) / width)))


@dataclass
class Compose(Policy):
    """The product of policies, such as clusters of series and then a calendar hash."""

    parts: Sequence[Policy]

    def key(self) -> Column | None:
        keys = [p.key() for p in self.parts]
        return None if any(k is None for k in keys) else F.struct(*[k.alias(f"k{i}") for i, k in enumerate(keys)])

    def assign(self, examples: DataFrame) -> DataFrame:
        if self.key() is not None:
            return super().assign(examples)
        found, names = examples, [f"_k{i}" for i in range(len(self.parts))]
        for name, part in zip(names, self.parts, strict=True):
            key = part.key()
            found = part.assign(found).withColumnRenamed("stratum", name) if key is None else found.withColumn(name, key)
        return dense(found.withColumn("_key", F.struct(*names)).drop(*names))


@dataclass
class MergeSmall(Policy):
    """Strata of fewer than min_n examples become one."""

    inner: Policy
    min_n: int

    def assign(self, examples: DataFrame) -> DataFrame:
        found = self.inner.assign(examples).withColumnRenamed("stratum", "_s")
        sizes = found.groupBy("_s").agg(F.count(F.lit(1)).alias("_n"))
        return dense(found.join(sizes, "_s").withColumn("_key", F.when(F.col("_n") < self.min_n, F.lit(-1)).otherwise(F.col("_s"))).drop("_s", "_n"))


@dataclass
class KMeansPolicy(Policy):
    """Clusters of a feature array: centres fitted on at most sample rows, every row assigned; level series clusters the mean features of series."""

    k: int
    features: str = "features"
    seed: int = 11
    sample: int = 100_000
    bisecting: bool = False
    level: str = "example"
    inertia: float | None = field(default=None, compare=False)

    def assign(self, examples: DataFrame) -> DataFrame:
        if self.level == "series":
            size = examples.select(F.size(self.features).alias("n")).first()["n"]
            means = examples.groupBy("series_id").agg(F.array(*[F.avg(F.get(self.features, F.lit(i))) for i in range(size)]).alias(self.features))
            clusters = KMeansPolicy(self.k, self.features, self.seed, self.sample, self.bisecting).assign(means).select("series_id", "stratum")
            return examples.join(clusters, "series_id")
        rows = examples.withColumn("_v", array_to_vector(F.col(self.features).cast("array<double>")))
        n = rows.count()
        train = rows if n <= self.sample else rows.sample(False, self.sample / n, self.seed)
        kind = BisectingKMeans if self.bisecting else KMeans
        model = kind(k=self.k, seed=self.seed, featuresCol="_v", predictionCol="_key").fit(train)
        self.inertia = float(model.summary.trainingCost)
        return dense(model.transform(rows).drop("_v"))


def _blocked(examples: DataFrame) -> DataFrame:
    return examples.withColumn("_block", F.floor(F.col("t0") / (1 << 20)).cast("long"))


def _offsets(counts: DataFrame, name: str, by: Sequence[str] = ()) -> DataFrame:
    """The number of examples before each block (by, series_id, _block; _c examples) within each value of by, in order of (series_id, _block).

    Blocks are added up within runs of series, and runs after that: at most RUNS series, picked by hash, are where runs begin. So no task orders all blocks.
    """
    hash_slot = F.pmod(F.xxhash64("series_id"), F.lit(RUNS))
    picks = counts.groupBy(hash_slot.alias("_slot")).agg(F.min_by("series_id", F.xxhash64("series_id", F.lit("pick"))).alias("_pick")).agg(F.collect_set("_pick").alias("_picks"))
    run = counts.join(F.broadcast(picks)).withColumn("_run", F.size(F.filter("_picks", lambda x: x <= F.col("series_id")))).drop("_picks")
    earlier = lambda *within: W.Window.partitionBy(*within).rowsBetween(W.Window.unboundedPreceding, -1)
    runs = run.groupBy(*by, "_run").agg(F.sum("_c").alias("_rc")).select(*by, "_run", F.coalesce(F.sum("_rc").over(earlier(*by).orderBy("_run")), F.lit(0)).alias("_before"))
    inner = run.select(*by, "series_id", "_block", "_run", F.coalesce(F.sum("_c").over(earlier(*by, "_run").orderBy("series_id", "_block")), F.lit(0)).alias("_in"))
    return inner.join(runs, [*by, "_run"]).select(*by, "series_id", "_block", (F.col("_in") + F.col("_before")).alias(name))


def numbered(examples: DataFrame, name: str, by: Sequence[str] = ()) -> DataFrame:
    """Number examples from 0 in order of (series_id, t0) within each value of by.

    Counts of blocks (a run of ticks of a series) give offsets; rows are numbered inside blocks only. So the work of a task is bounded by a block, and the
    result is that of one global row_number.
    """
    rows, keys = _blocked(examples), [*by, "series_id", "_block"]
    offsets = _offsets(prepared(rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("_c"))), "_start", by)
    inside = F.row_number().over(W.Window.partitionBy(*keys).orderBy("t0")) - 1
    return rows.withColumn("_i", inside).join(offsets, keys).withColumn(name, F.col("_i") + F.col("_start")).drop("_i", "_start", "_block")


def stratum_table(assigned: DataFrame) -> DataFrame:
    """stratum, n, w: sizes and weights; weights sum to 1, no stratum is empty."""
    sizes = assigned.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"))
    total = sizes.agg(F.sum("n").alias("_total"))
    return sizes.join(F.broadcast(total)).select("stratum", "n", (F.col("n") / F.col("_total")).alias("w"))


def layout(assigned: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The examples with pos, dense from 0 in each stratum, and gpos, dense from 0 over all, both in order of (series_id, t0); and the stratum table.

    One pass over the examples counts the blocks of strata, another numbers rows inside blocks, for both numbers after one exchange by block.
    """
    rows = _blocked(assigned)
    counts = prepared(rows.groupBy("stratum", "series_id", "_block").agg(F.count(F.lit(1)).alias("_c")))
    sizes = counts.groupBy("stratum").agg(F.sum("_c").alias("n"))
    table = sizes.join(F.broadcast(sizes.agg(F.sum("n").alias("_total")))).select("stratum", "n", (F.col("n") / F.col("_total")).alias("w"))
    whole = _offsets(counts.groupBy("series_id", "_block").agg(F.sum("_c").alias("_c")), "_g0")
    own = _offsets(counts, "_p0", ["stratum"])
    within = lambda *keys: F.row_number().over(W.Window.partitionBy(*keys).orderBy("t0")) - 1
    ranked = rows.withColumns({"_g": within("series_id", "_block"), "_p": within("series_id", "_block", "stratum")})
    offsets = own.join(whole, ["series_id", "_block"])
    placed = ranked.join(offsets, ["stratum", "series_id", "_block"]).withColumn("pos", F.col("_p") + F.col("_p0")).withColumn("gpos", F.col("_g") + F.col("_g0"))
    return placed.drop("_block", "_g", "_p", "_g0", "_p0"), table
