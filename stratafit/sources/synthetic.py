"""Synthetic series: the period-8 toy, seasonal carriers on given noise, and families of transformed ramps as a data source."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from stratafit.functions import portable


def toy(spark: SparkSession, n: int = 4000, step: float = math.pi / 4, noise: float = 0.2, seed: int = 1) -> DataFrame:
    """One series sin u + cos 2u + noise at u = step * t. At step pi/4 a period is 8 ticks; other steps have no period of whole ticks."""
    u = F.col("id") * F.lit(step)
    return spark.range(n).select(F.lit("toy").alias("series_id"), F.col("id").alias("t"), F.col("id").alias("bucket"), (F.sin(u) + F.cos(u * 2) + F.lit(noise) * portable.normal(seed, "toy", F.col("id"))).alias("z"))


def carrier(points: DataFrame, noise: float = 0.2) -> DataFrame:
    """A daily season on hourly points: 2 sin(2 pi h / 24) + cos(2 pi h / 6) + noise times the series' standardised values."""
    stats = points.groupBy("series_id").agg(F.avg("z").alias("m"), F.stddev_pop("z").alias("s"))
    h = F.pmod(F.col("bucket"), F.lit(24))
    season = F.lit(2.0) * F.sin(h * F.lit(2 * math.pi / 24)) + F.cos(h * F.lit(2 * math.pi / 6))
    return points.join(stats, "series_id").select("series_id", "t", "bucket", (season + F.lit(noise) * (F.col("z") - F.col("m")) / F.col("s")).alias("z"))


def toy_on(points: DataFrame, step: float = math.pi / 4, noise: float = 0.2) -> DataFrame:
    """The toy's season sin u + cos 2u at u = step * t on given points: noise times the series' standardised values stands for the random numbers."""
    stats = points.groupBy("series_id").agg(F.avg("z").alias("m"), F.stddev_pop("z").alias("s"))
    u = F.col("t") * F.lit(step)
    return points.join(stats, "series_id").select("series_id", "t", "bucket", (F.sin(u) + F.cos(u * 2) + F.lit(noise) * (F.col("z") - F.col("m")) / F.col("s")).alias("z"))


FAMILIES = ("sin1", "sin2", "sin4", "square", "cube", "sin_square", "root")


def family_values(family: str, t: np.ndarray, n: int) -> np.ndarray:
    """A ramp from 0 to 1 over n ticks, passed through a named transform."""
    x = t / n
    return {
        "sin1": lambda: np.sin(2 * np.pi * x), "sin2": lambda: np.sin(4 * np.pi * x), "sin4": lambda: np.sin(8 * np.pi * x), "square": lambda: x**2, "cube": lambda: x**3,
        "sin_square": lambda: np.sin(2 * np.pi * x) ** 2, "root": lambda: np.sqrt(x),
    }[family]()


def families_on(points: DataFrame, noise: float = 0.05) -> DataFrame:
    """series_id, family, t, z: each given series is a family. Its running share of its sum, a ramp from 0 to 1, goes through the family's transform (a multiple from the eighth
    series on), with noise times the standardised values added."""
    whole = W.Window.partitionBy("series_id")
    x = F.sum("z").over(whole.orderBy("t")) / F.sum("z").over(whole)
    full = F.lit(2 * math.pi) * F.col("x")
    shapes = {
        "sin1": F.sin(full), "sin2": F.sin(full * 2), "sin4": F.sin(full * 4), "square": F.col("x") * F.col("x"), "cube": F.col("x") * F.col("x") * F.col("x"), "sin_square": F.sin(full) * F.sin(full), "root": F.sqrt("x"),
    }
    names = points.select("series_id").distinct().select("series_id", (F.row_number().over(W.Window.orderBy("series_id")) - 1).alias("family"))
    shape = F.coalesce(*[F.when(F.col("family") % len(FAMILIES) == i, shapes[name]) for i, name in enumerate(FAMILIES)]) * (1 + F.floor(F.col("family") / len(FAMILIES)))
    spread = F.lit(noise) * (F.col("z") - F.avg("z").over(whole)) / F.stddev_pop("z").over(whole)
    return points.select("series_id", "t", x.alias("x"), spread.alias("spread")).join(names, "series_id").select("series_id", "family", "t", (shape + F.col("spread")).alias("z"))


class _Slice(InputPartition):
    def __init__(self, family: int, lo: int, hi: int) -> None:
        self.family, self.lo, self.hi = family, lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.n, self.noise, self.seed = int(options.get("n", "1000")), float(options.get("noise", "0.05")), int(options.get("seed", "0"))
        self.families, self.slice = int(options.get("families", "4")), int(options.get("slice", "100000"))

    def partitions(self) -> list[InputPartition]:
        return [_Slice(k, lo, min(self.n, lo + self.slice)) for k in range(self.families) for lo in range(0, self.n, self.slice)]

    def read(self, part: _Slice) -> Iterator[tuple]:
        t = np.arange(part.lo, part.hi)
        noise = np.random.default_rng((self.seed, part.family, part.lo)).normal(size=len(t)) * self.noise
        z = family_values(FAMILIES[part.family % len(FAMILIES)], t, self.n) * (1 + part.family // len(FAMILIES)) + noise
        for i, v in zip(t.tolist(), z.tolist(), strict=True):
            yield f"{FAMILIES[part.family % len(FAMILIES)]}.{part.family // len(FAMILIES)}", part.family, i, v


class SyntheticFamilies(DataSource):
    """spark.read.format("synthetic_families").option("families", 4).option("n", 1000): series_id, family (the true stratum), t, z."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_families"

    def schema(self) -> str:
        return "series_id string, family int, t bigint, z double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
