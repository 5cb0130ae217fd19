"""From rows to regular series, and from series to training examples."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.sources.tables import CLOCKS, cents, table


def in_order() -> W.WindowSpec:
    return W.Window.partitionBy("series_id").orderBy("t")


def regularize(df: DataFrame, series: Column, ts: Column, value: Column, freq: str = "hour", fill: str = "zero") -> DataFrame:
    """series_id, t, bucket, z: one row per series and tick of the common span; value is an aggregate expression.

    fill: zero; ffill (carry the last value on, ticks before the first go); drop (ticks without rows go). t counts from the first tick of any series.
    """
    cells = df.groupBy(series.cast("string").alias("series_id"), CLOCKS[freq](ts).alias("bucket")).agg(value.alias("z"))
    span = cells.agg(F.min("bucket").alias("lo"), F.max("bucket").alias("hi"))
    if fill == "drop":
        return cells.join(F.broadcast(span)).select("series_id", (F.col("bucket") - F.col("lo")).alias("t"), "bucket", "z")
    spine = cells.select("series_id").distinct().join(F.broadcast(span)).select("series_id", "lo", F.explode(F.sequence("lo", "hi")).alias("bucket"))
    full = spine.join(cells, ["series_id", "bucket"], "left").withColumn("t", F.col("bucket") - F.col("lo"))
    if fill == "zero":
        return full.select("series_id", "t", "bucket", F.coalesce("z", F.lit(0)).alias("z"))
    if fill == "ffill":
        carried = F.last("z", ignorenulls=True).over(in_order().rowsBetween(W.Window.unboundedPreceding, 0))
        return full.select("series_id", "t", "bucket", carried.alias("z")).filter("z is not null")
    raise ValueError(f"unknown fill {fill}")


def hourly_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return regularize(e, F.col("event_type"), F.col("ts"), F.sum(cents(F.col("value"))))


def hourly_by_bucket(spark: SparkSession, sf_dir: str, buckets: int = 8) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return regularize(e, F.pmod("user_id", F.lit(buckets)), F.col("ts"), F.sum(cents(F.col("value"))))


def hourly_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each type's share in the hour's events; 0 in an empty hour."""
    counts = regularize(table(spark, sf_dir, "events"), F.col("event_type"), F.col("ts"), F.count(F.lit(1)))
    total = F.sum("z").over(W.Window.partitionBy("t"))
    return counts.select("series_id", "t", "bucket", F.coalesce(F.col("z") / F.nullif(total, F.lit(0)), F.lit(0.0)).alias("z"))


def _orders_with_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("n_nationkey"))
    return table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_totalprice").join(customers, "o_custkey")


def daily_by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    nations = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    o = _orders_with_nation(spark, sf_dir).join(F.broadcast(nations), "n_nationkey")
    return regularize(o, F.col("n_regionkey"), F.col("o_orderdate"), F.sum(cents(F.col("o_totalprice"))), "day")


def daily_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean price in whole cents of each nation, the last value carried on."""
    o = _orders_with_nation(spark, sf_dir)
    mean = F.floor(F.sum(cents(F.col("o_totalprice"))) / F.count(F.lit(1))).cast("long")
    return regularize(o, F.col("n_nationkey"), F.col("o_orderdate"), mean, "day", "ffill")


def monthly_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    suppliers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_extendedprice").join(suppliers, "l_suppkey")
    return regularize(li, F.col("s_nationkey"), F.col("l_shipdate"), F.sum(cents(F.col("l_extendedprice"))), "month")


def daily_by_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_quantity")
    return regularize(li, F.col("l_suppkey"), F.col("l_shipdate"), F.sum(F.round("l_quantity").cast("long")), "day", "drop")


def scaled_by_mean(points: DataFrame) -> DataFrame:
    """z divided by the mean absolute value of all points, so that series keep their relative scales."""
    mean = points.agg((F.sum(F.abs("z")).cast("double") / F.count(F.lit(1)).cast("double")).alias("m"))
    return points.join(F.broadcast(mean)).select("series_id", "t", "bucket", (F.col("z").cast("double") / F.col("m")).alias("z"))


def fit_scale(points: DataFrame, kind: str = "mean_abs") -> DataFrame:
    """series_id, shift, scale of the training points; a scale of 0 becomes 1."""
    z = F.col("z").cast("double")
    shift, scale = {
        "mean_abs": (F.lit(0.0), F.sum(F.abs(z)) / F.count(F.lit(1))),
        "max_abs": (F.lit(0.0), F.max(F.abs(z))),
        "zscore": (F.avg(z), F.stddev_pop(z)),
    }[kind]
    return points.groupBy("series_id").agg(shift.alias("shift"), F.coalesce(F.nullif(scale, F.lit(0.0)), F.lit(1.0)).alias("scale"))


def apply_scale(points: DataFrame, scale: DataFrame) -> DataFrame:
    return points.join(scale, "series_id").withColumn("z", (F.col("z") - F.col("shift")) / F.col("scale")).drop("shift", "scale")


def split_by_time(points: DataFrame, cutoff: int, tau_c: int) -> tuple[DataFrame, DataFrame]:
    """Training points (t < cutoff) and test points; test contexts reach tau_c ticks back, test targets do not."""
    return points.filter(F.col("t") < cutoff), points.filter(F.col("t") >= cutoff - tau_c)


def lag_examples(points: DataFrame, order: int) -> DataFrame:
    """series_id, t0, y, x1 .. x_order: the next value and the values 1 to order steps before it."""
    z = F.col("z").cast("double")
    lags = [F.lag(z, j).over(in_order()).alias(f"x{j}") for j in range(1, order + 1)]
    extra = [c for c in points.columns if c not in ("series_id", "t", "z")]
    return points.select("series_id", (F.col("t") - 1).alias("t0"), *extra, z.alias("y"), *lags).filter(F.col(f"x{order}").isNotNull())


def segments(points: DataFrame, tau_c: int, tau_p: int, stride: int = 1) -> DataFrame:
    """series_id, t0, context, target as arrays; t0 is the tick of the last context value. Ticks are taken as they come, gaps included."""
    frame = in_order().rowsBetween(-(tau_c - 1), tau_p)
    cut = points.select("series_id", F.col("t").alias("t0"), F.collect_list(F.col("z").cast("double")).over(frame).alias("w"), F.row_number().over(in_order()).alias("i"))
    cut = cut.filter((F.size("w") == tau_c + tau_p) & ((F.col("i") - tau_c) % stride == 0))
    return cut.select("series_id", "t0", F.slice("w", 1, tau_c).alias("context"), F.slice("w", tau_c + 1, tau_p).alias("target"))


def example_index(points: DataFrame, tau_c: int, tau_p: int) -> DataFrame:
    """series_id, points and examples per series, by arithmetic; no example is formed."""
    return points.groupBy("series_id").agg(F.count(F.lit(1)).alias("n_points")).withColumn("n_examples", F.greatest(F.lit(0).cast("long"), F.col("n_points") - F.lit(tau_c + tau_p - 1)))


def chunk_series(points: DataFrame, chunk_len: int, halo: int) -> DataFrame:
    """series_id, chunk_no, t_first, values: chunk_len ticks and the halo that follows them, on a dense clock.

    A point goes to its own chunk and, where it lies in the halo, to those before; so a chunk is one group of at most chunk_len + halo rows, however long the
    series, and overlapping windows are never stored.
    """
    own = F.floor(F.col("t") / chunk_len).cast("long")
    first = F.greatest(F.lit(0).cast("long"), F.floor((F.col("t") - halo) / chunk_len).cast("long"))
    spread = points.select("series_id", "t", F.col("z").cast("double").alias("z"), F.explode(F.sequence(first, own)).alias("chunk_no")).filter(F.col("t") < (F.col("chunk_no") + 1) * chunk_len + halo)
    grouped = spread.groupBy("series_id", "chunk_no").agg(F.min("t").alias("t_first"), F.array_sort(F.collect_list(F.struct("t", "z"))).alias("rows"))
    return grouped.select("series_id", "chunk_no", "t_first", F.transform("rows", lambda r: r["z"]).alias("values"))


def chunk_windows(batch: pa.RecordBatch, chunk_len: int, length: int) -> Iterator[tuple[str, int, np.ndarray]]:
    """Of each chunk of a batch: its series, the tick of its first value and the windows of so many values that begin in it, a row each."""
    for name, first, number, values in zip(batch.column("series_id"), batch.column("t_first").to_pylist(), batch.column("chunk_no").to_pylist(), batch.column("values"), strict=True):
        z = values.values.to_numpy()
        n = min(len(z) - length + 1, (number + 1) * chunk_len - first)
        if n > 0:
            yield name.as_py(), first, np.lib.stride_tricks.sliding_window_view(z, length)[:n]


def chunk_segments(chunks: DataFrame, chunk_len: int, tau_c: int, tau_p: int) -> DataFrame:
    """The segments of chunks made with a halo of tau_c + tau_p - 1, each once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, first, w in chunk_windows(batch, chunk_len, tau_c + tau_p):
                lists = [pa.FixedSizeListArray.from_arrays(pa.array(np.ascontiguousarray(part).reshape(-1)), part.shape[1]).cast(pa.list_(pa.float64())) for part in (w[:, :tau_c], w[:, tau_c:])]
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(w)), pa.array(first + tau_c - 1 + np.arange(len(w))), *lists], names=["series_id", "t0", "context", "target"])

    return chunks.select("series_id", "t_first", "chunk_no", "values").mapInArrow(run, "series_id string, t0 long, context array<double>, target array<double>")


def segments_at(drawn: DataFrame, chunks: DataFrame, chunk_len: int, tau_c: int, tau_p: int, few: bool = False) -> DataFrame:
    """drawn (series_id, t0 and more) with context and target, cut from the chunk in which the segment begins; few broadcasts drawn."""
    begin = F.col("t0") - (tau_c - 1)
    keyed = drawn.withColumn("chunk_no", F.floor(begin / chunk_len).cast("long"))
    at = (begin - F.col("t_first") + 1).cast("int")
    met = (F.broadcast(keyed) if few else keyed).join(chunks.select("series_id", "chunk_no", "t_first", "values"), ["series_id", "chunk_no"])
    return met.select(*drawn.columns, F.slice("values", at, F.lit(tau_c)).alias("context"), F.slice("values", at + tau_c, F.lit(tau_p)).alias("target"))


def _turned(f, period: int):
    """One term of a Fourier sum."""
    return lambda x, i: x * f(F.lit(2 * np.pi / period) * i)


def segment_features(segs: DataFrame, periods: Sequence[int] = (24,)) -> DataFrame:
    """series_id, t0 and of each context: mean, std, density (share of values other than 0), lag-1 autocorrelation, DFT magnitude at each period."""
    n = F.size("context")
    mean = F.aggregate("context", F.lit(0.0), lambda s, x: s + x) / n
    dev = F.transform("context", lambda x: x - F.col("mean"))
    base = segs.select("series_id", "t0", "context", mean.alias("mean")).withColumn("dev", dev)
    square = F.aggregate("dev", F.lit(0.0), lambda s, x: s + x * x)
    lagged = F.aggregate(F.zip_with(F.slice("dev", 1, n - 1), F.slice("dev", 2, n - 1), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    density = F.size(F.filter("context", lambda x: x != 0)) / n
    cols = [mean.alias("mean"), F.sqrt(square / n).alias("std"), density.alias("density"), F.coalesce(lagged / F.nullif(square, F.lit(0.0)), F.lit(0.0)).alias("autocorr")]
    for p in periods:
        parts = [F.aggregate(F.transform("context", _turned(f, p)), F.lit(0.0), lambda s, x: s + x) for f in (F.cos, F.sin)]
        cols.append((F.sqrt(parts[0] * parts[0] + parts[1] * parts[1]) / n).alias(f"spectrum_{p}"))
    return base.select("series_id", "t0", *cols)


def calendar(bucket: Column, freq: str) -> dict[str, Column]:
    """Calendar covariates of a tick: day, weekday (Monday 0), hour of day, month, quarter, year where the clock has them."""
    if freq == "month":
        month = F.pmod(bucket, F.lit(12))
        return {"month": month + 1, "quarter": F.floor(month / 3) + 1, "year": F.floor(bucket / 12) + 1970}
    day = bucket if freq == "day" else F.floor(bucket / 24)
    date = F.date_add(F.lit("1970-01-01").cast("date"), day.cast("int"))
    out = {"day": day, "weekday": F.pmod(day + 3, F.lit(7)), "month": F.month(date), "quarter": F.quarter(date), "year": F.year(date)}
    if freq == "hour":
        hour = F.pmod(bucket, F.lit(24))
        out |= {"hour": hour, "hour_sin": F.sin(hour * (2 * np.pi / 24)), "hour_cos": F.cos(hour * (2 * np.pi / 24))}
    return out
