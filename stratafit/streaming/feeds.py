"""Streams of events as the same series, strata and segments that batches give."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from stratafit.functions import portable
from stratafit.operators.prepared import checkpoint_folder


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; event time becomes a timestamp, which watermarks ask for."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly_cents(stream: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """start, series_id, z_cents: windows of an hour by type; rows later than lateness are dropped."""
    amount = F.round(F.col("value") * 100).cast("long")
    counted = stream.withWatermark("ts", lateness).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.sum(amount).alias("z_cents"))
    return counted.select(F.col("window.start").alias("start"), F.col("event_type").alias("series_id"), "z_cents")


def sliding_counts(stream: DataFrame, length: str = "6 hours", slide: str = "3 hours", lateness: str = "1 hour") -> DataFrame:
    counted = stream.withWatermark("ts", lateness).groupBy(F.window("ts", length, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", lateness: str = "1 hour") -> DataFrame:
    counted = stream.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return counted.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def first_events(stream: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Each event once, repeats within the lateness dropped."""
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def stratum_counts(stream: DataFrame, stratum: Column) -> DataFrame:
    """stratum, n so far; the column expression is the one that batches use."""
    return stream.groupBy(stratum.alias("stratum")).agg(F.count(F.lit(1)).alias("n"))


def weighted(stream: DataFrame, strata: DataFrame, stratum: Column) -> DataFrame:
    """Each event with its stratum's size and weight, joined to the static table."""
    return stream.withColumn("stratum", stratum).join(F.broadcast(strata), "stratum")


def segment_stream(points: DataFrame, tau_c: int, tau_p: int) -> DataFrame:
    """series_id, t0, context, target as points (series_id, t, z) arrive in order of t: state is a ring of tau_c + tau_p values a series.

    Points of a batch are sorted by t; a point not newer than the last one seen is dropped.
    """
    length = tau_c + tau_p

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, ring = state.get if state.exists else (-1, [])
        ring = list(ring)
        rows = []
        batch = pd.concat(list(frames)).sort_values("t")
        for t, z in zip(batch["t"].tolist(), batch["z"].tolist(), strict=True):
            if t <= last:
                continue
            last = t
            ring = [*ring, z][-length:]
            if len(ring) == length:
                rows.append((key[0], last - tau_p, ring[:tau_c], ring[tau_c:]))
        state.update((last, ring))
        yield pd.DataFrame(rows, columns=["series_id", "t0", "context", "target"])

    return points.groupBy("series_id").applyInPandasWithState(step, "series_id string, t0 long, context array<double>, target array<double>", "last long, ring array<double>", "append", GroupStateTimeout.NoTimeout)


def run_once(result: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is and return the rows, which executors write as Parquet beside the checkpoints: a folder per micro-batch, written again if
    a batch is repeated; in complete mode the last batch's."""
    spark, folder = result.sparkSession, f"{checkpoint_folder(result.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    done: list[str] = []

    def write(batch: DataFrame, number: int) -> None:
        path = f"{folder}/rows/{number}"
        batch.write.mode("overwrite").parquet(path)
        done[:] = [path] if mode == "complete" else [*(p for p in done if p != path), path]

    query = result.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(result.schema).parquet(*done) if done else spark.createDataFrame([], result.schema)


def reservoirs(stream: DataFrame, stratum: Column, size: int, key: str, seed: int = 3) -> DataFrame:
    """stratum, u, key: after each micro-batch, those of a uniform sample without replacement of at most size keys a stratum that are new to it.

    The sample holds the keys of the smallest random numbers, which come from the key alone, so it is the same however events are cut into micro-batches: among all rows
    given out, the first size of each stratum. State is size numbers a stratum.
    """

    def step(label: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(state.get[0]) if state.exists else []
        batch = pd.concat(list(frames)).drop_duplicates("u").sort_values("u").head(size)
        new = batch[~batch["u"].isin(held)]
        held = sorted([*held, *new["u"].tolist()])[:size]
        state.update((held,))
        yield new[new["u"] <= held[-1]].assign(stratum=label[0])[["stratum", "u", "key"]]

    rows = stream.select(stratum.cast("int").alias("stratum"), portable.bits(seed, "reservoir", F.col(key)).alias("u"), F.col(key).cast("long").alias("key"))
    return rows.groupBy("stratum").applyInPandasWithState(step, "stratum int, u long, key long", "held array<long>", "append", GroupStateTimeout.NoTimeout)


def refresh_anchor(stream: DataFrame, anchor, checkpoint: str | None = None):
    """Call anchor(batch, number) for each micro-batch, as an anchor's refresh does; returns the started query."""
    writer = stream.writeStream.foreachBatch(anchor).trigger(availableNow=True)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()


def drift_alarm(shares: DataFrame, threshold: float) -> DataFrame:
    """Batches of (batch, within_share) in which strata have come to explain too little: within_share above threshold."""
    return shares.withColumn("alarm", F.col("within_share") > threshold)
