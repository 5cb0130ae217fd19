"""Where prepared series, chunks and traces go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_points(points: DataFrame, path: str, by: str = "bucket") -> None:
    """Points in ranges of time, sorted by series inside, so that a time filter reads few row groups."""
    points.repartitionByRange(by).sortWithinPartitions("series_id", "t").write.mode("overwrite").parquet(path)


def write_strata(assigned: DataFrame, path: str) -> None:
    """Examples in a folder per stratum: for few strata, as calendar policies make."""
    assigned.repartition("stratum").write.mode("overwrite").partitionBy("stratum").parquet(path)


def save_chunks(chunks: DataFrame, table: str, buckets: int = 64) -> None:
    """Chunks as a table bucketed and sorted by (series_id, chunk_no), so that schedules of the same bucketing join without moving them."""
    chunks.write.mode("overwrite").bucketBy(buckets, "series_id", "chunk_no").sortBy("series_id", "chunk_no").saveAsTable(table)


def append_trace(trace: DataFrame, path: str) -> None:
    trace.write.mode("append").partitionBy("method").parquet(path)
