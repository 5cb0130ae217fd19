"""Sharding by longest-processing-time scheduling: groups of equal texts, largest first, each to the least-loaded shard."""

from __future__ import annotations

import heapq
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.llm.common import checkpointed

#: Units that the scheduler sees per shard, at most twice so many: large groups one by one, small ones in bundles.
UNITS = 1024
#: Rows of a shard that one task numbers, about.
SLOT_ROWS = 100_000


def longest_processing_time(sizes: Sequence[tuple[int, object]], shards: int) -> dict[object, int]:
    """unit -> shard. Largest first, ties by unit; a heap gives the least-loaded shard, ties by number."""
    heap = [(0, k) for k in range(shards)]
    placed = {}
    for size, unit in sorted(sizes, key=lambda x: (-x[0], x[1])):
        load, k = heapq.heappop(heap)
        placed[unit] = k
        heapq.heappush(heap, (load + size, k))
    return placed


def shard_documents(docs: DataFrame, shards: int = 40, units: int = UNITS, slot_rows: int = SLOT_ROWS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for each row of docs (doc_id, text); law is always bytes.

    A row's size is its text's UTF-8 bytes plus 16, a null text counts as empty. Equal texts stay in one shard. Shard sizes come as near as
    groups allow. slot numbers a shard's rows from 0 without gaps, in an order that a rerun repeats. A null doc_id is a row like any other, last in its part; repeated
    rows each get a slot. An empty table gives no rows. Other columns, whatever their names, are not read.

    The driver schedules at most 2 * shards * units units, however many documents there are: each group of at least 1 / (shards * units) of all
    bytes is a unit (there can't be more of them), smaller groups are hashed into shards * units bundles of whole groups. Both maps have that
    bound, so they are broadcast and rows never move to find their shard. Slots are numbered within (shard, part) and shifted by the parts before.
    """
    spark: SparkSession = docs.sparkSession
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(text, 256).alias("group"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    rows = checkpointed(rows)
    groups = checkpointed(rows.groupBy("group").agg(F.sum("size").alias("bytes")))
    whole = groups.agg(F.sum("bytes").alias("b")).first()["b"] or 0
    bundles = shards * units
    bundle = F.pmod(F.xxhash64("group"), F.lit(bundles)).cast("int")
    large = [(r["bytes"], r["group"]) for r in groups.filter(F.col("bytes") * bundles >= whole).collect()]
    small = [(r["bytes"], r["bundle"]) for r in groups.filter(F.col("bytes") * bundles < whole).groupBy(bundle.alias("bundle")).agg(F.sum("bytes").alias("bytes")).collect()]
    placed = longest_processing_time([(b, f"g{g}") for b, g in large] + [(b, f"b{k:09d}") for b, k in small], shards)
    by_group = spark.createDataFrame([(g, placed[f"g{g}"]) for _, g in large], "large string, large_shard int")
    by_bundle = spark.createDataFrame([(k, placed[f"b{k:09d}"]) for _, k in small], "bundle int, bundle_shard int")
    dealt = rows.join(F.broadcast(by_group), F.col("group") == F.col("large"), "left").withColumn("bundle", bundle).join(F.broadcast(by_bundle), "bundle", "left")
    dealt = dealt.withColumn("shard", F.coalesce("large_shard", "bundle_shard"))
    return _slotted(dealt, docs.count(), shards, slot_rows)


def _slotted(dealt: DataFrame, total: int, shards: int, slot_rows: int) -> DataFrame:
    parts = max(1, -(-total // (shards * slot_rows)) * 4)
    dealt = checkpointed(dealt.select("doc_id", "size", "text_crc32", "shard", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(parts)).cast("int").alias("part")))
    before = W.Window.partitionBy("shard").orderBy("part").rowsBetween(W.Window.unboundedPreceding, -1)
    offsets = dealt.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n")).select("shard", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    within = W.Window.partitionBy("shard", "part").orderBy(F.col("doc_id").asc_nulls_last(), "text_crc32", "size")
    numbered = dealt.withColumn("rank", F.row_number().over(within).cast("long") - 1).join(offsets, ["shard", "part"])
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("rank") + F.col("start")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
