"""Exact duplicates by skew-safe combining, in DataFrame functions only."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed, hot_safe_lookup

#: Deleted before texts are compared: the space and \x09-\x0D. Fixed values.
BLANKS = " \t\n\x0b\x0c\r"
SALT_GROUPS = 16
_TOP = 2**63 - 1


def _word() -> Column:
    return F.lit(Decimal(2**64)).cast("decimal(20,0)")


def normalised(text: Column) -> Column:
    return F.translate(F.coalesce(text.cast("string"), F.lit("")), BLANKS, "")


def _rank(length: Column, doc_id: Column) -> Column:
    """Orders rows by code points, then by smaller doc_id, in one fixed-width number that hash aggregation can keep."""
    return length.cast("decimal(38,0)") * _word() + (F.lit(_TOP).cast("decimal(20,0)") - F.coalesce(doc_id, F.lit(_TOP)).cast("decimal(20,0)"))


def _doc_of(rank: Column) -> Column:
    """The doc_id inside a rank; the largest long stands for null."""
    return F.nullif((F.lit(_TOP).cast("decimal(20,0)") - rank % _word()).cast("long"), F.lit(_TOP))


def exact_duplicates(docs: DataFrame, digest=lambda text: F.sha2(text, 256)) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256; one row per row of docs (doc_id, text).

    Texts are equal when identical without blanks; a null is an empty text. The longest original (code points), then the smallest
    doc_id, stays. A null doc_id ranks after all others; if a group has none other, keep_id is null and the rows are kept.
    Rows that repeat the winner's doc_id are all kept: the id names the document. An empty table gives no rows; other columns of docs, whatever
    their names, are not read.

    Each stage groups by digest and by the full normalised text: map-side partial aggregation deduplicates within a task, salted groups
    merge next, winners of the salts last. Rows find their winner by digest; digests that hold several texts (none, for SHA-256) are
    resolved by text in a branch of their own.
    """
    total = max(1, docs.count())
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).select("doc_id", normalised(F.col("text")).alias("norm"), F.length("text").alias("len"))
    keyed = keyed.withColumn("digest", digest(F.col("norm")))
    ranked = keyed.select("digest", "norm", F.pmod(F.xxhash64("doc_id"), F.lit(SALT_GROUPS)).cast("int").alias("salt"), _rank(F.col("len"), F.col("doc_id")).alias("rank"))
    salted = ranked.groupBy("digest", "norm", "salt").agg(F.max("rank").alias("rank"), F.count(F.lit(1)).alias("size"))
    whole = salted.groupBy("digest", "norm").agg(F.max("rank").alias("rank"), F.sum("size").alias("size"))
    per_digest = whole.groupBy("digest").agg(F.count(F.lit(1)).alias("texts"), F.max("rank").alias("rank"), F.sum("size").alias("size"))
    winners = checkpointed(per_digest.select("digest", "texts", "size", _doc_of(F.col("rank")).alias("keep_id")))

    found = hot_safe_lookup(keyed.select("doc_id", "digest"), winners, "digest", "size", total).filter("texts = 1").select("doc_id", "digest", "keep_id", F.col("size").alias("group_size"))
    clashing = winners.filter("texts > 1").select("digest")
    if not clashing.isEmpty():
        by_text = whole.join(clashing, "digest", "left_semi").select("digest", "norm", _doc_of(F.col("rank")).alias("keep_id"), F.col("size").alias("group_size"))
        own = keyed.join(clashing, "digest", "left_semi").join(by_text, ["digest", "norm"])
        found = found.union(own.select("doc_id", "digest", "keep_id", "group_size"))
    return found.select("doc_id", "keep_id", "group_size", F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull()).alias("kept"), F.col("digest").alias("text_sha256"))
