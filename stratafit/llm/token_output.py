"""Token files: ids of all documents in ascending doc_id order, in compressed segments, written and read by Spark."""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from stratafit.llm.common import frugal, release_memory, shared_folder, small_batches
from stratafit.llm.token_codec import pack_segment, unpack_segment
from stratafit.llm.token_pieces import worker_encoder

END_ID = 2
#: Ids in a segment, about: whole documents, as many blocks side by side as this holds.
SEGMENT_IDS = 1_000_000
_DOCS = 32
_DIGESTS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def write_tokens(docs: DataFrame, path: str, tokenizer: str, end_id: int = END_ID, segment_ids: int = SEGMENT_IDS) -> None:
    """Encode docs (doc_id, text) and write segments under path: Parquet rows (part, start, n_ids, segment), part and start ascending with doc_id.

    A null text is empty. Rows of one doc_id stand together; a null doc_id comes first. Documents are dealt by ranges of (doc_id, hash of the text),
    so rows that repeat an id can be split. Spark commits the files, so lost tasks run again.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encoder = worker_encoder(tokenizer)
        part, start = TaskContext.get().partitionId(), 0
        names: list[int | None] = []
        held: list[np.ndarray] = []
        count = 0

        def flush() -> pa.RecordBatch:
            nonlocal names, held, count, start
            release_memory()
            data = pack_segment(names, np.array([len(x) for x in held]), np.concatenate(held))
            out = pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([start], pa.int64()), pa.array([count], pa.int64()), pa.array([data], pa.binary())], names=["part", "start", "n_ids", "segment"])
            start += count
            names, held, count = [], [], 0
            release_memory()
            return out

        for batch in batches:
            lengths, flat = encoder.encode(batch.column("text"))
            ends = lengths.cumsum()
            for doc_id, lo, hi in zip(batch.column("doc_id").to_pylist(), (ends - lengths).tolist(), ends.tolist(), strict=True):
                names.append(doc_id), held.append(np.append(flat[lo:hi], np.uint32(end_id)))
                count += hi - lo + 1
                if count >= segment_ids:
                    yield flush()
        if names:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("_tie", F.xxhash64("text"))
    dealt = rows.repartitionByRange(F.col("doc_id").asc_nulls_first(), "_tie").sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "_tie").select("doc_id", "text")
    dealt.mapInArrow(frugal(run), "part int, start long, n_ids long, segment binary").write.mode("overwrite").parquet(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens and ids of each document in the files under path.

    Segments know their start within their part; parts are as many as the writing tasks, which bounds their broadcast. Checksums are verified.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for names, starts, lengths, ids in _documents(batches):
            flat = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(lengths)]), pa.int32()), pa.array(ids.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(starts), pa.array(lengths), flat], names=["doc_id", "start", "n_tokens", "ids"])

    return _placed(spark, path).mapInArrow(frugal(run), "doc_id long, start long, n_tokens long, ids array<int>")


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """token_digests of read_tokens, by the Python workers that read: one for each task, and no ids between two of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for names, starts, lengths, ids in _documents(batches):
            yield _digests(pa.array(names, pa.int64()), pa.array(starts), pa.array(lengths), np.concatenate([[0], np.cumsum(lengths)]), ids)

    return _placed(spark, path).mapInArrow(frugal(run), _DIGESTS)


def _placed(spark: SparkSession, path: str) -> DataFrame:
    """start among all ids and segment of each segment under path."""
    segments = spark.read.parquet(path)
    before = W.Window.orderBy("part").rowsBetween(W.Window.unboundedPreceding, -1)
    parts = segments.groupBy("part").agg(F.sum("n_ids").alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return segments.join(F.broadcast(parts), "part").select((F.col("start") + F.col("base")).alias("start"), "segment")


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[int | None], np.ndarray, np.ndarray, np.ndarray]]:
    """doc ids, starts, lengths and ids of some documents at a time."""
    for batch in batches:
        for base, data in zip(batch.column("start").to_pylist(), batch.column("segment"), strict=True):
            names, lengths, ids = unpack_segment(data.as_py())
            ends = np.cumsum(lengths)
            for i in range(0, len(names), _DOCS):
                own = lengths[i : i + _DOCS]
                lo, hi = int(ends[i] - lengths[i]), int(ends[min(i + _DOCS, len(names)) - 1])
                yield names[i : i + _DOCS], base + ends[i : i + _DOCS] - own, own, ids[lo:hi]


def _digests(names: pa.Array, starts: pa.Array, lengths: pa.Array, offsets: np.ndarray, ids: np.ndarray) -> pa.RecordBatch:
    at, flat = offsets.tolist(), ids.astype("<u4")
    crc = [zlib.crc32(flat[i:j].tobytes()) for i, j in zip(at[:-1], at[1:], strict=True)]
    return pa.RecordBatch.from_arrays([names, starts, lengths, pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def token_digests(tokens: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (of the ids as little-endian unsigned 32-bit integers) of what read_tokens gives."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("ids")
            yield _digests(batch.column("doc_id"), batch.column("start"), batch.column("n_tokens"), ids.offsets.to_numpy(), ids.values.to_numpy())

    return tokens.mapInArrow(frugal(run), _DIGESTS)


def tokens_round_trip(docs: DataFrame, tokenizer: str, path: str | None = None) -> DataFrame:
    """Write docs' tokens under path (a new folder beside the session's checkpoints if none is given), read them back and digest them.

    One row per row of docs (doc_id, text): null ids stand first, rows of one id together in the order of a hash of their texts. Null and empty texts are the end id
    alone. An empty table gives no rows. Other columns, whatever their names, are not read.
    """
    spark = docs.sparkSession
    small_batches(spark)
    path = path or f"{shared_folder(spark).rstrip('/')}/tokens-{uuid.uuid4().hex}"
    write_tokens(docs, path, tokenizer)
    return read_digests(spark, path)
