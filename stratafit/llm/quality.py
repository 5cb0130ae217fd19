"""Quality classifier: naive Bayes support vectors over n-gram indicators."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed, frugal, small_batches
from stratafit.llm.language_id import fold
from stratafit.llm.text_arrays import Chunk, text_chunks, word_hashes, words

BITS = 18
#: Labelled rows that fitting uses at most, those with the smallest hash of the id. The bound keeps the fit on one machine.
FIT_ROWS = 6000
#: Distinct n-gram buckets that those rows hold together at most, which bounds the fit's memory to about 400 MB however long the texts are.
FIT_BUCKETS = 1 << 25
EPOCHS = 15
COST = 1.0
SMOOTHING = 1.0
#: Shapes of bytes: small letter, capital, digit, blank; punctuation stays itself, bytes above 127 are small letters.
_SHAPE = np.arange(256, dtype=np.uint32)
_SHAPE[97:123] = _SHAPE[128:] = 97
_SHAPE[65:91] = 65
_SHAPE[48:58] = 48
_SHAPE[[9, 10, 11, 12, 13, 32]] = 32


def _codes(chunk: Chunk) -> list[np.ndarray]:
    """For each byte position of the chunk, a bucket of the trigram there and one of the shape 5-gram there."""
    x = chunk.data.astype(np.uint32)
    s = _SHAPE[chunk.data]
    found = []
    for values, length, tag in ((x, 3, 0x85EBCA6B), (s, 5, 0xC2B2AE35)):
        n = max(0, len(values) - length + 1)
        code = np.zeros(n, np.uint32)
        for k in range(length):
            code *= np.uint32(0x01000193)
            code ^= values[k : k + n]
        code *= np.uint32(tag)
        code ^= code >> np.uint32(15)
        code *= np.uint32(0x9E3779B1)
        found.append(code >> np.uint32(32 - BITS))
    return found


def _repeats(chunk: Chunk) -> tuple[np.ndarray, list[int]]:
    """For each word, a bucket of the 5-gram there by which of its words equal the one before; and where documents' words begin."""
    found = words(chunk)
    hashes = word_hashes(chunk, found)
    same = (hashes[1:] == hashes[:-1]).astype(np.uint32)
    n = max(0, len(same) - 3)
    code = np.full(n, 0x27D4EB2F, np.uint32)
    for k in range(4):
        code = (code << np.uint32(1)) ^ same[k : k + n]
    return (code * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS), found.first.tolist()


def indicators(chunk: Chunk) -> Iterator[tuple[int, np.ndarray]]:
    """(row, distinct buckets of its n-grams). Texts too short for an n-gram have none."""
    three, five = _codes(chunk)
    repeats, first = _repeats(chunk)
    at = chunk.starts.tolist()
    seen = np.zeros(1 << BITS, bool)
    for k in range(chunk.n):
        i, j = at[k], at[k + 1]
        a, b = three[i : max(i, j - 2)], five[i : max(i, j - 4)]
        c = repeats[first[k] : max(first[k], first[k + 1] - 4)]
        if len(a) > 20_000:
            seen[a] = seen[b] = seen[c] = True
            own = np.flatnonzero(seen)
            seen[own] = False
        else:
            own = np.unique(np.concatenate([a, b, c]))
        yield chunk.first + k, own.astype(np.int64)


@dataclass
class Model:
    weights: np.ndarray  # of each bucket, for rows scaled to length 1
    ratios: np.ndarray
    bias: float
    slope: float
    offset: float


def dual_coordinate_descent(rows: list[np.ndarray], values: list[np.ndarray], labels: np.ndarray, size: int, cost: float = COST, epochs: int = EPOCHS, seed: int = 5) -> tuple[np.ndarray, float]:
    """Weights and bias of the linear hinge-loss model: one dual variable at a time, in shuffled order, the bias as one more feature."""
    weights, bias = np.zeros(size), 0.0
    alpha = np.zeros(len(rows))
    square = np.array([float(v @ v) + 1.0 for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            y = labels[i]
            slope = y * (weights[rows[i]] @ values[i] + bias) - 1
            new = min(max(alpha[i] - slope / square[i], 0.0), cost)
            change = (new - alpha[i]) * y
            if change:
                weights[rows[i]] += change * values[i]
                bias += change
                moved = max(moved, abs(change))
                alpha[i] = new
        if moved < 1e-3:
            break
    return weights, bias


def _platt(margins: np.ndarray, labels: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the logistic curve through margins, by Newton steps with softened targets."""
    pos, neg = float((labels > 0).sum()), float((labels < 0).sum())
    goal = np.where(labels > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margins + b, -30, 30)))
        w = p * (1 - p) + 1e-9
        g = np.array([(p - goal) @ margins, (p - goal).sum()])
        h = np.array([[w @ margins**2 + 1e-6, w @ margins], [w @ margins, w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return max(a, 1e-6), b


def fit(labelled: DataFrame, rows: int = FIT_ROWS, buckets: int = FIT_BUCKETS) -> Model:
    """Class log-count ratios and support vectors from labelled (doc_id, text, quality 0 or 1): the first rows in the order of hashes of id and text, at most rows rows and
    buckets n-gram buckets of them. Rows alike in id and text teach once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in text_chunks(batch.column("text")):
                own = [x for _, x in indicators(chunk)]
                lengths = np.concatenate([[0], np.cumsum([len(x) for x in own])])
                flat = pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(np.concatenate(own).astype(np.int32)))
                named = [batch.column(c).slice(chunk.first, chunk.n) for c in ("doc_id", "text_hash", "quality")]
                yield pa.RecordBatch.from_arrays([*named, flat], names=["doc_id", "text_hash", "quality", "buckets"])

    small_batches(labelled.sparkSession)
    text = F.col("text").cast("string")
    coded = labelled.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_hash"), F.col("quality").cast("int").alias("quality"), text.alias("text")).mapInArrow(
        frugal(run), "doc_id long, text_hash long, quality int, buckets array<int>"
    )
    coded = checkpointed(coded.dropDuplicates(["doc_id", "text_hash"]).withColumn("rank", F.struct(F.xxhash64("doc_id").alias("h"), "doc_id", "text_hash")))
    first = coded.select("rank", F.size("buckets").cast("long").alias("n")).orderBy("rank").limit(rows + 1)
    so_far = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    beyond = first.select("rank", F.count(F.lit(1)).over(so_far).alias("r"), F.sum("n").over(so_far).alias("n")).filter((F.col("r") > rows) | (F.col("n") > buckets)).orderBy("rank").limit(1)
    table = coded.join(F.broadcast(beyond.select(F.col("rank").alias("stop"))), F.col("rank") >= F.col("stop"), "left_anti").select("doc_id", "text_hash", "quality", "buckets").toArrow()
    order = np.lexsort((table["text_hash"].to_numpy(), table["doc_id"].fill_null(-1).to_numpy()))
    labels = np.where(table["quality"].to_numpy() == 1, 1.0, -1.0)[order]
    flat = table["buckets"].combine_chunks()
    at, all_buckets = flat.offsets.to_numpy(), flat.values.to_numpy()
    found = [all_buckets[at[i] : at[i + 1]] for i in order]
    size = 1 << BITS
    if not len(found) or (labels > 0).all() or (labels < 0).all():
        known = 1.0 if len(found) and (labels > 0).all() else -1.0 if len(found) else 0.0
        return Model(np.zeros(size, np.float32), np.zeros(size, np.float32), 0.0, 1.0, 2 * known)
    counts = [np.full(size, SMOOTHING), np.full(size, SMOOTHING)]
    for own, y in zip(found, labels, strict=True):
        counts[int(y > 0)][own] += 1
    ratios = np.log(counts[1] / counts[1].sum()) - np.log(counts[0] / counts[0].sum())
    values = [v / max(np.sqrt(v @ v), 1e-12) for v in (ratios[x] for x in found)]
    weights, bias = dual_coordinate_descent(found, values, labels, size)
    # The curve is drawn through margins of rows the fit has not seen: five folds would do it again, so a model of the even rows judges the odd ones.
    even = [i for i in range(len(found)) if i % 2 == 0]
    w, b = dual_coordinate_descent([found[i] for i in even], [values[i] for i in even], labels[even], size)
    odd = np.array([i for i in range(len(found)) if i % 2])
    slope, offset = _platt(np.array([w[found[i]] @ values[i] + b for i in odd]), labels[odd]) if len(odd) else (1.0, 0.0)
    return Model((weights * ratios).astype(np.float32), (ratios**2).astype(np.float32), bias, slope, offset)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of docs (doc_id, text, held_out); a null text is an empty one."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            margins = np.zeros(batch.num_rows)
            for chunk in text_chunks(batch.column("text")):
                for i, own in indicators(chunk):
                    margins[i] = m.weights[own].sum(dtype=np.float64) / max(np.sqrt(m.ratios[own].sum(dtype=np.float64)), 1e-12) + m.bias
            p = 1 / (1 + np.exp(-np.clip(m.slope * margins + m.offset, -30, 30)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p), pa.array((p >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "held_out", F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(frugal(run), "doc_id long, held_out boolean, score double, predicted int")


def quality_of(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> DataFrame:
    """Fit on labelled documents that aren't held out, at most rows of them, and score every document.

    Labels other than 0 and 1, and repeated labels of a document beyond the smallest, teach nothing. The chosen ids are at most rows, so they are broadcast; fit() bounds
    the rows that have them, and their n-grams.
    A null text is an empty one; empty texts and those too short for an n-gram score by the bias alone. A null doc_id is scored, never held out and never taught. Rows that
    repeat a doc_id are scored text by text, and each text teaches once. An empty table gives no rows; without labels of both classes the score is constant. Other columns are not read.
    """
    usable = labels.filter("quality in (0, 1) and doc_id is not null").filter(fold("doc_id", 3) != 1).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    chosen = usable.select(F.col("doc_id").alias("_id"), "quality").orderBy(F.xxhash64("_id"), "_id").limit(rows)
    labelled = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).select("doc_id", "text", "quality")
    return score(docs.select("doc_id", "text", (fold("doc_id", 3) == 1).alias("held_out")), fit(labelled))
