"""Language identification as a mixture: each document's language proportions by expectation-maximisation over its words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import frugal, small_batches
from stratafit.llm.text_arrays import FOLD, Chunk, row_text, text_chunks, words

#: Buckets of letter trigrams, and the one that counts for nothing.
BUCKETS = 1 << 16
NOTHING = BUCKETS
#: Added to every count.
SMOOTHING = 0.5
#: Cost of each further language, in units of half the logarithm of the number of words.
PENALTY = 2.0
ITERATIONS = 20
_LETTER = np.zeros(256, bool)
_LETTER[97:123] = _LETTER[128:] = True
_NOT_LETTER = ~_LETTER[FOLD]
_CLEAN = np.where(_LETTER[FOLD], FOLD, 32).astype(np.uint32)


def _grams(chunk: Chunk) -> np.ndarray:
    """The bucket of the trigram around each byte; bytes outside letters count for nothing. Documents don't touch."""
    here = _CLEAN[chunk.data]
    before, after = np.full(len(here), 32, np.uint32), np.full(len(here), 32, np.uint32)
    before[1:], after[:-1] = here[:-1], here[1:]
    cut = chunk.starts[1:-1]
    before[cut[cut < len(here)]] = 32
    after[cut[cut > 0] - 1] = 32
    code = (before << 16) | (here << 8) | after
    code *= np.uint32(0x9E3779B1)
    code >>= np.uint32(16)
    return np.where(here == 32, NOTHING, code)


def learn(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """Languages in code point order, and the log-likelihood of each bucket in each, from all rows of docs (text, lang) with a language.

    Counts are summed per task and then by Spark; the driver gets at most BUCKETS rows a language.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for batch in batches:
            langs = batch.column("lang").to_pylist()
            for chunk in text_chunks(batch.column("text")):
                codes = _grams(chunk)
                at = chunk.starts.tolist()
                for k in range(chunk.n):
                    own = counts.setdefault(langs[chunk.first + k], np.zeros(BUCKETS + 1, np.int64))
                    own += np.bincount(codes[at[k] : at[k + 1]], minlength=BUCKETS + 1)
        for lang, own in counts.items():
            used = np.flatnonzero(own[:BUCKETS])
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(used), pa.string()), pa.array(used.astype(np.int32)), pa.array(own[used])], names=["lang", "bucket", "n"])

    small_batches(docs.sparkSession)
    sums = docs.filter("lang is not null").select(F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text")).mapInArrow(frugal(run), "lang string, bucket int, n long")
    table = sums.groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    names = table["lang"].combine_chunks().dictionary_encode() if table.num_rows else pa.array([], pa.string()).dictionary_encode()
    langs = sorted(names.dictionary.to_pylist(), key=lambda x: x.encode())
    counts = np.zeros((len(langs), BUCKETS))
    place = np.array([langs.index(x) for x in names.dictionary.to_pylist()], int)
    counts[place[names.indices.to_numpy()], table["bucket"].to_numpy()] = table["n"].to_numpy()
    model = np.zeros((len(langs), BUCKETS + 1), np.float32)
    if langs:
        model[:, :BUCKETS] = np.log((counts + SMOOTHING) / (counts.sum(axis=1, keepdims=True) + SMOOTHING * BUCKETS))
    return langs, model


def _fit(likelihood: np.ndarray, iterations: int) -> tuple[np.ndarray, float]:
    """Proportions of the columns, and the log-likelihood, by expectation-maximisation over rows."""
    share = np.full(likelihood.shape[1], 1 / likelihood.shape[1])
    for _ in range(iterations):
        mass = likelihood @ share
        new = share * ((1 / mass) @ likelihood) / len(likelihood)
        if np.abs(new - share).max() < 1e-3:
            share = new
            break
        share = new
    return share, float(np.log(likelihood @ share).sum())


def mixture(scores: np.ndarray, penalty: float = PENALTY, iterations: int = ITERATIONS) -> np.ndarray:
    """Proportions of the languages in one document; scores has a log-likelihood for each word and language.

    Languages leave the set from the smallest proportion on, while the penalised likelihood rises.
    """
    top = scores.max(axis=1, keepdims=True)
    likelihood = np.exp(np.maximum(scores - top, -60.0)).astype(np.float64)
    cost = penalty * 0.5 * np.log(len(scores) + 1)
    active = np.arange(scores.shape[1])
    share, fit = _fit(likelihood, iterations)
    best = (fit - cost * len(active), active, share)
    while len(active) > 1:
        # Languages without a word's worth of mass add nothing to the likelihood and leave together.
        order = np.argsort(-share, kind="stable")
        keep = max(1, min(len(active) - 1, int((share > 0.5 / len(scores)).sum())))
        active = np.sort(active[order[:keep]])
        share, fit = _fit(likelihood[:, active], iterations) if keep > 1 else (np.ones(1), float(np.log(likelihood[:, active[0]]).sum()))
        if fit - cost * len(active) >= best[0]:
            best = (fit - cost * len(active), active, share)
    out = np.zeros(scores.shape[1])
    out[best[1]] = best[2] / best[2].sum()
    return out


def identify_rows(docs: DataFrame, langs: list[str], model: np.ndarray, penalty: float = PENALTY) -> DataFrame:
    """row (all columns of docs), lang_pred, score, proportions (language -> share of words) for each row of docs, of which text is read.

    und and 0 where the text is null or has no letter, or nothing was learned; ties go to the first language in code point order.
    """
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), F.coalesce(F.col("text").cast("string").rlike(r"\p{L}"), F.lit(False)).alias("_letters"))
    schema = rows.select("row", F.lit("").alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(None).cast("map<string,double>").alias("proportions")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            letters = batch.column("_letters").to_pylist()
            names, scores, shares = [], [], []
            for chunk in text_chunks(row_text(batch)):
                codes = _grams(chunk)
                found = words(chunk, _NOT_LETTER)
                each = np.stack([np.add.reduceat(row[codes], found.begin) for row in table], axis=1) if len(found.begin) and len(langs) else np.zeros((0, len(langs)))
                first = found.first.tolist()
                for k in range(chunk.n):
                    own = each[first[k] : first[k + 1]]
                    if not letters[chunk.first + k] or not len(own):
                        names.append("und"), scores.append(0.0), shares.append([])
                        continue
                    share = mixture(own, penalty)
                    best = int(np.argmax(share))
                    names.append(langs[best]), scores.append(min(1.0, float(share[best])))
                    shares.append([(langs[i], float(share[i])) for i in np.flatnonzero(share)])
            yield pa.RecordBatch.from_arrays(
                [batch.column("row"), pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(shares, pa.map_(pa.string(), pa.float64()))], names=["row", "lang_pred", "score", "proportions"]
            )

    return rows.mapInArrow(frugal(run), schema)


def fold(doc_id: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo; a null id is in fold 0."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % modulus, F.lit(0))


def language_of(docs: DataFrame) -> DataFrame:
    """Learn from the three quarters of docs that aren't held out, and identify every row. A null language teaches nothing.

    A null doc_id is never held out; rows that repeat an id are identified text by text, and each teaches. An empty table gives no rows. Other columns are not read.
    """
    marked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang", (fold("doc_id", 4) == 2).alias("held_out"))
    langs, model = learn(marked.filter("not held_out"))
    return identify_rows(marked.select("doc_id", "text", "held_out"), langs, model).select("row.doc_id", "row.held_out", "lang_pred", "score", "proportions")
