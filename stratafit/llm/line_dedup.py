"""Line deduplication by log templates: a fixed-depth tree over token count and leading tokens, variable fields generalised."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed, frugal, hot_safe_lookup, small_batches
from stratafit.llm.text_arrays import Chunk, scramble, text_chunks, word_hashes, words

#: Leading tokens that a tree path reads after the token count.
DEPTH = 3
#: A template recurs if lines of at least so many documents have it.
MIN_DOCS = 3
#: Shorter lines have no templates.
MIN_TOKENS = 4
#: Share of a template's tokens that must be constant.
CONSTANT = 0.6
#: A token is constant at shares of its leaf's lines, from the coarsest templates to the finest; MIN_DOCS holds besides.
SHARES = (0.5, 0.1, 0.02, 0.0)
_ANY = np.uint64(0x2545F4914F6CDD1D)
_DIGIT = np.zeros(256, np.int64)
_DIGIT[48:58] = 1
#: Bits of the filter by which the second pass knows leaves that hold several lines; a false hit costs time only.
FILTER_BITS = 1 << 21


def _lines(chunk: Chunk) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the words, and with one wildcard for all tokens with a digit; for each line that has words: the document, its number in it, its first word; last the count of words."""
    found = words(chunk)
    plain = word_hashes(chunk, found)
    digits = np.concatenate([[0], np.cumsum(_DIGIT[chunk.data])])
    hashes = np.where(digits[found.end] > digits[found.begin], _ANY, plain)
    breaks = np.concatenate([[0], np.cumsum(chunk.data == 10)])
    doc = np.repeat(np.arange(chunk.n), np.diff(found.first))
    number = breaks[found.begin] - breaks[chunk.starts[doc]]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (number[1:] != number[:-1])
    first = np.flatnonzero(new)
    return plain, hashes, doc[first], number[first], np.append(first, len(doc))


def _leaves(hashes: np.ndarray, first: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """For each line the hash of its tree path, and the hash of the whole line."""
    count = np.diff(first)
    leaf = scramble(count.astype(np.uint64))
    for k in range(depth):
        has = count > k
        leaf[has] = scramble(leaf[has] ^ (hashes[first[:-1][has] + k] + np.uint64(k + 1)))
    place = scramble((np.arange(len(hashes)) - np.repeat(first[:-1], count)).astype(np.uint64) + np.uint64(77)) | np.uint64(1)
    whole = scramble(np.add.reduceat(hashes * place, first[:-1]) + count.astype(np.uint64)) if len(count) else np.zeros(0, np.uint64)
    return leaf, whole


def tree_lines(docs: DataFrame, depth: int = DEPTH, min_tokens: int = MIN_TOKENS, short_tokens: int = MIN_TOKENS) -> DataFrame:
    """doc_id, digest (64-bit hash of the text), line (number in the text), leaf and whole (64-bit hashes) of every line of at least min_tokens tokens, and of those of at least short_tokens, each text of which is a leaf.

    A short line is hashed with its digits: it recurs only as it is.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, digests = batch.column("doc_id"), batch.column("digest")
            for chunk in text_chunks(batch.column("text")):
                plain, hashes, doc, number, first = _lines(chunk)
                leaf, whole = _leaves(hashes, first, depth)
                short = np.diff(first) < min_tokens
                whole[short] = scramble(_leaves(plain, first, depth)[1][short] + _ANY)
                leaf[short] = scramble(whole[short])
                keep = np.diff(first) >= min(min_tokens, short_tokens)
                rows = pa.array(doc[keep] + chunk.first)
                yield pa.RecordBatch.from_arrays(
                    [ids.take(rows), digests.take(rows), pa.array(number[keep].astype(np.int32)), pa.array(leaf[keep].view(np.int64)), pa.array(whole[keep].view(np.int64))], names=["doc_id", "digest", "line", "leaf", "whole"]
                )

    return docs.select("doc_id", F.xxhash64("text").alias("digest"), "text").mapInArrow(frugal(run), "doc_id long, digest long, line int, leaf long, whole long")


def _tokens_of(docs: DataFrame, bits: np.ndarray, depth: int, min_tokens: int) -> DataFrame:
    """leaf, whole, tokens (hashes) of the lines whose leaf may be among those wanted."""
    shared = docs.sparkSession.sparkContext.broadcast(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = shared.value
        for batch in batches:
            for chunk in text_chunks(batch.column("text")):
                _, hashes, _, _, first = _lines(chunk)
                leaf, whole = _leaves(hashes, first, depth)
                count = np.diff(first)
                keep = np.flatnonzero((count >= min_tokens) & wanted[(leaf % np.uint64(len(wanted))).astype(np.int64)])
                _, once = np.unique(whole[keep], return_index=True)
                keep = keep[once]
                n = count[keep]
                at = np.concatenate([[0], np.cumsum(n)])
                flat = hashes[np.repeat(first[:-1][keep] - at[:-1], n) + np.arange(at[-1])]
                yield pa.RecordBatch.from_arrays([pa.array(leaf[keep].view(np.int64)), pa.array(whole[keep].view(np.int64)), pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(flat.view(np.int64)))], names=["leaf", "whole", "tokens"])

    return docs.select("text").mapInArrow(frugal(run), "leaf long, whole long, tokens array<long>")


def recurring_lines(docs: DataFrame, min_docs: int = MIN_DOCS, depth: int = DEPTH, constant: float = CONSTANT, min_tokens: int = MIN_TOKENS, short_tokens: int = MIN_TOKENS) -> tuple[DataFrame, DataFrame]:
    """(lines, templates): lines has doc_id, digest, line, whole; templates has whole and template for the lines of templates that recur.

    Lines of one leaf share their token count and leading tokens. In a leaf, a token that at least a share of its lines, and min_docs of them, have at a
    position is constant (a line counts once per document that has it), any other is a variable field. A line's template is its constant tokens, if they are at least the given share; so lines
    that differ in variable fields meet in one template, and a line that recurs as it is is its own template. As a share of the leaf, a field stays a field
    however large the corpus; of the SHARES, a line takes the largest whose template recurs, that is, is in min_docs documents (distinct doc_ids).
    Supports are counted per (leaf, position, token), with partial sums, so a leaf that holds a large share of all lines is no single group.
    """
    lines = checkpointed(tree_lines(docs, depth, min_tokens, short_tokens))
    spread = checkpointed(lines.select("leaf", "whole", "doc_id").distinct().groupBy("leaf", "whole").agg(F.count(F.lit(1)).alias("docs")))
    open_leaves = checkpointed(spread.groupBy("leaf").agg(F.sum("docs").alias("leaf_docs"), F.count(F.lit(1)).alias("texts")).filter((F.col("leaf_docs") >= min_docs) & (F.col("texts") > 1)))
    several = checkpointed(hot_safe_lookup(spread, open_leaves, "leaf", "texts", max(1, spread.count()), "whole"))
    own = several.filter(F.col("texts").isNull() & (F.col("docs") >= min_docs)).select("whole", F.col("whole").alias("template"))
    several = several.filter("texts is not null").select("leaf", "whole", "docs", "leaf_docs")

    bits = np.zeros(FILTER_BITS, bool)
    # At most FILTER_BITS rows come to the driver, whatever the number of leaves; the size divides 2**64, so signed and unsigned hashes agree on their remainder.
    wanted = open_leaves.select((F.pmod(F.col("leaf"), F.lit(FILTER_BITS))).cast("int").alias("b")).distinct().toArrow()
    bits[wanted["b"].to_numpy()] = True
    tokens = _tokens_of(docs, bits, depth, min_tokens).join(several, ["leaf", "whole"]).dropDuplicates(["leaf", "whole"])
    weighed = checkpointed(tokens.select("leaf", "whole", "docs", "leaf_docs", F.posexplode("tokens").alias("at", "token")))
    support = weighed.groupBy("leaf", "at", "token").agg(F.sum("docs").alias("support")).filter(F.col("support") >= min_docs)
    mark = F.xxhash64("at", "token").cast("decimal(38,0)")
    holds = [F.col("support") >= F.col("leaf_docs") * F.lit(share) for share in SHARES]
    fixed = weighed.join(support, ["leaf", "at", "token"], "left").groupBy("leaf", "whole").agg(
        F.count(F.lit(1)).alias("n"), *[f for k, h in enumerate(holds) for f in (F.count_if(h).alias(f"kept{k}"), F.sum(F.when(h, mark)).alias(f"sum{k}"))]
    )
    levels = F.array(*[F.when(F.col(f"kept{k}") >= F.lit(constant) * F.col("n"), F.xxhash64("leaf", "n", f"kept{k}", f"sum{k}")) for k in range(len(SHARES))])
    made = fixed.select("whole", F.posexplode(F.array_distinct(F.array_compact(levels))).alias("rank", "template"))
    found = checkpointed(own.select("whole", F.lit(0).alias("rank"), "template").union(made))
    count = lines.select("whole", "doc_id").distinct().join(found, "whole").select("template", "doc_id").distinct().groupBy("template").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") >= min_docs)
    return lines, found.join(count, "template", "left_semi").groupBy("whole").agg(F.min_by("template", "rank").alias("template"))


def drop_recurring_lines(docs: DataFrame, min_docs: int = MIN_DOCS, keep_first: bool = True, **tree: float) -> DataFrame:
    """docs with recurring lines left out of text, and columns n_lines, n_dropped; one row per row of docs.

    keep_first leaves each template's first line (smallest doc_id, then hash of the text, then line) where it is; otherwise all go. A null text stays null with 0 lines; an
    empty one has one line. Lines shorter than MIN_TOKENS stay unless short_tokens says from how many tokens on they go where they recur as they are; blank ones stay.
    Rows that share a doc_id are one document to the counts, but each text is cleaned by its own lines; rows of equal id and text come back equal. A null doc_id
    counts as one document, whose lines stay. Columns n_lines and n_dropped of docs are replaced; other columns pass, whatever their names. An empty table gives no rows.
    """
    small_batches(docs.sparkSession)
    base = docs.withColumn("doc_id", F.col("doc_id").cast("long")).withColumn("text", F.col("text").cast("string"))
    lines, templates = recurring_lines(base, min_docs, **tree)
    hits = checkpointed(lines.filter("doc_id is not null").join(templates, "whole").select("doc_id", "digest", "line", "template"))
    if keep_first:
        first = hits.groupBy("template").agg(F.min(F.struct("doc_id", "digest", "line")).alias("_first")).select("template", "_first.*")
        hits = hits.join(first, ["template", "doc_id", "digest", "line"], "left_anti")
    gone = hits.groupBy("doc_id", "digest").agg(F.collect_set("line").alias("gone")).select(F.col("doc_id").alias("_of"), F.col("digest").alias("_digest"), "gone")
    kept = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    rows = base.select(F.struct(*[base[c] for c in kept]).alias("_row"), base["doc_id"].alias("_of"), F.xxhash64(base["text"]).alias("_digest")).join(gone, ["_of", "_digest"], "left")
    text = F.col("_row.text")
    rest = F.array_join(F.filter(F.split(text, "\n"), lambda _, i: ~F.array_contains("gone", i)), "\n")
    return rows.select(
        *[F.when(F.col("gone").isNull(), text).otherwise(rest).alias(c) if c == "text" else F.col("_row").getField(c).alias(c) for c in kept],
        F.coalesce(F.size(F.split(text, "\n")), F.lit(0)).alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).alias("n_dropped"),
    )
