"""MinHash near-duplicate groups with tensored banding.

Two small collections of minhash sub-signatures stand in for many independent bands: every pair (one of each
collection) is a table key, so SLOTS sub-signatures a side give SLOTS**2 keys out of 2 * SLOTS * ROWS minhashes, where
plain banding would need SLOTS**2 * 2 * ROWS. Candidates are confirmed on full shingle sets.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import checkpointed, collect_garbage, components, frugal, hot_keys, hot_safe_lookup, salted_join, small_batches
from stratafit.llm.text_arrays import document_shingles, scramble, text_chunks

SLOTS = 16
ROWS = 3
PERCENT = 75
_BLOCK = 2048


def _minhashes(shingles: np.ndarray, multipliers: np.ndarray, seconds: np.ndarray) -> np.ndarray:
    """The least value of each hash function over the set, a block of the set at a time."""
    low = (shingles ^ (shingles >> np.uint64(32))).astype(np.uint32)
    least = np.full(len(multipliers), 0xFFFFFFFF, np.uint32)
    for i in range(0, len(low), _BLOCK):
        mixed = low[None, i : i + _BLOCK] * multipliers
        mixed ^= mixed >> np.uint32(15)
        mixed *= seconds
        np.minimum(least, mixed.min(axis=1), out=least)
    return least


def signatures(docs: DataFrame, slots: int = SLOTS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, digest (128 bits of the exact shingle set, null without words), subs (2 * slots sub-signatures)."""
    count = 2 * slots * rows
    rng = np.random.default_rng(97)
    multipliers = (rng.integers(1, 2**31, (count, 1), dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
    seconds = (rng.integers(1, 2**31, (count, 1), dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
    tags = rng.integers(1, 2**63, 2 * slots, dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, digests, lengths, values = [], [], [0], []
            for chunk in text_chunks(batch.column("text")):
                for _, shingles in document_shingles(chunk):
                    distinct = np.unique(shingles)
                    sizes.append(len(distinct))
                    if len(distinct):
                        digests.append(hashlib.blake2b(distinct.tobytes(), digest_size=16).digest())
                        least = _minhashes(distinct, multipliers, seconds).astype(np.uint64).reshape(2 * slots, rows)
                        sub = tags.copy()
                        for r in range(rows):
                            sub = scramble(sub ^ least[:, r])
                        values.append(sub.view(np.int64))
                    else:
                        digests.append(None)
                    lengths.append(lengths[-1] + (2 * slots if len(distinct) else 0))
            flat = np.concatenate(values) if values else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(flat))],
                names=["doc_id", "n_shingles", "digest", "subs"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(frugal(run), "doc_id long, n_shingles long, digest binary, subs array<long>")


def shingle_sets(docs: DataFrame) -> DataFrame:
    """node (the doc_id) and its sorted distinct shingle hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id")
            for chunk in text_chunks(batch.column("text")):
                sets = [np.unique(s).view(np.int64) for _, s in document_shingles(chunk)]
                lengths = np.concatenate([[0], np.cumsum([len(s) for s in sets])])
                yield pa.RecordBatch.from_arrays([ids.slice(chunk.first, chunk.n), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(np.concatenate(sets)))], names=["node", "shingles"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(frugal(run), "node long, shingles array<long>")


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the similarity; pairs of a that has very many are salted."""
    left = sets.select(F.col("node").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("node").alias("b"), F.col("shingles").alias("sb"))
    both = salted_join(pairs.join(right, "b"), left, "a", hot_keys(pairs, "a", max(1, pairs.count())), "b", "inner")
    common = F.size(F.array_intersect("sa", "sb"))
    return both.filter(F.lit(100) * common >= F.lit(percent) * (F.size("sa") + F.size("sb") - common)).select("a", "b")


def candidate_keys(classes: DataFrame, slots: int = SLOTS) -> DataFrame:
    """(node, n, key) for every table key that a class shares with another.

    A key is shared only if both its halves are, so sub-signatures that one class alone has are dropped before
    keys are formed: texts unlike all others form none.
    """
    parts = classes.select("node", "n", F.posexplode("subs").alias("slot", "half"))
    shared = parts.groupBy("half").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("half")
    halves = parts.join(shared, "half").groupBy("node", "n").agg(
        F.collect_list(F.when(F.col("slot") < slots, F.col("half"))).alias("firsts"), F.collect_list(F.when(F.col("slot") >= slots, F.col("half"))).alias("seconds")
    )
    return halves.select("node", "n", F.explode("firsts").alias("f"), "seconds").select("node", "n", "f", F.explode("seconds").alias("s")).select("node", "n", F.xxhash64("f", "s").alias("key"))


def prefix_candidates(sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Distinct pairs (a, b), a < b, that hold every pair of sets (node, root, shingles) of different roots that reaches the similarity.

    Exact: sets are ordered rarest shingle first, and a pair that reaches it must meet in a prefix. With x the larger, overlap is at most what follows the
    first common shingle in either, so x offers for each class of smaller sizes, and each set for its own size, only the places where enough follows. A set
    of a crowd with many shingles of its own thus meets nobody. Any order of shingles is right; rarity comes from counts of 2**20 buckets of hashes.
    In a place where many sets of one component meet, only the others are paired with all.
    """
    slots = 1 << 20

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(slots, np.int64)
        for batch in batches:
            total += np.bincount(batch.column("shingles").flatten().to_numpy().view(np.uint64) >> np.uint64(44), minlength=slots)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array(total[used])], names=["slot", "n"])

    sets = checkpointed(sets)
    seen = sets.select("shingles").mapInArrow(frugal(count), "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    rarity = np.zeros(slots, np.int64)
    rarity[seen["slot"].to_numpy()] = seen["n"].to_numpy()
    shared = sets.sparkSession.sparkContext.broadcast(rarity)

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            nodes, roots, shingles = batch.column("node").to_pylist(), batch.column("root").to_pylist(), batch.column("shingles")
            for node, root, values in zip(nodes, roots, shingles, strict=True):
                own = values.values.to_numpy().view(np.uint64)
                n = len(own)
                own = own[np.lexsort((own, shared.value[own >> np.uint64(44)]))]
                smaller = np.arange(-(-percent * n // 100), n + 1)
                classes, at = np.unique(np.floor(24 * np.log(smaller)).astype(np.int64), return_index=True)
                keys, pos, probes = [], [], []
                for kind, least in [*zip(classes.tolist(), smaller[at].tolist(), strict=True), (None, n)]:
                    # (100 + percent) * overlap >= percent * (n + least), and n - place follow the place, itself included
                    length = max(0, min(n, n - -(-percent * (n + least) // (100 + percent)) + 1))
                    tag = scramble(np.array([int(classes[-1]) if kind is None else kind], np.uint64))[0]
                    keys.append(scramble(own[:length] ^ tag)), pos.append(np.arange(length)), probes.append(np.full(length, kind is not None))
                key = np.concatenate(keys)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(key.view(np.int64)), pa.array(np.concatenate(probes)), pa.array(np.full(len(key), node)), pa.array(np.full(len(key), root)), pa.array(np.full(len(key), n, np.int32)), pa.array(np.concatenate(pos).astype(np.int32))],
                    names=["key", "probe", "node", "root", "n", "place"],
                )

    found = sets.select("node", "root", "shingles").mapInArrow(frugal(places), "key long, probe boolean, node long, root long, n int, place int")
    met = found.groupBy("key", "root").agg(F.count(F.lit(1)).alias("c")).groupBy("key").agg(F.max_by("root", F.struct("c", "root")).alias("crowd"), F.count(F.lit(1)).alias("groups")).filter("groups > 1").select("key", "crowd")
    rows = checkpointed(found.join(met, "key").withColumn("few", F.col("root") != F.col("crowd")))
    collect_garbage(sets.sparkSession)
    larger = rows.filter("probe").select("key", F.col("node").alias("x"), F.col("root").alias("rx"), F.col("n").alias("nx"), F.col("place").alias("px"), F.col("few").alias("fx"))
    smaller = rows.filter("not probe").select("key", F.col("node").alias("y"), F.col("root").alias("ry"), F.col("n").alias("ny"), F.col("place").alias("py"), F.col("few").alias("fy"))
    enough = (F.col("nx") >= F.col("ny")) & (F.lit(100 + percent) * F.least(F.col("nx") - F.col("px"), F.col("ny") - F.col("py")) >= F.lit(percent) * (F.col("nx") + F.col("ny"))) & (F.col("rx") != F.col("ry"))
    pairs = larger.filter("fx").join(smaller, ["key"]).filter(enough).select("x", "y").union(larger.filter("not fx").join(smaller.filter("fy"), ["key"]).filter(enough).select("x", "y"))
    return pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def near_duplicate_components(docs: DataFrame, percent: int = PERCENT, slots: int = SLOTS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept, one row per row of docs (doc_id, text).

    Documents are linked when 100 * |intersection| >= percent * |union| of their sets of distinct 5-word shingles
    (A-Z folded; 1 to 4 words make one shingle; none without words or with a null text, which links with nothing).
    An empty table gives no rows; other columns of docs, whatever their names, are not read.
    component_id is the smallest doc_id reachable. Rows that repeat a doc_id share its component. A null doc_id joins no link;
    such a row is kept, with component_id the smallest doc_id that has exactly its set, or null.

    Equal sets make one class, joined by the digest of the set. Per table key each class is paired with the key's smallest class. The classes
    of keys that this leaves in several components are searched again, exactly, by prefix_candidates; so every pair that shares a key is confirmed, refused
    on full sets, or already in one component, and the pairs of a large group are not all formed. At similarity 0.75 a pair shares
    a key with probability (1 - (1 - 0.75**3)**16)**2, about 0.9997, and 0.99998 at 0.8.
    """
    small_batches(docs.sparkSession)
    total = max(1, docs.count())
    signed = checkpointed(signatures(docs, slots, rows))
    classes = checkpointed(
        signed.filter("n_shingles > 0").groupBy("digest").agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("members"), F.first("n_shingles").alias("n"), F.first("subs").alias("subs"))
    )
    keys = candidate_keys(classes.filter("node is not null"), slots)
    leaders = keys.groupBy("key").agg(F.min("node").alias("leader"), F.count(F.lit(1)).alias("c")).filter("c > 1")
    keyed = checkpointed(keys.join(leaders, "key").select("key", "node", "n", "leader", "c"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(keyed.select(F.col("node").alias("doc_id")).distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    sets = checkpointed(shingle_sets(texts))
    collect_garbage(docs.sparkSession)

    sized = keyed.filter("node != leader").select(F.col("leader").alias("a"), F.col("node").alias("b"), "n").distinct()
    of = keyed.filter("node = leader").select(F.col("node").alias("a"), F.col("n").alias("na")).distinct()
    able = F.lit(100) * F.least("na", "n") >= F.lit(percent) * F.greatest("na", "n")
    star = checkpointed(sized.join(of, "a").filter(able).select("a", "b"))
    links = checkpointed(_confirmed(star, sets, percent))
    roots = components(links)
    collect_garbage(docs.sparkSession)

    # Keys whose classes are still in several components: one row per key and component; a crowd of a component comes in by its root, not by each member's keys.
    tied = checkpointed(keyed.filter("c > 2").select("key", "node"))
    linked = checkpointed(roots.join(tied.select("node").distinct(), "node"))
    placed = tied.join(linked, "node", "left").groupBy("key", F.coalesce("root", "node").alias("root")).agg(F.min("node").alias("first"), F.max("node").alias("last"), F.count(F.lit(1)).alias("n"))
    placed = checkpointed(placed)
    open_keys = placed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("key")
    meeting = checkpointed(placed.join(open_keys, "key", "left_semi"))
    crowds = meeting.filter("n > 2").select("root").distinct()
    few = meeting.filter("n <= 2").select(F.explode(F.array("first", "last")).alias("node"), "root")
    members = salted_join(linked.select("node", "root"), crowds, "root", hot_keys(linked, "root", max(1, linked.count())), "node", "inner").select("node", "root")
    rest = checkpointed(few.union(members).distinct())
    collect_garbage(docs.sparkSession)
    across = prefix_candidates(sets.join(rest, "node"), percent)
    more = checkpointed(_confirmed(checkpointed(across.join(star, ["a", "b"], "left_anti")), sets, percent))
    if not more.isEmpty():
        roots = components(links.union(more))
    collect_garbage(docs.sparkSession)

    named = classes.join(roots.filter("root is not null"), "node", "left").select("digest", "members", F.coalesce("root", "node").alias("component"))
    found = hot_safe_lookup(signed.select("doc_id", "n_shingles", "digest"), named, "digest", "members", total)
    component = F.coalesce(F.col("component"), F.col("doc_id"))
    return found.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))
