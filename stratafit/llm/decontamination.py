"""Benchmark decontamination: candidates by SimHash of item-sized windows and by the items' rarest shingles, exact weighted-shingle verification of every window."""

from __future__ import annotations

import itertools
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stratafit.llm.common import frugal, small_batches
from stratafit.llm.text_arrays import SHINGLE, row_text, scramble, sequence_hash, sequence_hashes, shingle_hashes, text_chunks, word_hashes, words

SIMILARITY = 0.75
#: Fingerprints of 64 bits that differ in at most RADIUS bits are found with certainty.
RADIUS = 7
BLOCKS = 4
#: A window class is the largest step of this progression that an item has words for.
STEP = 1.25
#: Bytes of benchmark text in one pass over the documents; a larger benchmark takes several passes.
PASS_BYTES = 16 << 20
#: Similarities within this of the bound reach it: sums of weights are rounded.
_SLACK = 1e-12
_CHUNK = 1 << 15
_SEED = np.uint64(0x5851F42D4C957F2D)


def _classes(longest: int) -> list[int]:
    found, x = [], 1.0
    while round(x) <= longest:
        if not found or round(x) > found[-1]:
            found.append(round(x))
        x = max(x * STEP, x + 1)
    return found


def fingerprints(hashes: np.ndarray, sizes: list[int]) -> dict[int, np.ndarray]:
    """For each size, the SimHash of every window of so many words: bit b is set if more than half of the words' hashes have it."""
    n = len(hashes)
    bits = np.unpackbits(scramble(hashes ^ _SEED).view(np.uint8).reshape(n, 8), axis=1)
    if max(sizes, default=0) > 255:
        bits = bits.astype(np.uint16 if max(sizes) < 65536 else np.uint32)
    sums, width = {1: bits}, 1
    while width * 2 <= max(sizes, default=0):
        have = sums[width]
        sums[2 * width] = have[: max(0, len(have) - width)] + have[width:]
        width *= 2
    out = {}
    for size in sizes:
        if size > n:
            out[size] = np.zeros(0, np.uint64)
            continue
        total, at = None, 0
        for p in sorted(sums):
            if size & p:
                part = sums[p][at : at + n - size + 1]
                total = part if total is None else total + part
                at += p
        out[size] = np.packbits(total > size // 2, axis=1).reshape(-1).view(np.uint64)
    return out


@dataclass
class _Index:
    """Fingerprints of one class in BLOCKS tables, one for each block of bits.

    Of fingerprints within the radius, some block differs in at most radius // BLOCKS bits; each table lists an entry under every value so near its
    block, so one look per block finds all.
    """

    prints: np.ndarray
    item: np.ndarray
    offset: np.ndarray
    blocks: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    def build(self, radius: int) -> _Index:
        width = 64 // BLOCKS
        flips = [sum(1 << k for k in bits) for r in range(radius // BLOCKS + 1) for bits in itertools.combinations(range(width), r)]
        for block in range(BLOCKS):
            own = ((self.prints >> np.uint64(block * width)) & np.uint64((1 << width) - 1)).astype(np.int64)
            value = (own[:, None] ^ np.array(flips)[None, :]).ravel()
            order = np.argsort(value, kind="stable")
            count = np.bincount(value, minlength=1 << width)
            self.blocks.append((block * width, count > 0, order // len(flips), np.concatenate([[0], np.cumsum(count)])))
        return self

    def search(self, windows: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """(window, entry) of all pairs within the radius; a pair may come several times."""
        at, entry = [], []
        width = 64 // BLOCKS
        parts = windows.view(np.uint16).reshape(-1, BLOCKS) if width == 16 else None
        for k, (low, used, entries, start) in enumerate(self.blocks):
            value = parts[:, k] if parts is not None else ((windows >> np.uint64(low)) & np.uint64((1 << width) - 1)).astype(np.int64)
            hit = np.flatnonzero(used[value])
            value = value[hit].astype(np.int64)
            n = start[value + 1] - start[value]
            which = np.repeat(hit, n)
            step = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
            found = entries[np.repeat(start[value], n) + step]
            near = np.bitwise_count(windows[which] ^ self.prints[found]) <= radius
            at.append(which[near]), entry.append(found[near])
        return np.concatenate(at), np.concatenate(entry)


def _shingles(hashes: np.ndarray) -> list[int]:
    if not len(hashes):
        return []
    return (shingle_hashes(hashes) if len(hashes) >= SHINGLE else sequence_hash(hashes).reshape(1)).tolist()


def weighted_similarity(a: Counter, b: Counter, weight: dict[int, float], other: float) -> float:
    """Weighted Jaccard of two shingle multisets: summed minima over summed maxima, each times the shingle's weight."""
    low = high = 0.0
    for s in a.keys() | b.keys():
        w = weight.get(s, other)
        low += w * min(a[s], b[s])
        high += w * max(a[s], b[s])
    return low / high if high else 0.0


@dataclass
class _Keys:
    """Sorted shingle hashes and the items that hold each, behind a filter of their low bits."""

    used: np.ndarray
    key: np.ndarray
    item: np.ndarray

    @classmethod
    def of(cls, pairs: list[tuple[int, int]]) -> _Keys:
        key, item = np.array([s for s, _ in pairs], np.uint64), np.array([k for _, k in pairs], np.int64)
        order = np.argsort(key, kind="stable")
        used = np.zeros(max(1 << 12, 1 << (16 * len(pairs)).bit_length()), bool)
        used[(key & np.uint64(len(used) - 1)).astype(np.int64)] = True
        return cls(used, key[order], item[order])

    def search(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position, item) of all hashes that are a key."""
        hit = np.flatnonzero(self.used[(hashes & np.uint64(len(self.used) - 1)).astype(np.int64)])
        low = np.searchsorted(self.key, hashes[hit], "left")
        n = np.searchsorted(self.key, hashes[hit], "right") - low
        step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return np.repeat(hit, n), self.item[np.repeat(low, n) + step]


@dataclass
class Benchmark:
    ids: list[int]
    hashes: list[np.ndarray]
    counts: list[Counter]
    weight: dict[int, float]
    other: float
    indexes: dict[int, _Index]
    shortest: int
    longest: int
    #: Rarest shingles of the items of SHINGLE words or more, and by length the only shingle of each shorter one.
    rare: _Keys
    brief: dict[int, _Keys]


def _rarest(counts: Counter, weight: dict[int, float], similarity: float) -> list[int]:
    """The heaviest shingles of an item, until the rest weighs less than the given share of it: texts of that similarity hold one of them."""
    total = sum(weight[s] * n for s, n in counts.items())
    left, out = total, []
    for s in sorted(counts, key=lambda s: (-weight[s], s)):
        if left < (similarity - 1e-9) * total:
            break
        out.append(s)
        left -= weight[s] * counts[s]
    return out


def _spoken(items: list[tuple[int, str]]) -> tuple[list[tuple[int, str]], list[np.ndarray]]:
    """The items that have words, and their words' hashes."""
    items = [(k, t) for k, t in items if t is not None and t.strip(" \t\n\x0b\x0c\r")]
    hashes: list[np.ndarray] = []
    for chunk in text_chunks(pa.array([t for _, t in items], pa.string())):
        found = words(chunk)
        own = word_hashes(chunk, found)
        hashes += [own[i:j] for i, j in zip(found.first[:-1], found.first[1:], strict=True)]
    return items, hashes


def shingle_spread(portions: list[list[tuple[int, str]]]) -> tuple[Counter, int]:
    """How many items hold each shingle, and the number of items, over all portions: weights don't depend on how the benchmark is dealt."""
    spread, total = Counter(), 0
    for portion in portions:
        _, hashes = _spoken(portion)
        total += len(hashes)
        for h in hashes:
            spread.update(set(_shingles(h)))
    return spread, total


def prepare(items: list[tuple[int, str]], radius: int = RADIUS, similarity: float = SIMILARITY, spread: tuple[Counter, int] | None = None) -> Benchmark:
    """Fingerprints of each item's first and last window of its class, shingle weights (rarer among all items, heavier), and each item's rarest shingles."""
    items, hashes = _spoken(items)
    counts = [Counter(_shingles(h)) for h in hashes]
    holders, total = spread or (Counter(s for c in counts for s in c), len(items))
    weight = {s: float(np.log1p(total / holders[s])) for c in counts for s in c}
    classes = _classes(max((len(h) for h in hashes), default=0))
    entries: dict[int, list[tuple[int, int, int]]] = {}
    for k, h in enumerate(hashes):
        size = max(c for c in classes if c <= len(h))
        all_prints = fingerprints(h, [size])[size]
        for offset in sorted({0, len(h) - size}):
            entries.setdefault(size, []).append((int(all_prints[offset]), k, offset))
    indexes = {size: _Index(np.array([e[0] for e in own], np.uint64), np.array([e[1] for e in own]), np.array([e[2] for e in own])).build(radius) for size, own in entries.items()}
    lengths = [len(h) for h in hashes]
    rare = _Keys.of([(s, k) for k, c in enumerate(counts) if lengths[k] >= SHINGLE for s in _rarest(c, weight, similarity)])
    brief = {n: _Keys.of([(s, k) for k, c in enumerate(counts) if lengths[k] == n for s in c]) for n in sorted({n for n in lengths if n < SHINGLE})}
    return Benchmark([k for k, _ in items], hashes, counts, weight, float(np.log1p(total)), indexes, min(lengths, default=0), max(lengths, default=0), rare, brief)


def _best_window(b: Benchmark, item: int, shingles: np.ndarray, weights: np.ndarray) -> tuple[float, int]:
    """The largest similarity of an item of SHINGLE words or more to a window as long as it, or to what a text that ends earlier has, and the first such window.

    shingles and weights are a whole text's. The occurrence of a shingle adds to the common weight of the windows that hold it but not as many occurrences before it as the item has.
    """
    counts = b.counts[item]
    span = len(b.hashes[item]) - SHINGLE + 1
    low, last = np.zeros(len(shingles) + 1), {}
    for p, s in enumerate(shingles.tolist()):
        n = counts.get(s, 0)
        if n:
            before = last.setdefault(s, [])
            begin = max(p - span + 1, 0, before[-n] + 1 if len(before) >= n else 0)
            before.append(p)
            low[begin] += weights[p]
            low[p + 1] -= weights[p]
    low = np.cumsum(low)[:-1]
    total = np.concatenate([[0.0], np.cumsum(weights)])
    at = np.arange(len(shingles))
    window = total[np.minimum(at + span, len(shingles))] - total[at]
    own = sum(b.weight[s] * n for s, n in counts.items())
    score = low / (window + own - low)
    best = int(np.argmax(score >= score.max() - _SLACK))
    return weighted_similarity(Counter(shingles[best : best + span].tolist()), counts, b.weight, b.other), best


def _matches(b: Benchmark, hashes: np.ndarray, first: np.ndarray, radius: int, similarity: float) -> dict[int, dict[int, tuple[float, int]]]:
    """document -> item -> (similarity, first word) of the best window; first has the documents' word positions."""
    out: dict[int, dict[int, tuple[float, int]]] = {}
    if not len(hashes) or not b.ids:
        return out
    pairs: set[tuple[int, int]] = set()
    ends = np.repeat(first[1:], np.diff(first))
    sizes = sorted(b.indexes)
    prints = fingerprints(hashes, sizes)
    for size in sizes:
        if not len(prints[size]):
            continue
        inside = np.flatnonzero(ends[: len(prints[size])] - np.arange(len(prints[size])) >= size)
        index = b.indexes[size]
        at, entry = index.search(prints[size][inside], radius)
        pairs.update(zip((np.searchsorted(first, inside[at], "right") - 1).tolist(), index.item[entry].tolist(), strict=True))
    all_shingles = shingle_hashes(hashes)
    inside = np.flatnonzero(ends[: len(all_shingles)] - np.arange(len(all_shingles)) >= SHINGLE)
    at, item = b.rare.search(all_shingles[inside])
    pairs.update(zip((np.searchsorted(first, inside[at], "right") - 1).tolist(), item.tolist(), strict=True))

    weighed: dict[int, np.ndarray] = {}
    for doc, item in sorted(pairs):
        lo, hi = int(first[doc]), int(first[doc + 1])
        if len(b.hashes[item]) < SHINGLE or hi - lo < SHINGLE:
            continue
        shingles = all_shingles[lo : hi - SHINGLE + 1]
        if b.counts[item].keys().isdisjoint(shingles.tolist()):
            continue
        if doc not in weighed:
            weighed = {doc: np.array([b.weight.get(s, b.other) for s in shingles.tolist()])}
        s, start = _best_window(b, item, shingles, weighed[doc])
        if s >= similarity - _SLACK:
            out.setdefault(doc, {})[item] = (s, start)
    # Items of fewer than SHINGLE words are one shingle: the same words or none.
    for size, keys in b.brief.items():
        inside = np.flatnonzero(ends - np.arange(len(ends)) >= size)
        at, item = keys.search(sequence_hashes(hashes, size)[inside])
        for i, k in zip(inside[at].tolist(), item.tolist(), strict=True):
            doc = int(np.searchsorted(first, i, "right")) - 1
            out.setdefault(doc, {}).setdefault(k, (1.0, i - int(first[doc])))
    return out


def scan(docs: DataFrame, benchmark: Benchmark, radius: int = RADIUS, similarity: float = SIMILARITY) -> DataFrame:
    """row (all columns of docs) and matches, an array of (item_id, word_start, similarity), for each row of docs."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(benchmark)
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"))
    schema = rows.select("row", F.lit(None).cast("array<struct<item_id:bigint,word_start:bigint,similarity:double>>").alias("matches")).schema
    kind = pa.list_(pa.struct([("item_id", pa.int64()), ("word_start", pa.int64()), ("similarity", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b = shared.value
        for batch in batches:
            found: list[list[dict]] = [[] for _ in range(batch.num_rows)]
            for chunk in text_chunks(row_text(batch), _CHUNK):
                seen = words(chunk)
                for doc, items in _matches(b, word_hashes(chunk, seen), seen.first, radius, similarity).items():
                    found[chunk.first + doc] = [{"item_id": b.ids[k], "word_start": at, "similarity": s} for k, (s, at) in sorted(items.items(), key=lambda x: b.ids[x[0]])]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(found, kind)], names=["row", "matches"])

    return rows.mapInArrow(frugal(run), schema)


def _passes(items: DataFrame) -> list[list[tuple[int, str]]]:
    """The items in portions of PASS_BYTES, each small enough to broadcast."""
    portions: list[list[tuple[int, str]]] = [[]]
    size = 0
    for r in items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).filter("text is not null").orderBy("item_id", "text").toLocalIterator():
        size += len(r["text"])
        if size > PASS_BYTES and portions[-1]:
            portions.append([])
            size = len(r["text"])
        portions[-1].append((r["item_id"], r["text"]))
    return portions


def contaminated(docs: DataFrame, items: DataFrame, radius: int = RADIUS, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, item_id, word_start, similarity of each document and item of which it has a passage; clean documents give no row.

    Every window of as many words as an item's class gets a SimHash of its words (A-Z folded); documents with a fingerprint within radius of an item's are
    candidates, and so are those with one of the item's rarest 5-word shingles, as every document with a window of the similarity has. All windows as long as the item (shorter where the
    document ends) are then compared with it on multisets of shingles, weighted by rarity among the items. The best window counts, so nothing that reaches the similarity is missed.
    Null or blank texts match nothing, on either side. Items of fewer than 5 words are one shingle. Of equally similar windows the first counts. Rows that repeat a
    doc_id, a null one included, each give their own rows; items that repeat an item_id are compared one by one under that id. Other columns, whatever their names, are
    not read. An empty table on either side gives no rows.
    """
    portions = _passes(items)
    spread = shingle_spread(portions)
    parts = [scan(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), prepare(p, radius, similarity, spread), radius, similarity) for p in portions]
    found = [p.filter(F.size("matches") > 0).select("row.doc_id", F.explode("matches").alias("m")).select("doc_id", "m.item_id", "m.word_start", "m.similarity") for p in parts]
    out = found[0]
    for more in found[1:]:
        out = out.union(more)
    return out


def clean_documents(docs: DataFrame, items: DataFrame, radius: int = RADIUS, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of docs without a passage of any item, columns unchanged; null and blank texts, null and repeated ids stay as they are."""
    portions = _passes(items)
    spread = shingle_spread(portions)
    for portion in portions:
        docs = scan(docs, prepare(portion, radius, similarity, spread), radius, similarity).filter(F.size("matches") == 0).select("row.*")
    return docs
