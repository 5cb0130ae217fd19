"""Vectorised text kernels: words and shingles of whole Arrow string columns as numpy arrays.

A word is a run of bytes other than space and \\x09-\\x0D, A-Z folded to a-z. A word's hash is a polynomial in
randomly drawn byte values modulo 2**64, scrambled; a shingle's hash combines its words' hashes in order.
Texts are cut into chunks of whole documents, so memory is bounded by CHUNK or by the longest text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK = 1 << 19
SHINGLE = 5
_rng = np.random.default_rng(20240607)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64)
_PLACE = _rng.integers(1, 2**63, SHINGLE, dtype=np.uint64) | np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_UNBASE = pow(_BASE, -1, 2**64)
GAP = np.zeros(256, bool)
GAP[[9, 10, 11, 12, 13, 32]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
_FOLDED = _BYTE[FOLD]


def scramble(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words in which every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_powers: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n + 1:
        size = max(n + 1, CHUNK + 1)
        for k, base in enumerate((_BASE, _UNBASE)):
            grown = np.full(size, np.uint64(base))
            grown[0] = 1
            np.multiply.accumulate(grown, out=grown)
            _powers[k : k + 1] = [grown]
    return _powers[0], _powers[1]


@dataclass
class Chunk:
    """Documents first .. first + n - 1 of a batch: bytes, and where each document begins."""

    first: int
    n: int
    data: np.ndarray
    starts: np.ndarray  # n + 1 byte positions


def text_chunks(column: pa.Array | pa.ChunkedArray, limit: int = CHUNK) -> Iterator[Chunk]:
    """Whole documents, about limit bytes at a time; a null counts as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if len(column) == 0:
        return
    column = column.cast(pa.large_string()).fill_null("")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(at, at[i] + limit, "right")) - 1)
        j = min(j, len(column))
        yield Chunk(i, j - i, raw[at[i] : at[j]], at[i : j + 1] - at[i])
        i = j


def row_text(batch: pa.RecordBatch) -> pa.Array:
    """The column text inside a batch's column row, so that a text travels once."""
    return pc.struct_field(batch.column("row"), "text")


@dataclass
class Words:
    begin: np.ndarray  # byte positions
    end: np.ndarray
    first: np.ndarray  # n + 1: number of words before each document


def words(chunk: Chunk, gap: np.ndarray = GAP) -> Words:
    """The words of each document of the chunk."""
    n = len(chunk.data)
    inside = np.ones(n + 2, bool)
    inside[0] = inside[-1] = False
    np.logical_not(gap[chunk.data], out=inside[1:-1])
    edge = inside[1:-1] & ~inside[:-2]
    stop = inside[1:-1] & ~inside[2:]
    cut = chunk.starts[1:-1]
    cut = cut[(cut > 0) & (cut < n)]
    edge[cut] |= inside[1:-1][cut]
    stop[cut - 1] |= inside[1:-1][cut - 1]
    begin = np.flatnonzero(edge)
    return Words(begin, np.flatnonzero(stop) + 1, np.searchsorted(begin, chunk.starts))


def word_hashes(chunk: Chunk, found: Words) -> np.ndarray:
    """64-bit hash of every word, A-Z folded."""
    if not len(found.begin):
        return np.zeros(0, np.uint64)
    up, down = _power_tables(len(chunk.data))
    total = np.zeros(len(chunk.data) + 1, np.uint64)
    np.cumsum(_FOLDED[chunk.data] * up[: len(chunk.data)], out=total[1:])
    return scramble((total[found.end] - total[found.begin]) * down[found.begin])


def sequence_hash(hashes: np.ndarray) -> np.uint64:
    """Hash of a sequence of fewer than SHINGLE words."""
    with np.errstate(over="ignore"):
        return scramble((hashes * _PLACE[: len(hashes)]).sum(keepdims=True, dtype=np.uint64) + np.uint64(len(hashes)))[0]


def sequence_hashes(hashes: np.ndarray, size: int) -> np.ndarray:
    """sequence_hash of the size words, fewer than SHINGLE, from each word on, over a whole chunk; the last ones are short and for the caller to leave out."""
    total = np.full(len(hashes), np.uint64(size))
    for k in range(size):
        total[: len(hashes) - k] += hashes[k:] * _PLACE[k]
    return scramble(total)


def shingle_hashes(hashes: np.ndarray) -> np.ndarray:
    """Hash of the SHINGLE words from each word on, over a whole chunk; those that pass a document's end are for the caller to leave out."""
    n = len(hashes) - SHINGLE + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = hashes[:n] * _PLACE[0]
    for k in range(1, SHINGLE):
        total += hashes[k : k + n] * _PLACE[k]
    return scramble(total)


def document_shingles(chunk: Chunk) -> Iterator[tuple[int, np.ndarray]]:
    """(row in the batch, hashes of all its 5-word shingles, repeats included); one hash for 1 to 4 words, none without words."""
    found = words(chunk)
    hashes = word_hashes(chunk, found)
    all_shingles = shingle_hashes(hashes)
    first = found.first.tolist()
    for k in range(chunk.n):
        i, j = first[k], first[k + 1]
        if j - i >= SHINGLE:
            yield chunk.first + k, all_shingles[i : j - SHINGLE + 1]
        elif j > i:
            yield chunk.first + k, sequence_hash(hashes[i:j]).reshape(1)
        else:
            yield chunk.first + k, hashes[:0]
