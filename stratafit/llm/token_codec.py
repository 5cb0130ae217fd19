"""Adaptive context-mixing coder for token ids, many lanes at a time.

Two predictors, of order 1 and 2, name the id that last followed the context; how often each was right at its present confidence, counted in both and added up,
mixes them with order 0 into one distribution over {order-2 id, order-1 id, spans of other ids}. Order 0 knows ids by rank among the segment's ids: each of the most
frequent ids, and each quarter of an octave of the others, has a count, taken from the segment (stored once); where in its quarter a rank lies is coded evenly.
A segment's ids are lanes of BLOCK ids that advance together: one step codes one id of every lane. All lanes share one model, which learns from a step's ids when
they are known, the ones of the last lane last, and one asymmetric-numeral-system stream of 16-bit words. Shares of the outcomes are counted anew at the steps of _stretches().
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np

#: Ids in a lane.
BLOCK = 512
MAGIC = b"TOKSEG03"
_U = np.uint32
#: Shares of a distribution add up to 2**_BITS; contexts have so many bits; confidences are 0 to _SURE - 1.
_BITS, _CONTEXT, _SURE = 12, 17, 5
_LEAST, _WORD = _U(1 << 16), _U(16)
#: Sum of the order-0 counts of a segment, beside the 1 that each span's count has at least.
_PRIOR = 2048


class _Spans:
    """Spans of ranks: ranks 0 to 15 one by one, then quarters of octaves, up to 65535 or, with wide, to all 32-bit ranks."""

    def __init__(self, wide: bool) -> None:
        self.width = np.array([1] * 16 + [1 << (octave - 2) for octave in range(4, 32 if wide else 16) for _ in range(4)], np.int64)
        self.base = self.width.cumsum() - self.width
        self.n = len(self.width)
        self.low = self._search(np.arange(1 << 16))

    def _search(self, ranks: np.ndarray) -> np.ndarray:
        return (np.searchsorted(self.base, ranks, "right") - 1).astype(np.uint8)

    def of(self, ranks: np.ndarray) -> np.ndarray:
        return self.low[ranks] if int(ranks.max(initial=0)) < 1 << 16 else self._search(ranks)

    def prior(self, ranks: np.ndarray) -> np.ndarray:
        """Order-0 counts that every block of these ranks starts from."""
        return (1 + np.bincount(self.of(ranks), minlength=self.n) * _PRIOR // max(1, len(ranks))).astype(np.uint16)


def _stretches(steps: int) -> Iterator[tuple[int, int]]:
    """First and next step of the stretches that have the same shares: they double up to 32 steps."""
    lo = 0
    while lo < steps:
        hi = min(steps, lo + min(max(lo, 1), 32))
        yield lo, hi
        lo = hi


class _Model:
    def __init__(self, lanes: int, prior: np.ndarray) -> None:
        self.guess = [np.full(1 << _CONTEXT, -1, np.int32) for _ in (0, 1)]
        self.trust = [np.zeros(1 << _CONTEXT, np.uint8) for _ in (0, 1)]
        self.right = np.tile(np.array([1, 1, 2]), (2, _SURE, 1))
        self.prior, self.kinds = np.array(prior, np.int64), len(prior) + 2
        self.last, self.before = np.zeros(lanes, _U), np.zeros(lanes, _U)

    def share(self) -> None:
        """From now on: starts and sizes (one number each: start << 16 | size) of the outcomes by both confidences, and the outcome at each of the 2**_BITS places."""
        counts = (self.right[0][:, None] + self.right[1][None, :]).reshape(-1, 3)
        room = (1 << _BITS) - self.kinds
        sizes = np.ones((len(counts), self.kinds), np.int64)
        sizes[:, :2] += counts[:, :2] * room // counts.sum(axis=1, keepdims=True)
        left = (1 << _BITS) - sizes.sum(axis=1)
        sizes[:, 2:] += self.prior * left[:, None] // self.prior.sum()
        sizes[np.arange(len(sizes)), 2 + int(self.prior.argmax())] += (1 << _BITS) - sizes.sum(axis=1)
        self.parts = ((sizes.cumsum(axis=1) - sizes) << 16 | sizes).astype(_U).reshape(-1)
        self.places = np.repeat(np.tile(np.arange(self.kinds, dtype=np.uint8), len(sizes)), sizes.reshape(-1))

    def predict(self) -> None:
        """ids and confidences of both predictors, and the row of their distribution."""
        self.slot = (((self.last * _U(2654435761) + self.before * _U(40503 * 65537)) >> _U(32 - _CONTEXT)).astype(np.int64), (self.last & _U((1 << _CONTEXT) - 1)).astype(np.int64))
        self.ids = [self.guess[k].take(self.slot[k]) for k in (0, 1)]
        self.sure = [self.trust[k].take(self.slot[k]) for k in (0, 1)]
        self.row = self.sure[0] * np.uint8(_SURE) + self.sure[1]

    def learn(self, ids: np.ndarray) -> None:
        for k in (0, 1):
            self.trust[k][self.slot[k]] = np.minimum(self.sure[k], np.uint8(_SURE - 2)) * (self.ids[k] == ids) + np.uint8(1)
            self.guess[k][self.slot[k]] = ids
        self.before, self.last = self.last, ids.view(_U)

    def count(self, rows: np.ndarray, outcomes: np.ndarray) -> None:
        """Outcomes that came up in rows; order 0 counts the ids that neither predictor named."""
        self.prior += np.bincount(outcomes.reshape(-1), minlength=self.kinds)[2:]
        seen = np.bincount(rows.reshape(-1).astype(np.int64) * 3 + np.minimum(outcomes, 2).reshape(-1), minlength=3 * _SURE * _SURE).reshape(_SURE, _SURE, 3)
        self.right[0] += seen.sum(axis=1)
        self.right[1] += seen.sum(axis=0)


class _Writer:
    """Coder of one state a lane; what is put last is got first."""

    def __init__(self, lanes: int) -> None:
        self.state, self.words = np.full(lanes, _LEAST), []

    def _shed(self, over: np.ndarray) -> None:
        go = np.flatnonzero(over)
        some = self.state.take(go)
        self.words.append(some.astype(np.uint16))
        self.state[go] = some >> _WORD

    def put_bits(self, value: np.ndarray, bits: np.ndarray) -> None:
        """Values of 0 to 16 bits."""
        self._shed(self.state >> (_U(32) - bits))
        self.state = self.state << bits | value

    def put(self, part: np.ndarray) -> None:
        size = part & _U(0xFFFF)
        self._shed(self.state >> _U(32 - _BITS) >= size)
        times = self.state // size
        self.state = (times << _U(_BITS)) + (self.state - times * size) + (part >> _WORD)

    def finish(self) -> list[bytes]:
        return [self.state.astype("<u4").tobytes(), np.concatenate([np.zeros(0, np.uint16), *self.words[::-1]]).astype("<u2").tobytes()]


class _Reader:
    def __init__(self, state: bytes, words: bytes, lanes: int) -> None:
        self.state = np.frombuffer(state, "<u4").astype(_U)
        self.words, self.at = np.concatenate([np.frombuffer(words, "<u2"), np.zeros(4 * lanes, np.uint16)]).astype(_U), 0

    def _fill(self) -> None:
        go = np.flatnonzero(self.state < _LEAST)
        self.state[go] = self.state.take(go) << _WORD | self.words[self.at : self.at + len(go)]
        self.at += len(go)

    def get_bits(self, bits: np.ndarray) -> np.ndarray:
        value = self.state & ((_U(1) << bits) - _U(1))
        self.state = self.state >> bits
        self._fill()
        return value

    def get(self, model: _Model) -> np.ndarray:
        place = self.state & _U((1 << _BITS) - 1)
        row = model.row.astype(np.int64)
        outcome = model.places.take((row << _BITS) | place)
        part = model.parts.take(row * model.kinds + outcome)
        self.state = (part & _U(0xFFFF)) * (self.state >> _U(_BITS)) + place - (part >> _WORD)
        self._fill()
        return outcome


def _outcomes(spans: _Spans) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By outcome: the first rank of its span, and how many bits, 16 and then those above, tell where in it a rank lies."""
    bits = np.concatenate([[0, 0], np.log2(spans.width).round()]).astype(_U)
    return np.concatenate([[0, 0], spans.base]).astype(_U), np.minimum(bits, _WORD), bits - np.minimum(bits, _WORD)


def encode_blocks(ranks: np.ndarray, wide: bool = False, prior: np.ndarray | None = None) -> list[bytes]:
    """The lanes' last states and the words of ranks: 0 to 65535, or with wide any 32-bit ones. Order 0 starts from prior, else from equal counts.

    A short last lane is filled with zeros, which its reader drops.
    """
    steps, lanes = min(BLOCK, len(ranks)), max(1, -(-len(ranks) // BLOCK))
    padded = np.zeros(lanes * steps, _U)
    padded[: len(ranks)] = ranks
    columns = np.ascontiguousarray(padded.reshape(lanes, steps).T)
    spans = _Spans(wide)
    base, bits, above = _outcomes(spans)
    literal = spans.of(columns) + np.uint8(2)
    model = _Model(lanes, np.ones(spans.n) if prior is None else prior)
    outcomes, rows, parts = np.empty(columns.shape, np.uint8), np.empty(columns.shape, np.uint8), np.empty(columns.shape, _U)
    for lo, hi in _stretches(steps):
        model.share()
        for t in range(lo, hi):
            ids = columns[t].view(np.int32)
            model.predict()
            outcomes[t] = np.where(model.ids[0] == ids, 0, np.where(model.ids[1] == ids, 1, literal[t]))
            rows[t] = model.row
            model.learn(ids)
        model.count(rows[lo:hi], outcomes[lo:hi])
        parts[lo:hi] = model.parts.take(rows[lo:hi].astype(np.int64) * model.kinds + outcomes[lo:hi])
    coder = _Writer(lanes)
    for t in range(steps - 1, -1, -1):
        low = np.where(outcomes[t] < 2, _U(0), columns[t] - base.take(outcomes[t]))
        if wide:
            coder.put_bits(low >> _WORD, above.take(outcomes[t]))
            low = low & _U(0xFFFF)
        coder.put_bits(low, bits.take(outcomes[t]))
        coder.put(parts[t])
    return coder.finish()


def decode_blocks(payloads: list[bytes], count: int, wide: bool = False, prior: np.ndarray | None = None) -> np.ndarray:
    """The count values that encode_blocks was given."""
    steps, lanes = min(BLOCK, count), max(1, -(-count // BLOCK))
    columns = np.empty((steps, lanes), _U)
    spans = _Spans(wide)
    base, bits, above = _outcomes(spans)
    model, coder = _Model(lanes, np.ones(spans.n) if prior is None else prior), _Reader(*payloads, lanes)
    outcomes, rows = np.empty(columns.shape, np.uint8), np.empty(columns.shape, np.uint8)
    for lo, hi in _stretches(steps):
        model.share()
        for t in range(lo, hi):
            model.predict()
            outcome = coder.get(model)
            ids = base.take(outcome) + coder.get_bits(bits.take(outcome))
            if wide:
                ids = ids + (coder.get_bits(above.take(outcome)) << _WORD)
            for k in (1, 0):
                ids = np.where(outcome == k, model.ids[k].view(_U), ids)
            outcomes[t], rows[t], columns[t] = outcome, model.row, ids
            model.learn(ids.view(np.int32))
        model.count(rows[lo:hi], outcomes[lo:hi])
    return columns.T.reshape(-1)[:count]


def pack_segment(doc_ids: list[int | None], lengths: np.ndarray, ids: np.ndarray) -> bytes:
    """A self-contained segment of whole documents.

    MAGIC, then little-endian: documents n, ids, distinct ids, lanes, bytes of words, crc32 of the ids (6 x u32); n signed 64-bit doc ids; n bytes that are 1 for a null
    doc id; n u32 lengths; the distinct ids, most frequent first (u32 each); the order-0 counts (u16 each); the lanes' states (u32 each); the words; last the crc32
    of all before.
    """
    if int(ids.max(initial=0)) < 1 << 20:
        every = np.bincount(ids)
        used, at = np.flatnonzero(every), ids
        counts = every[used]
    else:
        used, at, counts = np.unique(ids, return_inverse=True, return_counts=True)
        every = used
    order = np.argsort(-counts, kind="stable")
    rank = np.empty(len(every), np.uint32)
    rank[used[order] if every is not used else order] = np.arange(len(used), dtype=np.uint32)
    wide, ranks = len(used) > 65535, rank[at]
    prior = _Spans(wide).prior(ranks)
    states, words = encode_blocks(ranks, wide, prior) if len(ids) else (b"", b"")
    sizes = struct.pack("<6I", len(doc_ids), len(ids), len(used), len(states) // 4, len(words), zlib.crc32(ids.astype("<u4").tobytes()))
    body = b"".join(
        [MAGIC, sizes, np.array([d or 0 for d in doc_ids], "<i8").tobytes(), bytes(d is None for d in doc_ids), lengths.astype("<u4").tobytes(), used[order].astype("<u4").tobytes(), prior.astype("<u2").tobytes(), states, words]
    )
    return body + struct.pack("<I", zlib.crc32(body))


def unpack_segment(data: bytes) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    """doc ids, lengths and ids of a segment; ValueError where a checksum or the form is wrong."""
    if data[:8] != MAGIC or zlib.crc32(data[:-4]) != struct.unpack("<I", data[-4:])[0]:
        raise ValueError("not a token segment, or damaged")
    n, total, distinct, lanes, size, check = struct.unpack_from("<6I", data, 8)
    at = 32
    doc_ids = np.frombuffer(data, "<i8", n, at)
    nulls = np.frombuffer(data, np.uint8, n, at := at + 8 * n)
    lengths = np.frombuffer(data, "<u4", n, at := at + n)
    used = np.frombuffer(data, "<u4", distinct, at := at + 4 * n)
    wide = distinct > 65535
    prior = np.frombuffer(data, "<u2", _Spans(wide).n, at := at + 4 * distinct)
    at += prior.nbytes
    states, words = data[at : at + 4 * lanes], data[at + 4 * lanes : at + 4 * lanes + size]
    ids = used[decode_blocks([states, words], total, wide, prior)] if total else np.zeros(0, "<u4")
    if zlib.crc32(ids.astype("<u4").tobytes()) != check:
        raise ValueError("the ids do not match their checksum")
    return [None if z else d for d, z in zip(doc_ids.tolist(), nulls.tolist(), strict=True)], lengths.astype(np.int64), ids
