"""Token ids of whole texts by the tokenizers library, which encodes each distinct piece of text once."""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Pieces that are remembered at most between batches, and their bytes.
KNOWN_PIECES = 400_000
KNOWN_BYTES = 16 << 20
#: Pieces that the library is given at once, joined where a pre-token surely ends.
_GIVEN = 2_000
_SPACE, _LETTER, _DIGIT, _SIGN, _HIGH = range(5)


def _classes() -> np.ndarray:
    kinds = np.full(256, _HIGH, np.uint8)
    for c in map(chr, range(128)):
        kinds[ord(c)] = _LETTER if c.isalpha() else _DIGIT if c.isdigit() else _SPACE if c <= " " or c == "\x7f" else _SIGN
    return kinds


def _cuts() -> np.ndarray:
    """By the classes of two neighbouring bytes (8 * first + second): a pre-token always ends between them."""
    cuts = np.zeros(64, bool)
    for first in (_LETTER, _DIGIT):
        for second in (_SPACE, _LETTER, _DIGIT, _SIGN):
            cuts[8 * first + second] = first != second
    cuts[8 * _SIGN + _SPACE] = True
    return cuts


_KINDS, _CUTS = _classes(), _cuts()


class PieceEncoder:
    """The library's ids of whole texts, without special tokens.

    A byte-level tokenizer that splits by its usual expression never joins what stands on both sides of the end of an ASCII word or number, or of any sign or
    letter before an ASCII space: its ids are those of the pieces between such places, one after the other. So each distinct piece is encoded once, and remembered
    for later texts. Texts that hold an added token, and all texts of tokenizers of another kind, are one piece each.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer, models, pre_tokenizers

        self.encoder = Tokenizer.from_file(path)
        split, model = self.encoder.pre_tokenizer, self.encoder.model
        usual = isinstance(split, pre_tokenizers.ByteLevel) and split.use_regex and not split.add_prefix_space and isinstance(model, models.BPE) and not model.dropout
        self.splits = bool(usual and self.encoder.normalizer is None and self.encoder.truncation is None and self.encoder.padding is None)
        self.added = [t.content for t in self.encoder.get_added_tokens_decoder().values()]
        # a byte-level token has one character a byte
        vocabulary = self.encoder.get_vocab()
        self.bytes = np.zeros(max(vocabulary.values(), default=0) + 1, np.int64)
        self.bytes[list(vocabulary.values())] = list(map(len, vocabulary))
        self._forget()

    def _forget(self) -> None:
        self.known, self.ids, self.starts, self.again = pa.array([], pa.binary()), np.zeros(0, np.uint32), np.zeros(1, np.int64), np.zeros(0, bool)

    def _thin(self) -> None:
        """Keep the pieces that came again in a later batch, if they fill less than half of the bounds."""
        counts, known = np.diff(self.starts), self.known.filter(pa.array(self.again))
        if 2 * len(known) > KNOWN_PIECES or 2 * known.nbytes > KNOWN_BYTES:
            return self._forget()
        self.known, self.ids = known, self.ids[np.repeat(self.again, counts)]
        self.starts = np.concatenate([[0], counts[self.again].cumsum()])
        self.again = np.zeros(len(known), bool)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """How many ids each text has, and the ids of all texts; a null is empty."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        offsets = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1]
        first, last = int(offsets[0]), int(offsets[-1])
        if first == last:
            return np.zeros(len(texts), np.int64), np.zeros(0, np.uint32)
        data = np.frombuffer(texts.buffers()[2], np.uint8)[first:last]
        offsets = offsets - np.int32(first)
        begins = self._begins(texts, offsets, data)
        ends = np.append(begins, len(data)).astype(np.int32)
        pieces = pa.Array.from_buffers(pa.binary(), len(begins), [None, pa.py_buffer(ends), pa.py_buffer(data)]).dictionary_encode()
        number = self._numbers(pieces.dictionary)[pieces.indices.to_numpy()]
        counts = np.diff(self.starts)[number]
        to = np.concatenate([[0], counts.cumsum()])
        ids = self.ids[np.repeat(self.starts[number] - to[:-1], counts) + np.arange(to[-1])]
        return np.diff(to[np.searchsorted(begins, offsets)]), ids

    def _begins(self, texts: pa.Array, offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
        """Where pieces begin."""
        at = np.zeros(len(data), bool)
        if self.splits:
            kinds = _KINDS[data]
            np.take(_CUTS, (kinds[:-1] << 3) | kinds[1:], out=at[1:])
            # the second byte of a character from U+00C0 to U+07FF, none of which is a space, before an ASCII space
            high = np.flatnonzero((kinds[1:-1] == _HIGH) & (data[2:] == 32))
            at[high[(data[high] >= 0xC3) & (data[high] <= 0xDF)] + 2] = True
            for token in self.added:
                for i in np.flatnonzero(pc.match_substring(texts, token).to_numpy(zero_copy_only=False)):
                    at[offsets[i] : offsets[i + 1]] = False
        at[offsets[:-1][offsets[:-1] < len(data)]] = True
        return np.flatnonzero(at)

    def _numbers(self, pieces: pa.Array) -> np.ndarray:
        """The numbers of distinct pieces among the known; the library encodes the others."""
        if len(self.known) > KNOWN_PIECES or self.known.nbytes > KNOWN_BYTES:
            self._thin()
        found = pc.index_in(pieces, self.known)
        new = pieces.filter(found.is_null())
        counts, made = [], [self.ids]
        for i in range(0, len(new), _GIVEN):
            for part in self._encoded(new.slice(i, _GIVEN)):
                counts.append(part[0]), made.append(part[1])
        numbers = found.fill_null(0).to_numpy().copy()
        numbers[found.is_null().to_numpy(zero_copy_only=False)] = len(self.known) + np.arange(len(new))
        self.again[numbers[numbers < len(self.again)]] = True
        if len(new):
            self.again = np.append(self.again, np.zeros(len(new), bool))
            self.known, self.ids = pa.concat_arrays([self.known, new]), np.concatenate(made)
            self.starts = np.concatenate([self.starts, self.starts[-1] + np.concatenate(counts).cumsum()])
        return numbers

    def _encoded(self, pieces: pa.Array) -> list[tuple[np.ndarray, np.ndarray]]:
        """How many ids some distinct pieces have, and their ids, by runs of pieces.

        The library gets each run as one text: most of its time for a short text goes by the text. The bytes of the ids tell where a piece ends. A run in which the
        joints make an added token, or whose ids do not end where pieces do, is given piece by piece.
        """
        ends = np.frombuffer(pieces.buffers()[1], np.int32)[pieces.offset : pieces.offset + len(pieces) + 1]
        data = np.frombuffer(pieces.buffers()[2], np.uint8)
        heads = np.ones(len(pieces), bool)
        if self.splits:
            heads[1:] = ~_CUTS[(_KINDS[data[ends[1:-1] - 1]] << 3) | _KINDS[data[ends[1:-1]]]]
        first = np.append(np.flatnonzero(heads), len(pieces))
        runs = [data[lo:hi].tobytes().decode() for lo, hi in zip(ends[first[:-1]].tolist(), ends[first[1:]].tolist(), strict=True)]
        size = np.diff(first)
        whole = np.array([n == 1 or not any(t in run for t in self.added) for run, n in zip(runs, size.tolist(), strict=True)], bool)
        given = iter(self._library([run for run, one in zip(runs, whole.tolist(), strict=True) if one]))
        none = np.zeros(0, np.uint32)
        found = [next(given) if one else none for one in whole.tolist()]
        ids = np.concatenate([none, *found])
        at, want = self.bytes[ids].cumsum(), (ends[1:] - ends[0]).astype(np.int64)
        last = np.searchsorted(at, want)
        if whole.all() and len(ids) and last[-1] == len(ids) - 1 and np.array_equal(at[last], want):
            return [(np.diff(last, prepend=-1), ids)]
        parts = []
        for lo, n, one, ids in zip(first[:-1].tolist(), size.tolist(), whole.tolist(), found, strict=True):
            at, want = self.bytes[ids].cumsum(), (ends[lo + 1 : lo + n + 1] - ends[lo]).astype(np.int64)
            last = np.searchsorted(at, want)
            if n == 1:
                parts.append((np.array([len(ids)]), ids))
            elif one and last[-1] == len(ids) - 1 and np.array_equal(at[last], want):
                parts.append((np.diff(last, prepend=-1), ids))
            else:
                parts += [(np.array([len(ids)]), ids) for ids in self._library(pieces.slice(lo, n).cast(pa.string()).to_pylist())]
        return parts

    def _library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.encoder.encode_batch_fast(texts, add_special_tokens=False)]


#: The encoders of this Python worker, by path and time of change: later tasks know its pieces.
_HELD: dict[tuple[str, float], PieceEncoder] = {}


def worker_encoder(path: str) -> PieceEncoder:
    """The worker's encoder of the tokenizer at path; it holds the last one."""
    key = (path, os.stat(path).st_mtime)
    if key not in _HELD:
        _HELD.clear()
        _HELD[key] = PieceEncoder(path)
    return _HELD[key]
