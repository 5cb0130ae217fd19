import random

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from stratafit.llm import token_pieces
from stratafit.llm.token_codec import pack_segment, unpack_segment
from stratafit.llm.token_output import read_digests, read_tokens, token_digests, tokens_round_trip, write_tokens


@pytest.fixture(scope="module")
def tokenizer():
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def test_reading_and_digesting_take_one_python_worker_a_task(spark, sf, tokenizer, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plan = tokens_round_trip(docs, tokenizer)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1
    write_tokens(docs, str(tmp_path / "t"), tokenizer, segment_ids=5_000)
    tokens = read_tokens(spark, str(tmp_path / "t"))
    assert all(r["n_tokens"] == len(r["ids"]) for r in tokens.limit(50).collect())
    assert sorted(read_digests(spark, str(tmp_path / "t")).collect()) == sorted(token_digests(tokens).collect())


class _Counting:
    """A tokenizer that notes what it is given."""

    def __init__(self, encoder):
        self.encoder, self.given = encoder, []

    def encode_batch_fast(self, texts, **how):
        self.given += texts
        return self.encoder.encode_batch_fast(texts, **how)


def test_each_distinct_piece_is_encoded_once_with_the_ids_of_whole_texts(sf, tokenizer):
    encoder = token_pieces.PieceEncoder(tokenizer)
    library = encoder.encoder
    encoder.encoder = counting = _Counting(library)
    rng = random.Random(4)
    parts = ["a", "Zeit", "'", "'s", "'ll", " ", "  ", "\n", "\t", "\r\n", " ", "\u0085", " ", "　", "é", "ß", "ж", "中", "一", "½", "Ⅷ", "٣", "1", "23", ".", ",", "_", "<|endoftext|>", "<|", "|>", "\x00", "\x1c", "\x7f", "é", "\U0001f600", "ſ", "K", "​", "߿", "¿", "ª", "µ"]
    odd = ["".join(rng.choice(parts) for _ in range(rng.randrange(30))) for _ in range(5000)]
    texts = [*odd, "", None, *pq.read_table(f"{sf}/documents.parquet", columns=["text"])["text"].to_pylist()]
    for some in (texts, texts[::-1]):
        counts, ids = encoder.encode(pa.array(some, pa.string()))
        want = [e.ids for e in library.encode_batch_fast([t or "" for t in some], add_special_tokens=False)]
        assert counts.tolist() == [len(w) for w in want] and ids.tolist() == [i for w in want for i in w]
    assert len(counting.given) == len(set(counting.given)) and sum(map(len, counting.given)) < 0.6 * sum(len(t or "") for t in texts)
    assert encoder.encode(pa.array(["x y", "z"]).slice(1))[0].tolist() == [1] and encoder.encode(pa.array([], pa.string()))[0].tolist() == []


def test_pieces_are_forgotten_at_the_bound_and_other_tokenizers_get_whole_texts(tokenizer, monkeypatch, tmp_path):
    monkeypatch.setattr(token_pieces, "KNOWN_PIECES", 3)
    encoder = token_pieces.PieceEncoder(tokenizer)
    for text in ("one two three four five", "six seven", "one"):
        assert encoder.encode(pa.array([text]))[1].tolist() == encoder.encoder.encode(text, add_special_tokens=False).ids
    assert len(encoder.known) <= 3
    from tokenizers import Tokenizer, normalizers

    other = Tokenizer.from_file(tokenizer)
    other.normalizer = normalizers.Replace("a b", "c")
    other.save(str(tmp_path / "other.json"))
    whole = token_pieces.PieceEncoder(str(tmp_path / "other.json"))
    assert not whole.splits and whole.encode(pa.array(["a b c"]))[1].tolist() == other.encode("a b c", add_special_tokens=False).ids


def test_large_ids_round_trip():
    ids = np.array([0, 2**32 - 1, 7, 2**20, 7, 2**31], np.uint32)
    assert np.array_equal(unpack_segment(pack_segment([1], np.array([6]), ids))[2], ids)


def test_new_pieces_are_joined_and_those_that_came_again_stay_known(sf, tokenizer, monkeypatch):
    encoder = token_pieces.worker_encoder(tokenizer)
    assert token_pieces.worker_encoder(tokenizer) is encoder
    library = encoder.encoder
    monkeypatch.setattr(encoder, "encoder", counting := _Counting(library))
    encoder._forget()
    parts = pq.read_table(f"{sf}/documents.parquet", columns=["text"])["text"].to_pylist()
    joints = ["<|endoftext", "|>", "a", " b", "c", "'s", "1", "2", " <|endoftext", "|>."]
    for some in (joints, parts[:200], parts[100:300]):
        want = [i for e in library.encode_batch_fast(some, add_special_tokens=False) for i in e.ids]
        assert encoder.encode(pa.array(some))[1].tolist() == want
    assert len(counting.given) < 0.5 * len(encoder.known)
    monkeypatch.setattr(token_pieces, "KNOWN_PIECES", len(encoder.known) - 1)
    encoder._forget()
    encoder.encode(pa.array(["one two"])), encoder.encode(pa.array(["two three"]))
    monkeypatch.setattr(token_pieces, "KNOWN_PIECES", 2)
    counting.given.clear()
    assert encoder.encode(pa.array(["two six two"]))[1].tolist() == library.encode("two six two", add_special_tokens=False).ids
    assert b" two" not in [g.encode() for g in counting.given]


def test_lanes_of_a_segment_learn_from_each_other():
    """What one lane has seen the others predict: sequences that come once in each lane cost little."""
    sequence = np.random.default_rng(5).integers(0, 40_000, 256)
    rng = np.random.default_rng(6)
    ids = np.concatenate([np.concatenate([rng.integers(0, 40_000, 256), np.roll(sequence, -8 * k)]) for k in range(200)]).astype(np.uint32)
    data = pack_segment([1], np.array([len(ids)]), ids)
    assert np.array_equal(unpack_segment(data)[2], ids)
    assert len(data) - 4 * len(np.unique(ids)) < 0.6 * 2 * len(ids)
