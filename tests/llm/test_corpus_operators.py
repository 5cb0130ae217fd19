import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stratafit.llm import mixing, queries, token_codec
from stratafit.llm.decontamination import clean_documents, contaminated, fingerprints, prepare
from stratafit.llm.line_dedup import drop_recurring_lines
from stratafit.llm.mixing import balance, capped_targets, mix_sources, repeat_rows
from stratafit.llm.sharding import longest_processing_time, shard_documents
from stratafit.llm.token_output import tokens_round_trip
from stratafit.llm.url_filter import judge_urls


def test_templates_generalise_fields_and_keep_the_first(spark):
    lines = lambda k: f"Visit page {k} of our great site today\nown text number {hashlib.md5(str(k).encode()).hexdigest()} here\nAll rights are reserved by us\nshort line"
    rows = [(k, lines(k), "g", 1) for k in range(6)] + [(10, None, "g", 1), (11, "", "g", 1), (None, "All rights are reserved by us", "g", 1), (12, "a b c d e\n" + "x y " * 30_000, "g", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, template string, line int")
    got = {r["doc_id"]: r for r in drop_recurring_lines(docs).collect()}
    assert got[0]["text"] == lines(0) and got[0]["n_dropped"] == 0
    assert all("rights" not in got[k]["text"] and "Visit" not in got[k]["text"] and "short line" in got[k]["text"] for k in range(1, 6))
    assert got[10]["text"] is None and got[10]["n_lines"] == 0 and got[11]["text"] == "" and got[None]["text"] == "All rights are reserved by us"
    assert got[12]["n_dropped"] == 0 and drop_recurring_lines(docs.limit(0)).count() == 0
    none = {r["doc_id"]: r["n_dropped"] for r in drop_recurring_lines(docs, keep_first=False).collect()}
    assert none[0] == none[1] + 0 and none[0] >= 2


def test_exactly_recurring_lines_against_brute_force(spark):
    rng = random.Random(3)
    pool = [" ".join(rng.choice("abcdefghij") * 3 for _ in range(rng.randint(2, 9))) for _ in range(60)]
    docs = [(k, "\n".join(rng.choice(pool) if rng.random() < 0.6 else " ".join(f"{rng.random():.9f}".replace("0.", "q").translate(str.maketrans("0123456789", "klmnoprstu")) for _ in range(6)) for _ in range(8))) for k in range(40)]
    got = {r["doc_id"]: r["text"] for r in drop_recurring_lines(spark.createDataFrame(docs, "doc_id long, text string"), depth=64).collect()}
    has = {}
    for k, t in docs:
        for i, x in enumerate(t.split("\n")):
            has.setdefault(x, []).append((k, i))
    for k, t in docs:
        keep = [x for i, x in enumerate(t.split("\n")) if len(x.split()) < 4 or len({d for d, _ in has[x]}) < 3 or (k, i) == min(has[x])]
        assert got[k] == "\n".join(keep)


def test_lines_of_rows_that_repeat_an_id_are_cleaned_text_by_text(spark):
    stock = "All rights are reserved by us"
    rows = [(k, f"{stock}\n{'abcde'[k] * 9} text is here {'klmno'[k] * 9}") for k in (1, 3, 4)] + [(2, f"{stock}\nfirst unique line of this"), (2, f"second unique line of that\n{stock}"), (2, f"second unique line of that\n{stock}")]
    rows += [(None, f"{stock}\nnull id"), (None, None), (2, None)]
    docs = spark.createDataFrame([(k, t, "a", "b", 7) for k, t in rows], "doc_id long, text string, _row string, gone string, n_lines int")
    out = drop_recurring_lines(docs, depth=64)
    assert out.columns == ["doc_id", "text", "_row", "gone", "n_lines", "n_dropped"] and out.filter("gone = 'b' and _row = 'a'").count() == len(rows)
    got = Counter((r["doc_id"], r["text"]) for r in out.collect())
    own = {1: stock + "\n"} | dict.fromkeys((3, 4), "")
    want = Counter((k, f"{own[k]}{'abcde'[k] * 9} text is here {'klmno'[k] * 9}") for k in own) + Counter([(2, "first unique line of this"), *[(2, "second unique line of that")] * 2, (None, f"{stock}\nnull id"), (None, None), (2, None)])
    assert got == want


def test_templates_with_variable_fields_against_brute_force(spark):
    """Lines of known templates with alphabetic fields, beside lines of their own: with no line kept, exactly the templates' lines go."""
    rng = random.Random(8)
    letters = lambda n: "".join(rng.choice("abcdefghijklmnop") for _ in range(n))
    fixed = ["posted by user {} from city {} today", "this page was last seen by {} here", "read more about {} in our daily letter of news"]
    made = {k: [rng.choice(fixed).format(letters(8), letters(9)) if rng.random() < 0.5 else " ".join(letters(7) for _ in range(rng.randint(4, 9))) for _ in range(6)] for k in range(200)}
    docs = spark.createDataFrame([(k, "\n".join(v)) for k, v in made.items()], "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in drop_recurring_lines(docs, keep_first=False).collect()}
    of_template = re.compile("|".join(f.replace("{}", "[a-p]+") for f in fixed))
    assert got == {k: "\n".join(x for x in v if not of_template.fullmatch(x)) for k, v in made.items()}


def words(rng, n):
    return [f"t{rng.randrange(5000)}" for _ in range(n)]


def test_decontamination_finds_exact_and_edited_passages(spark):
    rng = random.Random(5)
    items = [words(rng, n) for n in (3, 6, 15, 20, 40, 60, 90)] + [words(rng, 300)]
    table = [(100 + k, " ".join(w)) for k, w in enumerate(items)] + [(900, None), (901, " \n")]
    rows, want = [], set()
    for k in range(60):
        text = words(rng, rng.randint(0, 200))
        if k % 3 == 0:
            j = k // 3 % len(items)
            piece = list(items[j])
            if k % 2 and len(piece) >= 60:
                piece[rng.randrange(len(piece))] = "edited"
            at = rng.randint(0, len(text))
            text[at:at] = [w.upper() if k % 4 == 0 else w for w in piece]
            want.add((k, 100 + j))
        rows.append((k, " ".join(text), "c"))
    rows += [(500, None, "c"), (501, "", "c"), (None, "free text", "c"), (502, " ".join(items[5][:-4]), "c"), (503, "w " * 50_000, "c")]
    want.add((502, 105))
    docs = spark.createDataFrame(rows, "doc_id long, text string, matches string")
    bench = spark.createDataFrame(table, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in contaminated(docs, bench).collect()}
    assert got == want
    clean = clean_documents(docs, bench)
    assert clean.columns == docs.columns and {r["doc_id"] for r in clean.collect()} == {r[0] for r in rows} - {d for d, _ in want}
    assert contaminated(docs.limit(0), bench).count() == 0 and contaminated(docs, bench.limit(0)).count() == 0


def test_hamming_search_finds_everything_within_the_radius():
    rng = np.random.default_rng(1)
    bench = prepare([(k, " ".join(f"w{x}" for x in rng.integers(0, 10_000, 30))) for k in range(40)])
    index = bench.indexes[30]
    windows = index.prints[rng.integers(0, len(index.prints), 3000)].copy()
    for i in range(len(windows)):
        for b in rng.choice(64, rng.integers(0, 12), replace=False):
            windows[i] ^= np.uint64(1) << np.uint64(b)
    got = set(zip(*(x.tolist() for x in index.search(windows, 7)), strict=True))
    want = {(i, j) for i in range(len(windows)) for j in range(len(index.prints)) if int(windows[i] ^ index.prints[j]).bit_count() <= 7}
    assert got == want


def test_window_fingerprints_against_plain_sums():
    h = np.random.default_rng(2).integers(0, 2**63, 50, dtype=np.uint64)
    from stratafit.llm.decontamination import _SEED
    from stratafit.llm.text_arrays import scramble

    bits = np.unpackbits(scramble(h ^ _SEED).view(np.uint8).reshape(50, 8), axis=1).astype(int)
    for size in (1, 7, 24, 50):
        want = [np.packbits(bits[i : i + size].sum(axis=0) > size // 2).view(np.uint64)[0] for i in range(51 - size)]
        assert fingerprints(h, [size])[size].tolist() == [int(x) for x in want]


def test_targets_stop_at_the_cap():
    got = capped_targets({"a": 10, "b": 100, "c": 1000}, {"a": 5, "b": 2, "c": 1})
    assert got["a"] == 30 and got["b"] == 300 and abs(got["c"] - 780) < 1e-9
    assert capped_targets({}, {}) == {} and capped_targets({"a": 0}, {"a": 1.0}) == {"a": 0}


def test_balance_meets_crossing_constraints(spark):
    rng = random.Random(1)
    rows = [(rng.choice("ab"), rng.choice(["x", "y", None]), rng.randint(1, 50)) for _ in range(500)]
    df = spark.createDataFrame(rows, "s string, l string, tokens long")
    total = sum(r[2] for r in rows)
    targets = {(0, "a"): 0.7 * total, (0, "b"): 0.3 * total, (1, "x"): 0.5 * total, (1, "y"): 0.2 * total, (1, None): 0.3 * total}
    m = balance(df, ["s", "l"], targets)
    rate = lambda s, l: np.exp(m[0, s] + m[1, l])
    for (c, v), t in targets.items():
        assert abs(sum(n * rate(s, l) for s, l, n in rows if (s, l)[c] == v) / t - 1) < 1e-6


def test_mixing_follows_the_contract(spark):
    rng = random.Random(2)
    rows = [(k, "w " * rng.randint(0, 80), rng.choice(["é", "a", "Z", None, "a", "a"]), 5, 0.5) for k in range(600)] + [(1000, None, "a", 1, None), (1001, "", "only-empty", 1, None), (1002, "q " * 100_000, "one-document", 1, None), (5, "twice here", "a", 1, 1.0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, size long, rate double")
    got = mix_sources(docs).collect()
    sizes = {}
    for _, t, s, *_ in rows:
        sizes[s] = sizes.get(s, 0) + len((t or "").split())
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    want = capped_targets(sizes, {s: (5.0, 2.0, 1.0)[i % 3] for i, s in enumerate(order)})
    taken = {}
    for r in got:
        assert r["taken"] == r["copies"] * r["size"] and r["taken"] <= 3 * r["size"] and r["source_size"] == sizes[r["source"]] and abs(r["target"] - want[r["source"]]) < 1e-6
        taken[r["source"]] = taken.get(r["source"], 0) + r["taken"]
    assert len(got) == len(rows) and all(abs(taken[s] - want[s]) <= 0.02 * want[s] + 1 for s in order if s != "one-document")
    assert sorted(map(str, got)) == sorted(map(str, mix_sources(docs.repartition(7)).collect()))
    assert mix_sources(docs.limit(0)).count() == 0
    repeated = repeat_rows(docs, mix_sources(docs))
    assert repeated.columns == docs.columns and repeated.filter("doc_id = 1000").count() in (0, 1, 2, 3)


@pytest.mark.parametrize("n", [0, 1, 5, 1023, 1024, 1025, 9000])
def test_codec_round_trip(n):
    rng = np.random.default_rng(n)
    ids = np.where(rng.random(n) < 0.5, rng.integers(0, 50_000, n), rng.integers(0, 12, n)).astype(np.uint32)
    cut = np.sort(rng.integers(0, n + 1, 3))
    lengths = np.diff(np.concatenate([[0], cut, [n]]))
    data = token_codec.pack_segment([7, None, -3, 2**62], lengths, ids)
    names, back, out = token_codec.unpack_segment(data)
    assert names == [7, None, -3, 2**62] and back.tolist() == lengths.tolist() and np.array_equal(out, ids)
    if n:
        broken = bytearray(data)
        broken[len(data) // 2] ^= 1
        with pytest.raises(ValueError):
            token_codec.unpack_segment(bytes(broken))


def test_codec_uses_context():
    pattern = np.tile(np.random.default_rng(0).integers(0, 40_000, 37), 200)
    noise = np.random.default_rng(1).integers(0, 40_000, len(pattern))
    assert len(b"".join(token_codec.encode_blocks(pattern))) < 0.25 * len(b"".join(token_codec.encode_blocks(noise)))


def test_order_zero_predicts_ids():
    """Independent ids cost about their entropy: frequent ids have counts of their own, and blocks start from the segment's shares."""
    share = 1 / np.arange(1, 3001) ** 1.3
    share /= share.sum()
    ids = np.random.default_rng(3).choice(3000, 60_000, p=share).astype(np.uint32) * 17
    data = token_codec.pack_segment([1], np.array([len(ids)]), ids)
    table = 4 * len(np.unique(ids))
    assert np.array_equal(token_codec.unpack_segment(data)[2], ids)
    assert 8 * (len(data) - table) < 1.08 * len(ids) * -(share * np.log2(share)).sum()


def test_spans_cover_all_ranks():
    for wide, end in ((False, 1 << 16), (True, 1 << 32)):
        spans = token_codec._Spans(wide)
        assert spans.base[0] == 0 and (spans.base[1:] == (spans.base + spans.width)[:-1]).all() and spans.base[-1] + spans.width[-1] == end
        ranks = np.unique(np.concatenate([spans.base, spans.base + spans.width - 1]))
        at = spans.of(ranks)
        assert ((ranks >= spans.base[at]) & (ranks < spans.base[at] + spans.width[at])).all()


def test_tokens_round_trip_against_the_tokenizer(spark, sf):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = str(public_tokenizers.path("byte_bpe_50k.json"))
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").union(spark.createDataFrame([(10**9, None), (-5, ""), (10**9 + 1, "é😀 " * 20_000)], "doc_id long, text string")).withColumn("start", F.lit("clash"))
    got = tokens_round_trip(docs, path).orderBy("doc_id").collect()
    encoder, start = Tokenizer.from_file(path), 0
    for r, want in zip(got, docs.orderBy("doc_id").collect(), strict=True):
        ids = [*encoder.encode(want["text"] or "", add_special_tokens=False).ids, 2]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (want["doc_id"], start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert tokens_round_trip(docs.limit(0), path).count() == 0
    twice = tokens_round_trip(spark.createDataFrame([(None, "b"), (3, "a"), (3, "a"), (None, None)], "doc_id long, text string"), path).collect()
    assert sorted(r["start"] for r in twice) == sorted(set(r["start"] for r in twice)) and {r["doc_id"] for r in twice} == {None, 3}


RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"), ("x.y.org", "/f", "block"), (None, "/", "block"), ("", "/", "block"), ("net", "/", "block")]


def judge(url):
    rest = url.split("://", 1)[1] if url and "://" in url else None
    host = re.match("[^/?#]*", rest)[0] if rest is not None else ""
    path = re.match("[^?#]*", rest[len(host) :])[0] if rest is not None else ""
    host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
    fits = [(h + p, v) for h, p, v in RULES if h and (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = min(fits, key=lambda x: (-len(x[0]), x[1] != "block", x[0]), default=(None, "allow"))
    return host, path, *best


@pytest.mark.parametrize("limit", [100_000, 0])
def test_urls_against_brute_force(spark, limit, monkeypatch):
    monkeypatch.setattr("stratafit.llm.url_filter.BROADCAST_RULES", limit)
    rng = random.Random(1)
    hosts = ["net", "a.net", "anet", "example.net", "b.EXAMPLE.net", "example.com", "q.example.com", "org", "z.x.y.org", "x.y.org", "", "net.", "1.2.3.4:80", "u@example.net"]
    urls = [f"{rng.choice(['http', 'https', ''])}://{rng.choice(hosts)}{rng.choice(['', '/', '/en', '/en/', '/de/x', '/fr/', '/f', '?q=/en/', '#/en/', '/en/?x://y', '//en/'])}" for _ in range(300)]
    urls += [None, "", "no scheme", "http:/x", "://", "http://" + "a." * 3000 + "net/" + "p/" * 3000, "x://y://net/"]
    pages = spark.createDataFrame([(k, u, "old", 1) for k, u in enumerate(urls)], "page_id long, url string, rule string, best int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in judge_urls(pages, spark.createDataFrame(RULES, "host string, path string, verdict string")).collect()}
    assert got == {k: judge(u) for k, u in enumerate(urls)}


def test_url_edges(spark):
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    pages = spark.createDataFrame([(1, "http://net/"), (1, "http://net/")], "page_id long, url string")
    assert judge_urls(pages, rules).count() == 2 and judge_urls(pages.limit(0), rules).count() == 0
    assert {r["verdict"] for r in judge_urls(pages, rules.limit(0), default="block").collect()} == {"block"}


def test_longest_processing_time_by_hand():
    placed = longest_processing_time([(5, "a"), (4, "b"), (3, "c"), (3, "d"), (3, "e")], 2)
    assert placed == {"a": 0, "b": 1, "c": 1, "d": 0, "e": 1}


@pytest.mark.parametrize("units", [1024, 1])
def test_shards(spark, units):
    rng = random.Random(4)
    rows = [(k, rng.choice(["same", None, "", "é" * rng.randint(1, 300), "word " * rng.randint(0, 40)]), "s", 1) for k in range(500)] + [(None, "n", "s", 1), (7, "x" * 100_000, "s", 1), (7, "x" * 100_000, "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, group string, shard int")
    got = shard_documents(docs, 5, units, 20).collect()
    assert len(got) == len(rows) and {r["law"] for r in got} == {"bytes"} and all(r["grown_shard"] is None for r in got)
    where = {}
    for r in got:
        where.setdefault((r["text_crc32"], r["size"]), set()).add(r["shard"])
    assert all(len(x) == 1 for x in where.values())
    for k in range(5):
        slots = sorted(r["slot"] for r in got if r["shard"] == k)
        assert slots == list(range(len(slots)))
    sizes = {(r["text_crc32"], r["size"]) for r in got}
    assert {(zlib.crc32(b"same"), 20), (0, 16)} <= sizes
    assert shard_documents(docs.limit(0), 5).count() == 0
    assert sorted(map(str, got)) == sorted(map(str, shard_documents(docs.repartition(6), 5, units, 20).collect()))


def test_decontamination_equals_a_search_of_all_windows(spark):
    rng = random.Random(11)
    items = [words(rng, n) for n in (4, 5, 9, 37, 47, 58, 73, 114, 300)] + [["a", "b"] * 20]
    share = items[6][:30] + words(rng, 40)
    items.append(share)
    docs = []
    for w, edit, cut in ((73, 5, 0), (114, 9, 0), (300, 35, 0), (58, 0, 10), (47, 0, 10), (37, 0, 6), (73, 12, 0), (40, 0, 5), (9, 1, 0), (4, 0, 0), (5, 0, 0), (70, 3, 0)):
        item = next(i for i in items if len(i) == w)
        for _ in range(12):
            piece = item[: len(item) - cut]
            at = rng.randint(0, len(piece) - edit)
            piece = piece[:at] + words(rng, edit + rng.choice([0, 0, 1]) * bool(edit)) + piece[at + edit :]
            docs.append(piece if cut else words(rng, rng.randint(0, 40)) + piece + words(rng, rng.randint(0, 40)))
    grams = lambda w: [tuple(w[i : i + 5]) for i in range(len(w) - 4)] if len(w) >= 5 else [tuple(w)]
    bags = [Counter(grams(i)) for i in items]
    spread = Counter(g for b in bags for g in b)
    weight = lambda g: np.log1p(len(items) / spread[g]) if g in spread else np.log1p(len(items))
    want = {}
    for d, text in enumerate(docs):
        for k, item in enumerate(items):
            for at in range(len(text)):
                bag = Counter(grams(text[at : at + len(item)]))
                both = bag.keys() | bags[k].keys()
                s = sum(weight(g) * min(bag[g], bags[k][g]) for g in both) / sum(weight(g) * max(bag[g], bags[k][g]) for g in both)
                if s >= 0.75 - 1e-12 and s > want.get((d, k), (0, 0))[0] + 1e-12:
                    want[d, k] = (s, at)
    rows = contaminated(spark.createDataFrame([(d, " ".join(t)) for d, t in enumerate(docs)], "doc_id long, text string"), spark.createDataFrame([(k, " ".join(i)) for k, i in enumerate(items)], "item_id long, text string")).collect()
    got = {(r["doc_id"], r["item_id"]): (r["similarity"], r["word_start"]) for r in rows}
    assert got.keys() == want.keys() and len(want) > 80
    assert all(abs(got[x][0] - want[x][0]) < 1e-9 and got[x][1] == want[x][1] for x in want)


@pytest.mark.parametrize("n", [60, 1000, 6000])
def test_fields_stay_fields_however_often_their_values_recur(spark, n):
    rng = random.Random(n)
    name = lambda k: "".join("abcdefghijklmnopqrst"[int(d)] for d in str(k))
    rows = [(k, f"posted by user {name(rng.randrange(40))} from {name(100 + rng.randrange(30))} today\nposted by user request only once today") for k in range(n)]
    rows += [(n + k, f"posted by user {name(rng.randrange(40))} of the {name(rng.randrange(30))} group since long ago") for k in range(n // 4)]
    got = drop_recurring_lines(spark.createDataFrame(rows, "doc_id long, text string")).agg(F.sum("n_lines").alias("n"), F.sum("n_dropped").alias("dropped")).first()
    assert got["n"] - got["dropped"] == 3


def test_short_lines_go_where_they_recur_as_they_are(spark, tmp_path):
    rows = [(k, f"All rights  reserved.\nPage {k}\nown{'abcdefgh'[k]} line\n\nHome" if k < 5 else "Page 7\nALL rights reserved.\nfew words") for k in range(7)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {r["doc_id"]: r for r in queries.op1_template_line_dedup(spark, str(tmp_path)).collect()}
    want = {k: t if k == 0 else f"Page {k}\nown{'abcdefgh'[k]} line\n" if k < 5 else "Page 7\nfew words" for k, t in rows}
    assert {k: r["text_sha256"] for k, r in got.items()} == {k: hashlib.sha256(t.encode()).hexdigest() for k, t in want.items()}
    assert [got[k]["n_dropped"] for k in range(7)] == [0, 2, 2, 2, 2, 1, 1]


def test_rows_without_or_with_the_same_id_are_repeated_by_their_own_copies(spark):
    rng = random.Random(8)
    rows = [(rng.choice([None, 1, 2, k]), f"t{k} " + "w " * rng.randint(0, 4), rng.choice(["a", "b", "c", None])) for k in range(400)] + [(None, None, "a")] * 3 + [(7, "same text", "b")] * 5
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    mixed = mix_sources(docs)
    want, got = Counter(), Counter()
    for r in mixed.collect():
        want[r["doc_id"], r["source"], r["size"]] += r["copies"]
    out = repeat_rows(docs, mixed).collect()
    for r in out:
        got[r["doc_id"], r["source"], len((r["text"] or "").split())] += 1
    assert got == +want and any(k[0] is None for k in got) and max(Counter(map(tuple, out)).values()) <= 3 * 5
    assert all(n <= 3 for r, n in Counter(map(tuple, out)).items() if r[1] not in (None, "same text"))
    assert sorted(map(str, out)) == sorted(map(str, repeat_rows(docs.repartition(5), mix_sources(docs.repartition(3))).collect()))


def test_copies_that_share_an_id_are_spread_over_blocks(spark):
    n = 3 * mixing.ALIKE_ROWS + 7
    docs = spark.createDataFrame([(None, "same few words", "a", k) for k in range(n)] + [(k, f"one {k}", "b", k) for k in range(4000)], "doc_id long, text string, source string, nr int")
    mixed = mix_sources(docs, block_rows=500)
    rows = mixed.collect()
    assert len(rows) == n + 4000 and sum(r["doc_id"] is None for r in rows) == n
    own = [r for r in rows if r["source"] == "a"]
    assert abs(sum(r["taken"] for r in own) - own[0]["target"]) <= 0.01 * own[0]["target"]
    out = repeat_rows(docs, mixed).collect()
    assert Counter(Counter(r["nr"] for r in out if r["doc_id"] is None).values()) == Counter(r["copies"] for r in rows if r["doc_id"] is None and r["copies"])
    assert sorted(map(str, out)) == sorted(map(str, repeat_rows(docs.repartition(6), mix_sources(docs.repartition(3), block_rows=500)).collect()))


def test_codec_takes_more_distinct_ids_than_two_bytes_hold():
    ids = np.random.default_rng(2).permutation(70_000).astype(np.uint32) * 7
    names, lengths, back = token_codec.unpack_segment(token_codec.pack_segment([1, None], np.array([30_000, 40_000]), ids))
    assert names == [1, None] and lengths.tolist() == [30_000, 40_000] and (back == ids).all()


def test_shard_sizes_are_near_equal(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = shard_documents(docs, shards=8).groupBy("shard").agg(F.sum("size").alias("b")).collect()
    largest = docs.groupBy("text").agg(F.sum(F.octet_length("text") + 16).alias("b")).agg(F.max("b")).first()[0]
    sizes = [r["b"] for r in got]
    assert len(sizes) == 8 and max(sizes) <= max(largest, sum(sizes) / 8 * 1.01) and (max(sizes) - min(sizes) <= 0.01 * max(sizes) or max(sizes) == largest)


def test_weights_do_not_depend_on_portions(spark, monkeypatch):
    from stratafit.llm import decontamination

    rng = random.Random(12)
    shared = words(rng, 12)
    items = [(k, " ".join([*words(rng, 18), *shared, *words(rng, 10)])) for k in range(12)]
    docs = spark.createDataFrame([(k, " ".join([*t.split()[: 40 - k], *words(rng, k)])) for k, t in items], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    whole = sorted(tuple(r) for r in contaminated(docs, bench).collect())
    monkeypatch.setattr(decontamination, "PASS_BYTES", 600)
    assert len(decontamination._passes(bench)) > 3 and sorted(tuple(r) for r in contaminated(docs, bench).collect()) == whole and whole
