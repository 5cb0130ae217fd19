import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from stratafit.llm import text_arrays as T
from stratafit.llm.common import components, hot_safe_lookup
from stratafit.llm.exact_dedup import exact_duplicates
from stratafit.llm.near_dedup import near_duplicate_components, prefix_candidates

SCHEMA = "doc_id long, text string, digest string, node long, key string, _salt int"
WORDS = [f"w{i}" for i in range(400)]


def frame(spark, rows):
    """Documents with columns whose names the operators use inside."""
    return spark.createDataFrame([(i, t, "x", 7, "k", 1) for i, t in rows], SCHEMA)


def shingles(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if w]
    if not words:
        return set()
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} if len(words) >= 5 else {tuple(words)}


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and 100 * len(x & y) >= 75 * len(x | y):
                root[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(sets):
        least[find(k)] = min(i, least.get(find(k), i))
    return {(i, len(s), least[find(k)], i == least[find(k)]) for k, (i, s) in enumerate(sets)}


def near_copies(rng, n=60):
    rows, k = [], 0
    for _ in range(8):
        base = [rng.choice(WORDS) for _ in range(rng.randint(3, 120))]
        for _ in range(n // 8):
            copy = [rng.choice(WORDS) if rng.random() < rng.choice([0, 0.01, 0.03, 0.06]) else w for w in base]
            rows.append((k, " ".join(copy)))
            k += 1
    return rows + [(k, None), (k + 1, ""), (k + 2, " \t\n"), (k + 3, "One two"), (k + 4, "one\ttwo"), (k + 5, "x " * 30_000), (k + 6, "x " * 40_000)]


def test_words_and_shingles_agree_with_plain_python():
    texts = ["A b\tc", None, "", "  x  ", "é ü\x0b\x0cß", "one two three four five six", "Z\x1fq z"]
    column = pa.array(texts)
    found = [(t, len(set(s.tolist()))) for chunk in T.text_chunks(column, 4) for t, s in T.document_shingles(chunk)]
    assert found == [(i, len(shingles(t))) for i, t in enumerate(texts)]
    same = {s.tobytes() for chunk in T.text_chunks(pa.array(["one TWO", "one two", "\none  two"])) for _, s in T.document_shingles(chunk)}
    assert len(same) == 1


def test_word_hashes_do_not_depend_on_the_place():
    a = T.word_hashes(c := next(T.text_chunks(pa.array(["aa bb aa cc"]))), T.words(c))
    assert a[0] == a[2] and len(set(a.tolist())) == 3
    assert T.text_chunks(pa.array([], pa.string())) is not None and list(T.text_chunks(pa.array([], pa.string()))) == []


def test_exact_duplicates_rules(spark):
    rows = [(5, "a b"), (3, "ab"), (4, "a  b"), (9, "a  b"), (1, None), (2, " \n"), (7, "A b"), (None, "z"), (8, "z"), (-6, "q"), (-7, "q"), (11, "y" * 50_000), (11, "y" * 50_000)]
    got = {(r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exact_duplicates(frame(spark, rows)).collect()}
    assert (3, 4, 4, False) in got and (4, 4, 4, True) in got and (9, 4, 4, False) in got
    assert (1, 2, 2, False) in got and (2, 2, 2, True) in got
    assert (7, 7, 1, True) in got and (None, 8, 2, False) in got and (-7, -7, 2, True) in got and (11, 11, 2, True) in got
    assert exact_duplicates(frame(spark, [])).count() == 0


def test_exact_duplicates_when_digests_clash(spark):
    rows = [(i, t) for i, t in enumerate(["a", "b", "a", "c c", "cc", "b"])]
    weak = exact_duplicates(frame(spark, rows), digest=lambda t: F.substring(F.sha2(t, 256), 1, 0)).collect()
    assert {(r["doc_id"], r["keep_id"], r["group_size"]) for r in weak} == {(0, 0, 2), (2, 0, 2), (1, 1, 2), (5, 1, 2), (3, 3, 2), (4, 3, 2)}


def test_exact_duplicates_run_no_python(spark):
    plan = exact_duplicates(frame(spark, [(1, "a")]))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_near_duplicates_against_brute_force(spark, seed):
    rows = near_copies(random.Random(seed))
    got = {tuple(r) for r in near_duplicate_components(frame(spark, rows)).collect()}
    assert got == brute_components(rows)


def test_near_duplicates_edges(spark):
    rows = [(3, "a b c d e f"), (3, "a b c d e f"), (None, "A b c d e f"), (None, None), (2, None)]
    got = sorted(((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in near_duplicate_components(frame(spark, rows)).collect()), key=str)
    assert got == sorted([(3, 2, 3, True), (3, 2, 3, True), (None, 2, 3, True), (None, 0, None, True), (2, 0, 2, True)], key=str)
    assert near_duplicate_components(frame(spark, [])).count() == 0


def test_prefix_candidates_hold_every_similar_pair(spark):
    rng = random.Random(9)
    sets = {}
    for k in range(150):
        base = set(rng.sample(range(60), rng.randint(1, 50))) if k < 100 else sets[rng.randrange(100)] - {rng.randrange(60)}
        sets[k] = base or {0}
    rows = [(k, k % 7, [int(T.scramble(np.array([x], np.uint64))[0].astype(np.int64)) for x in sorted(s)]) for k, s in sets.items()]
    df = spark.createDataFrame(rows, "node long, root long, shingles array<long>")
    got = {(r["a"], r["b"]) for r in prefix_candidates(df).collect()}
    want = {(a, b) for a in sets for b in sets if a < b and a % 7 != b % 7 and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])}
    assert want and want <= got


def test_components_of_paths_stars_and_loops(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, k) for k in range(101, 140)] + [(200, 200), (None, 3), (300, 301), (301, 302), (302, 300)]
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[k] == 0 for k in range(41)) and all(got[k] == 100 for k in range(100, 140)) and got[302] == 300 and 200 not in got
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_small_graphs_take_few_jobs_and_large_ones_the_same_components(spark, monkeypatch):
    rng = random.Random(6)
    pairs = [(rng.randrange(-600, 600), rng.randrange(-600, 600)) for _ in range(500)] + [(k, k + 1) for k in range(1000, 1060)] + [(None, 3), (7, 7)]
    edges = spark.createDataFrame(pairs, "a long, b long")
    context = spark.sparkContext
    context.setJobGroup("small-graph", "components")
    small = {tuple(r) for r in components(edges).collect()}
    context.setJobGroup("other", "")
    assert len(context.statusTracker().getJobIdsForGroup("small-graph")) <= 8
    for most in (0, 40):
        monkeypatch.setattr("stratafit.llm.common.DRIVER_EDGES", most)
        assert {tuple(r) for r in components(edges).collect()} == small


def test_lookup_spreads_hot_keys(spark):
    rows = spark.range(5000).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 3000, 1).otherwise(F.col("id")).alias("k"))
    groups = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    got = hot_safe_lookup(rows, groups, "k", "n", 5000)
    assert got.count() == 5000 and got.filter("k = 1 and n = 3000").count() == 3000


def test_a_large_group_of_near_copies_is_one_component(spark):
    """Each copy differs in one word of its own; a copy of a copy and texts that share less than the bound hang on the same keys."""
    rng = random.Random(4)
    base = [f"w{rng.randrange(10**6)}" for _ in range(160)]
    rows = [(k, " ".join([*base[: k % 150], f"own{k}", *base[k % 150 + 1 :]])) for k in range(10, 1510)]
    rows += [(5, " ".join(base[:60] + [f"x{i}" for i in range(100)])), (6, " ".join(f"x{i}" for i in range(100)))]
    got = {r["doc_id"]: r["component_id"] for r in near_duplicate_components(frame(spark, rows)).collect()}
    assert len(got) == 1502 and all(got[k] == 10 for k in range(10, 1510)) and got[5] == 5 and got[6] == 6
