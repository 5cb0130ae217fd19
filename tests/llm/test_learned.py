import random
import zlib

import numpy as np
from pyspark.sql import functions as F

from stratafit.llm.language_id import language_of, mixture
from stratafit.llm.quality import dual_coordinate_descent, fit, quality_of


def test_mixture_finds_shares_and_drops_languages():
    rng = np.random.default_rng(0)
    scores = rng.normal(0, 0.3, (300, 3))
    scores[:200, 0] += 6
    scores[200:, 1] += 6
    share = mixture(scores)
    assert abs(share[0] - 2 / 3) < 0.03 and abs(share[1] - 1 / 3) < 0.03 and share[2] == 0
    pure = mixture(scores[:200])
    assert pure[0] == 1 and pure[1] == pure[2] == 0
    assert mixture(np.zeros((1, 2))).argmax() == 0


def test_language_accuracy_on_held_out(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = language_of(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert len(got) == docs.count()
    held = [r for r in got if r["held_out"]]
    assert held and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    assert np.mean([r["lang_pred"] == r["lang"] for r in held]) > 0.95
    assert all(0 <= r["score"] <= 1 and abs(sum(r["proportions"].values()) - 1) < 1e-9 for r in got)


def test_language_edges(spark):
    rows = [(1, "the cat sat", "en", "s", 0.1), (2, "die Katze saß", "de", "s", 0.2), (3, None, "en", None, 0.3), (4, "", None, "s", 0.1), (5, "1234 !!", "de", "s", 0.1), (None, "the the", "en", "s", 0.0), (6, "中文", None, "s", 0.1), (7, "the " * 40_000, "en", "s", 0.1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, row string, score double")
    got = {r["doc_id"]: r for r in language_of(docs).collect()}
    assert len(got) == 8 and all(got[k]["lang_pred"] == "und" and got[k]["score"] == 0 for k in (3, 4, 5))
    assert got[6]["lang_pred"] in ("de", "en") and got[7]["lang_pred"] == "en"
    assert language_of(docs.limit(0)).count() == 0
    blank = language_of(docs.withColumn("lang", F.lit(None).cast("string"))).collect()
    assert {r["lang_pred"] for r in blank} == {"und"}


def test_quality_accuracy_on_held_out(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = quality_of(docs, labels)
    held = [r for r in got.join(labels, "doc_id").collect() if r["held_out"]]
    assert got.count() == docs.count() and len(held) > 50
    assert np.mean([r["predicted"] == r["quality"] for r in held]) > 0.9
    pairs = [(a["score"], b["score"]) for a in held for b in held if a["quality"] > b["quality"]]
    assert np.mean([x > y for x, y in pairs]) > 0.95


def test_quality_edges(spark):
    rng = random.Random(0)
    rows = [(k, " ".join(rng.choice(["good", "fine", "nice"] if k % 2 else ["spam!!", "buy$$", "win%%"]) for _ in range(20)), 1.0, "x") for k in range(60)]
    rows += [(100, None, 1.0, "x"), (101, "", 1.0, "x"), (None, "good", 1.0, "x"), (103, "a", None, None), (103, "a", None, None), (104, "fine " * 60_000, 0.0, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score double, predicted string")
    labels = spark.createDataFrame([(k, k % 2, 0) for k in range(60)] + [(0, 1, 0), (None, 1, 0), (1, None, 0), (500, 1, 1)], "doc_id long, quality int, toxic int")
    got = quality_of(docs, labels).collect()
    assert len(got) == len(rows) and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in got)
    by = {r["doc_id"]: r["predicted"] for r in got}
    assert np.mean([by[k] == k % 2 for k in range(60)]) == 1
    assert quality_of(docs.limit(0), labels).count() == 0
    assert quality_of(docs, labels.limit(0)).count() == len(rows)
    assert {r["predicted"] for r in quality_of(docs, labels.filter("quality = 1")).collect()} == {1}


def test_the_fit_takes_rows_in_order_until_rows_or_buckets_are_full(spark):
    rows = [(k, f"good fine {k}" if k % 2 else f"spam buy$$ {k}", k % 2) for k in range(40)]
    labelled = spark.createDataFrame(rows, "doc_id long, text string, quality int")
    order = [r[0] for r in labelled.orderBy(F.xxhash64("doc_id")).select("doc_id").collect()]
    model = fit(labelled)
    ten = labelled.filter(F.col("doc_id").isin(order[:10]))
    assert np.array_equal(fit(labelled, rows=10).weights, fit(ten).weights) and not np.array_equal(fit(ten).weights, model.weights)
    assert np.array_equal(fit(labelled.union(labelled).repartition(5)).weights, model.weights)
    few = fit(labelled, buckets=100)
    assert any(np.array_equal(few.weights, fit(labelled, rows=n).weights) for n in range(1, 10))
    assert fit(labelled, buckets=0).bias == 0


def test_dual_coordinate_descent_reaches_the_primal_optimum():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(80, 5))
    y = np.sign(x @ np.array([1, -2, 0.5, 0, 0]) + rng.normal(scale=0.5, size=80))
    rows, values = [np.arange(5)] * 80, list(x)
    w, b = dual_coordinate_descent(rows, values, y, 5, epochs=500)
    objective = lambda w, b: 0.5 * (w @ w + b * b) + np.maximum(0, 1 - y * (x @ w + b)).sum()
    best = objective(w, b)
    for _ in range(300):
        assert objective(w + rng.normal(scale=0.05, size=5), b + rng.normal(scale=0.05)) > best - 1e-2
