import re
from collections import Counter

from pyspark.sql import functions as F

import __spark_entry__ as entry_module
import corpus_pipeline
from stratafit.llm import queries
from stratafit.llm.mixing import mix_sources


def test_stages_return_documents_and_take_effect(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    extra = spark.createDataFrame([(10**6, None, "en", "s", 0), (10**6 + 1, "12 34", "en", "s", 5)], docs.schema)
    docs = docs.union(extra)
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        out = spark.read.parquet(str(tmp_path / name))
        if name == "language":
            assert docs.count() - out.count() == 2
        if name == "near_dedup":
            assert out.count() < docs.count() and out.count() == out.select("doc_id").distinct().count()
        if name == "decontamination":
            items = [re.sub(r"\s+", " ", r["text"].lower()) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            dirty = {r["doc_id"] for r in docs.collect() if any(i in re.sub(r"\s+", " ", r["text"].lower()) for i in items)}
            assert {r["doc_id"] for r in docs.collect()} - {r["doc_id"] for r in out.collect()} == dirty
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == columns
        docs = out
    assert docs.columns == ["doc_id", "start", "n_tokens", "ids_crc32"] and docs.count() > 0


def test_run_is_registered(spark, sf):
    assert [k for k, _ in corpus_pipeline.STAGES] == ["language", "near_dedup", "decontamination", "mixing", "tokens"]
    assert queries.queries()["pipeline"] is corpus_pipeline.run
    rows = corpus_pipeline.run(spark, sf)
    last = rows.agg(F.max(F.col("start") + F.col("n_tokens")).alias("end"), F.sum("n_tokens").alias("sum")).first()
    assert last["end"] == last["sum"]


def test_ten_operators_are_registered():
    names = entry_module.queries()
    assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
    assert set(entry_module.oracle_sql()) <= set(names)


def test_stages_on_null_and_repeated_ids_empty_tables_and_clashing_columns(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60)
    known = docs.first()
    odd = [(None, known["text"] + " and then some more words", "en", "s", 3), (None, None, None, None, None), (10**7, "one two three four five six seven", "en", None, 1), (10**7, "eight nine ten eleven twelve thirteen", "en", None, 1), (10**7, "eight nine ten eleven twelve thirteen", "en", None, 1), (6, "", "en", "s", 0)]
    docs = docs.union(spark.createDataFrame(odd, docs.schema))
    for name in ("row", "_row", "key", "node", "size", "copies", "matches", "lang_pred", "kept", "component_id", "_n"):
        docs = docs.withColumn(name, F.lit(name))
    columns, key = docs.columns, ["doc_id", "text", "source"]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        out = spark.read.parquet(str(tmp_path / name))
        assert stage(spark, docs.limit(0), sf).count() == 0
        if k == len(corpus_pipeline.STAGES) - 1:
            assert sorted((r["doc_id"] for r in out.collect()), key=str) == sorted((r["doc_id"] for r in docs.collect()), key=str)
            continue
        assert out.columns == columns and all(r["row"] == "row" and r["_n"] == "_n" for r in out.collect())
        before, after = Counter(tuple(r[c] for c in key) for r in docs.collect()), Counter(tuple(r[c] for c in key) for r in out.collect())
        assert set(after) <= set(before)
        if name == "language":
            assert after == Counter({k: n for k, n in before.items() if k[1] and re.search(r"[^\W\d_]", k[1])})
        if name in ("near_dedup", "decontamination"):
            assert all(after[k] == before[k] for k in after) and sum(n for k, n in after.items() if k[0] is None) == 1
            assert sum(n for k, n in after.items() if k[0] == 10**7) == 3
        if name == "mixing":
            rates = mix_sources(docs).collect()
            assert sum(after.values()) == sum(r["copies"] for r in rates)
            assert sum(n for k, n in after.items() if k[0] == 10**7) == sum(r["copies"] for r in rates if r["doc_id"] == 10**7)
        docs = out
