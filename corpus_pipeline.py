"""The training-data pipeline: five stages, each written as Parquet and read again as the next one's documents.

Every stage works row by row on what it is given: rows with a null doc_id, rows that repeat an id or a whole row, and columns of any other name pass with their values
unchanged; the first four return the columns of docs in their order. An empty table gives an empty one.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from stratafit.llm.common import checkpointed, collect_garbage, shared_folder
from stratafit.llm.decontamination import clean_documents
from stratafit.llm.language_id import fold, identify_rows, learn
from stratafit.llm.mixing import mix_sources, repeat_rows
from stratafit.llm.near_dedup import near_duplicate_components
from stratafit.llm.token_output import tokens_round_trip


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language is found; texts that are null or without a letter go. Only rows outside the held-out fold teach, a null lang teaches nothing; where nothing can be learned, all go."""
    langs, model = learn(docs.filter(fold("doc_id", 4) != 2).select("text", "lang"))
    return identify_rows(docs, langs, model).filter("lang_pred != 'und'").select("row.*")


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest doc_id. Texts without words, and rows with a null doc_id, link with nothing and stay; rows that share an id share its fate."""
    dropped = checkpointed(near_duplicate_components(docs).filter("not kept").select("doc_id").distinct())
    collect_garbage(spark)
    return docs.join(dropped, "doc_id", "left_anti").select(docs.columns)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark. A null or blank text has none; a benchmark without rows takes nothing out."""
    return clean_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated, kept or left out so that sources reach their target weights. Each row is repeated by its own copies, whatever its id; a null source is a source, null texts have size 0."""
    return repeat_rows(docs, mix_sources(docs))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files in ascending doc_id order, null ids first, read back: doc_id, start, n_tokens, ids_crc32, one row per row of docs; a null text is its end id alone."""
    import public_tokenizers

    return tokens_round_trip(docs, str(public_tokenizers.path("byte_bpe_50k.json")))


STAGES = [("language", language_stage), ("near_dedup", near_dedup_stage), ("decontamination", decontamination_stage), ("mixing", mixing_stage), ("tokens", token_stage)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over documents; what each returns is written beside the checkpoints and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_folder(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
