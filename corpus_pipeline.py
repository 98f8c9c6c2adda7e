"""Corpus preparation in five stages: quality, near duplicates, decontamination, mixing, token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from levelgraph.llm.decontamination import drop_contaminated
from levelgraph.llm.line_quality import drop_low_quality, fit
from levelgraph.llm.mixing import mixed_documents
from levelgraph.llm.near_duplicates import drop_near_duplicates
from levelgraph.llm.token_output import token_table
from levelgraph.runtime import materialize


BATCH_ROWS = 1000


def _bounded_batches(spark: SparkSession) -> None:
    """Rows of whole texts that a Python worker gets at once; the default of 10,000 takes tens of megabytes several times over."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line classifier, fitted on the labelled part of the source tables, accepts."""
    _bounded_batches(spark)
    model = fit(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return drop_low_quality(docs, model)


def keep_first_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates."""
    _bounded_batches(spark)
    return drop_near_duplicates(docs)


def keep_uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    _bounded_batches(spark)
    return drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix of its source asks for."""
    return mixed_documents(docs)


def write_token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token-id shards in the shared folder, and the row that each document has when read back."""
    _bounded_batches(spark)
    return token_table(docs)


STAGES = [
    ("quality_classifier", keep_good),
    ("minhash_near_dedup", keep_first_copies),
    ("benchmark_decontamination", keep_uncontaminated),
    ("source_mix", mix_sources),
    ("token_output", write_token_ids),
]

# A conditional random field and a tokenizer are outside SQL; tests hold run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet to the shared folder and read again.

    The session's batch size is as it was afterwards."""
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(setting)
    try:
        docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
        for name, stage in STAGES:
            docs = materialize(stage(spark, docs, sf_dir), name)
    finally:
        spark.conf.set(setting, before)
    return docs
