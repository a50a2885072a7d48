"""The document pipeline: each stage reads all that its predecessor kept, written down in between."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cleantrain.llm import decontaminate, language_id, line_windows, probminhash, sentencepiece_lattice
from cleantrain.llm.common import scratch_table


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in no trained language go."""
    return language_id.keep_identified(docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later occurrences of three-line passages are cut; a document of which no line stays goes."""
    return line_windows.dedup_lines(docs)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates the document with the least doc_id stays."""
    return probminhash.keep_one(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans that occur in a benchmark item are cut; a document that is mostly such spans goes."""
    return decontaminate.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and ids of the documents that are left."""
    return sentencepiece_lattice.encode(docs)


STAGES = [("language_id", language_stage), ("line_dedup", line_stage), ("near_duplicates", near_duplicate_stage), ("decontaminate", decontamination_stage), ("sentencepiece", token_stage)]
#: SQL can't express the trained, sketched and iterated stages; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for number, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number < len(STAGES) - 1:
            docs = scratch_table(docs)
    return docs
