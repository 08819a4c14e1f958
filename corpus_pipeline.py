"""A corpus pipeline: low quality out, near copies out, benchmark passages out, secrets redacted, texts encoded.

Every stage takes nulls in any column, empty and very long texts, repeated rows, empty tables and further columns of any
name; what becomes of them is said with each operator.  Each stage reads all that its predecessor kept, as Parquet, and all but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relprop.llm import bpe, decontaminate, jaccard, quality, secrets
from relprop.llm.base import drop_dealt, remove_folder, shared_folder, table
from relprop.llm.queries import word_vocabulary


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose perplexity is above their language's threshold go."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one with the smallest id.

    Rows without an id stay last, different texts of one id are told apart by their hash.  Near copies are linked by the trie of fingerprints, directly or through others; those of a Jaccard likeness of 0.8 or more over five-word shingles that the trie has apart are linked too.
    """
    return jaccard.deduplicate(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    return decontaminate.remove(docs, table(spark, sf_dir, "benchmark"))


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every reported span becomes a mark; n_chars follows the text."""
    out = secrets.redacted(docs)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def encode_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The token ids of each text, with the columns that describe it."""
    return bpe.encode(docs, word_vocabulary()).withColumn("n_tokens", F.size("ids").cast("long")).drop("text")


STAGES = [
    ("quality", quality_stage),
    ("near_dedup", near_dedup_stage),
    ("decontamination", decontamination_stage),
    ("secrets", secrets_stage),
    ("encode", encode_stage),
]
#: Perplexities, trie links and merges are not for SQL; the tests compare the stages with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; between stages the rows are written to the checkpoint folder and read again.

    What a stage leaves there goes as soon as the next one's rows are written; the last but one stays, as the result reads it.
    """
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        drop_dealt(spark)
        if before:
            remove_folder(spark, before)
        before = f"{folder}/{name}"
        docs = spark.read.parquet(before)
    return STAGES[-1][1](spark, docs, sf_dir)
