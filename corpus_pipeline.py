"""A corpus pipeline over `documents`: language, near copies, test items, personal data, packing.

Each stage takes what the stage before kept; run() writes each stage's result
and reads it back, so that a lost executor costs one stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cityweave.llm import decontam, langid, packing, pii, simhash
from cityweave.llm.queries import table, tokenizer_path
from cityweave.scratch import Scratch


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents whose language can't be told; the model learns from the given rows."""
    return langid.keep_identified(docs, langid.train(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group of near copies."""
    return simhash.simhash_representatives(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that overlap with a test item."""
    return decontam.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data in the texts."""
    return pii.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the texts into sequences of at most 4096 tokens."""
    return packing.best_fit_packing(docs, tokenizer_path())


STAGES = [
    ("language_id", language),
    ("simhash_near_dedup", near_dedup),
    ("decontamination", decontaminate),
    ("pii", private),
    ("packing", pack),
]

#: Stages with trained models and iteration have no SQL form; tests hold them against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scratch = Scratch(spark, "pipeline")
    for _, stage in STAGES:
        docs = scratch.keep(stage(spark, docs, sf_dir))
    return docs
