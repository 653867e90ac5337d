"""A training-corpus pipeline: language, quality, exact and near duplicates, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes each result
as Parquet and hands what it reads back to the next.  All stages but the last return the
columns of ``documents``; the last returns the packed pieces.  A document of which a stage
can't tell anything bad stays.  No SQL expresses the learned stages.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from winsub.llm import op01_exact_dedup, op03_language_id, op04_packing, op06_parity_join, op07_quality
from winsub.llm.common import fold, small_batches, stage, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a language; those without a letter, or with letters of no language, go."""
    small_batches(spark)
    return op03_language_id.kept_documents(docs, op03_language_id.fit(op03_language_id.training_rows(docs)))


def select_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a quality score of at least one half."""
    small_batches(spark)
    labels = table(spark, sf_dir, "labels").where(fold("doc_id", 4) != 2)
    return op07_quality.kept_documents(docs, op07_quality.fit(docs.where(fold("doc_id", 4) != 2), labels))


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal normalised texts."""
    return op01_exact_dedup.kept_documents(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that near-duplicate links connect."""
    return op06_parity_join.kept_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 4096 ids."""
    small_batches(spark)
    return op04_packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language_id", identify_language),
    ("quality", select_quality),
    ("exact_dedup", drop_exact_copies),
    ("near_duplicates", drop_near_copies),
    ("packing", pack_sequences),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
