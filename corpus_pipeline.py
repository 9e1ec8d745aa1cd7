"""Corpus pipeline: language ID, quality rules, near-duplicates, packing.

Each stage gets what the one before kept and decides with the operator of its
name; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from bitextspark.llm import langid_crf, nnls_packing, quality_rules, simhash
from bitextspark.llm.common import cut, table


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, and those of which no language has half of the words, go."""
    return langid_crf.keep(docs)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or their group's fences go."""
    return quality_rules.keep(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five-word shingles, similarity 0.8 by 256-bit fingerprints) the document with the smallest id stays."""
    return simhash.keep_one(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents' ids in sequences, one row per piece."""
    return nnls_packing.pack(docs)


STAGES = [("language_id", language_id), ("quality_rules", quality), ("near_dedup", near_dedup), ("packing", packing)]

#: A trained model and sketches decide, which SQL can't express; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
