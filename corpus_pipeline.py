"""Corpus pipeline: quality rules, exact dedup, near dedup, mixing, packing.

Every stage reads what its predecessor kept, as Parquet, and all but the last return the
columns of `documents`.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from subvote.llm import exact_dedup, mixing, ngram_join, packing, quality_rules
from subvote.llm._store import discard, documents, materialize


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line model and the base rules keep."""
    field = quality_rules.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality_rules.kept_rows(docs, field)


def dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of every group of equal texts."""
    return exact_dedup.kept_rows(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of every component of near copies: five words, similarity 0.8."""
    return ngram_join.kept_rows(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources brought to their target sizes; rows repeat once per epoch."""
    return mixing.apply_mix(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 4096 tokens."""
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality_rules", quality), ("exact_dedup", dedup), ("ngram_jaccard_join", near_dedup), ("mixing", mixture), ("packing", pack)]

#: Line labelling and the tokenizer have no SQL form; a brute-force version is in tests/llm.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order; a stage's table is deleted once its successor has read it."""
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        kept = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        discard(docs)
        docs = kept
    packed = STAGES[-1][1](spark, docs, sf_dir)
    discard(docs)  # packing has written its pieces
    return packed
