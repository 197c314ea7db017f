"""A training-data pipeline: quality rules, near-duplicates, personal data, mixing, token pieces.

Each stage takes (spark, docs, sf_dir) and returns a table that is written as Parquet and read again for the next one.
All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import functools

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wsig.llm import mixing, piece_codec, pii, quality_rules, shared, simhash

#: Quality rules and merge-dropout have no SQL form; tests/llm/test_pipeline.py holds run() against brute force.
ORACLE_SQL = None


#: Near copies: fingerprints of five-word shingles that differ in at most six bits. README has the recall by similarity.
NEAR_BITS, NEAR_SHINGLE = 6, 5


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and their language's perplexity band keep."""
    return quality_rules.keep_good(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each near-duplicate group."""
    return simhash.near_dedup(docs, NEAR_BITS, NEAR_SHINGLE)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced by their kinds."""
    return pii.mask_pii(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's target takes it, in training order."""
    return mixing.in_training_order(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of every copy, one segmentation for each document."""
    return piece_codec.encode_pieces(docs, public_tokenizers.path("piece_bpe_32k.model"))


def _bounded(stage):
    """A stage with small Arrow batches, as two tasks' batches and workers share an executor with the JVM's heap."""

    @functools.wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        shared.small_batches(spark)
        return stage(spark, docs, sf_dir)

    return run_stage


_STAGES = [("quality rules", drop_low_quality), ("near duplicates", drop_near_duplicates), ("personal data", mask_personal_data), ("mixing", mix), ("token pieces", encode)]
STAGES = [(name, _bounded(stage)) for name, stage in _STAGES]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs, _ = shared.settle(docs, f"stage-{name.replace(' ', '-')}")
    return docs
