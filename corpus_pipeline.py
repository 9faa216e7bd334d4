"""The corpus pipeline: five stages, each over all that the one before kept, written between.

Quality rules, SimHash near-dedup, removal of repeated passages, mixing of sources, packing. All but the last return the columns
of the documents; the last returns the pieces with their sequences. A document that is mixed in twice is two rows
of one id from there on. Empty tables go through; nulls are as each operator defines them."""

from __future__ import annotations

from collections.abc import Callable

from pathtraces.llm import mixing, packing, quality, simhash, substrings
from pathtraces.llm.common import spill
from pathtraces.llm.queries import tokenizer_path
from pyspark.sql import DataFrame, SparkSession

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality.quality_filter(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, as operator 6 defines them, the document of the smallest id stays."""
    return simhash.simhash_dedup(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of fifty words or more that an earlier document holds go; so do documents of which nothing is left."""
    return substrings.without_passages(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are repeated or cut to their targets."""
    return mixing.mixed(docs)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces and their places."""
    return packing.packed(docs, tokenizer_path("byte_bpe_50k.json"), cache_bytes=12 << 20)


STAGES: list[tuple[str, Stage]] = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("source_mix", source_mix),
    ("sequences", sequences),
]

#: Tokens and divergence are beyond SQL; the tests run plain versions of the stages.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = spill(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
