"""From raw documents to packed training sequences: five stages, each one operator of the ``llm`` subpackage.

Every stage takes all that its predecessor kept, written as Parquet and read again. The first four return the columns of
``documents``; the last returns one row per packed piece.

Nulls and edges: a null or empty text has too few words and goes in the first stage, so does every document of under 20 words; a
null doc_id is kept by the second stage and unchanged by the third; columns beyond doc_id and text pass through; repeated
rows are copies of one document and are kept or dropped together; empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from affinity_graph.llm import bin_packing, near_dedup, quality_rules, secret_scan, substring_dedup
from affinity_graph.llm.common import load, public_path, stored
from affinity_graph.llm.token_output import TOKENIZER


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Failing lines go, then documents that fail the base rules or have lost too much."""
    return quality_rules.clean(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: 5-word shingles, similarity 0.8 or more."""
    return near_dedup.deduplicated(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words of passages that a document with a smaller id has too are removed; every document stays."""
    return substring_dedup.deduplicated(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; every document stays."""
    return secret_scan.redact(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Tokenized, cut and packed into sequences of at most 4096 tokens."""
    return bin_packing.pack(docs, public_path(TOKENIZER))


STAGES = [
    ("quality rules", quality),
    ("near duplicates", near_duplicates),
    ("repeated passages", repeated_passages),
    ("secret scan", secrets),
    ("best-fit packing", packing),
]

#: Tokenization cannot be said in SQL; tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, f"stage-{k}")
    return docs
