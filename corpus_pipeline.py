"""A corpus pipeline in five stages over the documents table.

Each stage takes (spark, docs, sf_dir) with docs read from files and works on all rows its predecessor
kept. All but the last return the columns of documents; the last returns the encoded documents.
Exact dedup keeps the row op8 keeps. The near-duplicate stage keeps the document with the smallest id of
each component. Mixing repeats or drops whole documents as often as the words taken from them, rounded,
are their size. Rows with a null doc_id pass the deduplication stages as documents of their own unless
their text is that of another row; among near-duplicates they stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from steadysketch.llm import bpe, exact_dedup, mixing, quality, simhash
from steadysketch.llm.common import table
from steadysketch.llm.queries import public_file
from steadysketch.runtime import materialise


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the quality classifier rejects."""
    return quality.accepted(docs, table(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group of equal texts."""
    return exact_dedup.keep_first(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near-duplicates."""
    return simhash.keep_one(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats and drops documents so that the sources come to their target weights."""
    return mixing.mixed_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, with the round trip's digest."""
    path, pattern = public_file("byte_bpe_50k.tiktoken")
    return bpe.encode_documents(docs, path, pattern, with_ids=True)


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("simhash near-dedup", near_stage),
    ("mixing to target weights", mixing_stage),
    ("byte-level bpe", encoding_stage),
]

#: No SQL: perplexities, fingerprints of 64-bit hashes and merges have none; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), "stage")
    return STAGES[-1][1](spark, docs, sf_dir)
