"""The corpus pipeline: stages over documents, each written as Parquet and read again.

Quality rules drop documents, the n-gram join leaves one document of each group, suffix-array
deduplication cuts later copies of long strings, mixing repeats or leaves out documents until
every source has its share, and packing gives the token sequences.

Nulls and edge cases: a null or empty text fails the first stage's base rule; a null doc_id is a
document of its own, and of a group of near-duplicates the last one; rows that share a doc_id go
or stay together where a stage decides by id (quality, near-duplicates) and are apart where it
doesn't; columns beside those used pass through all stages but the last; empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wfpath.llm import mixing, ngram_join, packing, quality_rules, shared, suffix_dedup


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the risk-controlled rules keep."""
    return quality_rules.filtered(docs, shared.load(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents linked by their shingles, the one with the smallest id."""
    return ngram_join.first_of_each(docs)


def repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later copies of strings of 200 bytes; the first copy stays."""
    return suffix_dedup.deduplicated(docs, keep_first=True)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, whole."""
    return mixing.mixed(docs, whole=True)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents' ids and the sequence that each is packed in."""
    return packing.packed(docs.select("doc_id", "text"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("repeated_strings", repeated_strings), ("mix", mix), ("pack", pack)]
#: No SQL: calibrated cutoffs, suffix order and the packing program are beyond it.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written as Parquet and read again."""
    docs = shared.load(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = shared.materialised(docs)
    return docs
