"""The corpus pipeline: quality, exact copies, near copies, benchmark passages, then token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ownerdp.llm import bpe, decontaminate, exact_dedup, quality, simhash
from ownerdp.llm.common import materialise, table
from ownerdp.llm.queries import byte_vocabulary, split_pattern


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble rejects go; it learns from the labelled documents of its own input.

    Each text is judged alone, null as empty, so repeated rows go or stay together. Without labelled documents all stay."""
    return quality.keep_good(docs, quality.fit_quality(docs, table(spark, sf_dir, "labels")))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the largest doc_id stays; null is equal to empty, a null doc_id below all others, and of rows that repeat
    both doc_id and text one stays."""
    return exact_dedup.drop_exact_duplicates(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, five-word shingles at a similarity of 0.8 or more, the smallest doc_id stays; null and empty texts all stay."""
    return simhash.drop_near_duplicates(docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of a benchmark item go, and all rows that share their doc_id; null and empty texts hold none."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The byte-level BPE ids of each document, with digests of the ids and of what they decode to; null and empty texts have no ids.

    In every stage an empty table gives an empty result, and columns beside doc_id and text may have any names."""
    return bpe.encode_documents(docs, byte_vocabulary(), split_pattern())


STAGES = [("quality", quality_stage), ("exact", exact_stage), ("near", near_stage), ("benchmark", benchmark_stage), ("tokens", token_stage)]

#: Neither the rule ensemble nor the components of near copies can be written in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        docs = out if name == STAGES[-1][0] else materialise(out, f"pipeline-{name}")
    return docs
