"""The corpus pipeline: stages over ``documents``, each one of the training-data operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from edgesketch.llm import decontam, jaccard, packing, quality_rules, suffix_dedup
from edgesketch.llm.common import delete_path, scratch_path, scratch_scope, shuffles_released, table

#: Bytes of a repeated passage that the corpus is cleaned of: less than 50 words of any usual length.
PASSAGE_BYTES = 200


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the quality rules reject, and lines that a source repeats."""
    return quality_rules.apply(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group that word 5-shingles link at a Jaccard similarity of 0.8."""
    return jaccard.keep_one(docs, width=5, percent=80)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes passages that occur more than once."""
    return suffix_dedup.apply(docs, length=PASSAGE_BYTES)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes the words of benchmark items, or the document if they are most of it."""
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into training sequences."""
    return packing.pack_documents(docs)


STAGES = [
    ("quality rules", rules),
    ("n-gram jaccard join", near_duplicates),
    ("suffix-array dedup", repeated_passages),
    ("benchmark decontamination", benchmark_passages),
    ("best-fit packing", sequences),
]

#: Greedy packing and the removal of repeated bytes are beyond SQL; tests hold the run against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages in order; each result is written as Parquet and read again, and what it was made of goes."""
    docs, before = table(spark, sf_dir, "documents"), None
    for k, (name, stage) in enumerate(STAGES[:-1]):
        with scratch_scope(spark), shuffles_released(spark):
            path = scratch_path(spark, f"stage-{k}", outer=1)
            stage(spark, docs, sf_dir).write.parquet(path)
        if before is not None:
            delete_path(spark, before)
        docs, before = spark.read.parquet(path), path
    return STAGES[-1][1](spark, docs, sf_dir)
