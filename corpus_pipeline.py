"""From raw documents to token ids: quality, near-duplicates, repeated passages, benchmark leaks, encoding.

Each stage takes all that its predecessor kept and returns the columns of documents; the last adds token ids. run()
writes every stage as Parquet in the shared folder and reads it again, so a lost executor repeats one stage at most.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sparsewire.llm import byte_bpe, decontaminate, rule_ensemble, simhash_dedup, suffix_dedup
from sparsewire.llm.common import fresh_dir, table


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the rule ensemble, fitted on labelled rows of docs, predicts bad."""
    return rule_ensemble.keep_good(docs, table(spark, sf_dir, "labels"))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each near-duplicate group."""
    return simhash_dedup.keep_one(docs)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts the strings of 50 bytes out of texts that a document with a smaller id has as well."""
    return suffix_dedup.without_repeats(docs)


def without_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents with a window like a benchmark item."""
    return decontaminate.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds ids and n_tokens; text is what the ids decode to."""
    return byte_bpe.round_trip(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", good_quality),
    ("near_duplicates", one_of_each),
    ("repeated_passages", without_repeats),
    ("benchmark_leaks", without_leaks),
    ("byte_bpe", encoded),
]

#: SQL has neither the fitted score nor the encoder; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, folder = table(spark, sf_dir, "documents"), fresh_dir(spark, "pipeline")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
