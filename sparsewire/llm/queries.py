"""Queries of the training-data operators, and the SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import byte_bpe, chat_format, decontaminate, hash_forest, html_wrapper, rule_ensemble, shard_store, simhash_dedup, suffix_dedup, warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_decontamination": decontaminate.op1_decontamination,
    "op2_suffix_array_dedup": suffix_dedup.op2_suffix_array_dedup,
    "op3_byte_bpe": byte_bpe.op3_byte_bpe,
    "op4_html_wrapper": html_wrapper.op4_html_wrapper,
    "op5_warc": warc.op5_warc,
    "op6_hash_forest": hash_forest.op6_hash_forest,
    "op7_chat_format": chat_format.op7_chat_format,
    "op8_size_tiered_shards": shard_store.op8_size_tiered_shards,
    "op9_simhash_near_dedup": simhash_dedup.op9_simhash_near_dedup,
    "op10_rule_ensemble_quality": rule_ensemble.op10_rule_ensemble_quality,
}

ORACLE_SQL: dict[str, str] = {"op5_warc": warc.OP5_SQL, "op7_chat_format": chat_format.OP7_SQL, "op8_size_tiered_shards": shard_store.OP8_SQL}
