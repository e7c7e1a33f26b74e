"""Queries of the corpus operators and their SQL, where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat, decontaminate, lm_scoring, ngram_join, packing, pii, sharding, suffix_dedup, topk_search, toxicity
from .common import table

Query = Callable[[SparkSession, str], DataFrame]


def op1_weak_supervision_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score_documents(spark, table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"))


def op2_length_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(spark, table(spark, sf_dir, "documents").select("doc_id", "text"))


def op3_repeated_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.dedup(spark, table(spark, sf_dir, "documents"))


def op4_contained_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark")
    return decontaminate.contained_items(spark, docs, items)


def op5_cover_tree_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(spark, table(spark, sf_dir, "embeddings"))


def op6_private_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.report(spark, table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_shingle_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_components(spark, table(spark, sf_dir, "documents"))


def op8_prefix_target_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return chat.digest(chat.format_conversations(rows.unionByName(chat.control_conversation(spark))))


def op9_jump_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op10_log_bilinear_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score_texts(spark, table(spark, sf_dir, "documents").select("doc_id", "text"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_weak_supervision_toxicity, op2_length_buckets, op3_repeated_bytes, op4_contained_items, op5_cover_tree_top_k, op6_private_spans, op7_shingle_components, op8_prefix_target_chat, op9_jump_shards, op10_log_bilinear_scores, pipeline)}


def oracle_sql() -> dict[str, str]:
    return {"op4_contained_items": decontaminate.ORACLE, "op5_cover_tree_top_k": topk_search.ORACLE, "op7_shingle_components": ngram_join.ORACLE, "op8_prefix_target_chat": chat.ORACLE}
