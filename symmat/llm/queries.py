"""Queries of the corpus operators, each over its whole table with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import ann, chat, embed_dedup, mixing, near_dup, packing, secrets, sharding, toxicity, url_filter
from ._common import table


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document; empty texts are linked with nothing, rows without a doc_id are kept, an empty table gives no rows."""
    return near_dup.near_duplicates(table(spark, sf_dir, "documents"))


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_entropy of every document; a null text counts as empty."""
    return secrets.scan(table(spark, sf_dir, "documents"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, host, path, rule, verdict, score of every page; a null url has an empty host and path."""
    return url_filter.judge(table(spark, sf_dir, "pages"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted, n_sentences, worst_at of every document; a text without words scores 0."""
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op5_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken of every document; a null source is one of its own, a null text has size 0."""
    return mixing.mix(table(spark, sf_dir, "documents")).drop("times")


def op6_graph_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    """query_id, rank, vec_id, score of the five nearest of every query; unusable vectors take no part."""
    return ann.search(table(spark, sf_dir, "embeddings"))


def op7_rendezvous_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every document; a null doc_id is a key like others."""
    return sharding.assign(table(spark, sf_dir, "documents"))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conv_id, turn, position, role, line, n_calls, n_linked, n_invalid, orphan of every turn; rows without a conv_id are one conversation."""
    return chat.format_chat(table(spark, sf_dir, "conversations"))


def op9_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, n_links, component_id, kept of every vector; unusable vectors are linked with nothing."""
    return embed_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset of every piece; an empty text is its end id alone."""
    return packing.pack(table(spark, sf_dir, "documents"))


_ALL = (op1_minhash_near_dedup, op2_secret_scan, op3_url_filter, op4_toxicity, op5_mix_sources, op6_graph_ann, op7_rendezvous_sharding, op8_chat_format, op9_embedding_near_dedup, op10_packing)


def queries() -> dict:
    return {f.__name__: f for f in _ALL}


def oracle_sql() -> dict:
    return {"op1_minhash_near_dedup": near_dup.ORACLE, "op5_mix_sources": mixing.ORACLE, "op8_chat_format": chat.ORACLE, "op9_embedding_near_dedup": embed_dedup.ORACLE}
