"""Corpus preparation: the stages in order, each over all its predecessor kept.

toxicity drops documents that score as toxic; near-dedup keeps one document of each group; the secret scan masks what it
finds in the text; mixing repeats or leaves out documents to meet the sources' targets; packing lays the tokens out.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from symmat.llm import mixing, near_dup, packing, secrets, toxicity

#: Near copies, on shingles of five words, are as similar as this or more.
SIMILAR_PERCENT = 80


def _toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score as toxic go; a text without words stays. The model learns from labels.parquet; without labels nothing goes."""
    weights = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.drop_toxic(docs, weights)


def _near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, the one of smallest doc_id; rows equal in id and words become one. Rows without words or id stay."""
    return near_dup.drop_near_duplicates(docs, SIMILAR_PERCENT)


def _secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Found secrets are masked in the text and n_chars follows it, where it is not null; all rows stay."""
    return secrets.redact(docs).withColumn("n_chars", F.when(F.col("n_chars").isNotNull(), F.length("text").cast("long")))


def _mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows are repeated or left out to meet the sources' targets; rows without words stay once."""
    return mixing.resample(docs)


def _packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The tokens of all rows, in pieces (see packing.pack); the last stage, whose columns are its own."""
    return packing.pack(docs)


STAGES = [("toxicity", _toxicity), ("minhash_near_dedup", _near_dedup), ("secret_scan", _secrets), ("mix_sources", _mixing), ("packing", _packing)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over documents.parquet. An empty table gives no rows; other columns than those of documents pass through all but the last."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs
