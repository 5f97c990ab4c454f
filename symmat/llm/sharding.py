"""Sharding by rendezvous hashing of stable record keys over weighted shards (DataFrame functions only).

Every (key, shard) pair gets a score from a hash of both and the shard's weight; the key goes to the shard of the best
score. Another shard only adds a competitor: a key stays or moves to the new shard. Nothing is shuffled for that; only
the gapless slots need a shuffle of narrow rows: a range sort by shard and key, whose partitions are numbered on their own
and set off by counts, so neither a shard nor the rows of one key are ever one task.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._common import cut

SHARDS = 16


def rendezvous(key: Column, weights: Sequence[float]) -> Column:
    """The shard (0-based) of ``key`` among shards of the given positive weights: the largest -weight / ln(u), ties to the smaller shard."""
    def score(shard: int, weight: float) -> Column:
        u = (F.shiftrightunsigned(F.xxhash64(key, F.lit(shard)), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
        return F.struct((-F.lit(float(weight)) / F.log(u)).alias("score"), F.lit(-shard).alias("shard"))

    scores = [score(i, w) for i, w in enumerate(weights)]
    best = F.greatest(*scores) if len(scores) > 1 else scores[0]
    return (-best["shard"]).cast("int")


def assign(docs: DataFrame, weights: Sequence[float] = (1.0,) * SHARDS, grown: float = 1.0) -> DataFrame:
    """A row per row of ``docs`` (doc_id, text): doc_id, size, text_crc32, law, shard, slot, grown_shard.

    size: UTF-8 bytes of the text plus 1 (null: 1); text_crc32 of a null text is that of an empty one. doc_id and the
    shards alone decide the shard; grown_shard is the shard when one of weight ``grown`` is added. A null doc_id is a key
    like others. Slots of a shard run from 0 without a gap; rows that repeat a doc_id get slots next to each other.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))
    base = docs.select(
        "doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).cast("long").alias("text_crc32"),
        rendezvous(key, weights).alias("shard"), rendezvous(key, [*weights, grown]).alias("grown_shard"), F.xxhash64(key, F.lit("slot")).alias("__h"),
    )
    # numbers of the checkpointed rows part equal rows; a slot is a row's rank in its shard, however the sort is dealt
    base = cut(base).withColumn("__row", F.monotonically_increasing_id())
    lined = cut(base.orderBy("shard", "__h", "doc_id", "text_crc32", "__row").withColumn("__at", F.monotonically_increasing_id())).withColumn("__part", F.shiftright("__at", 33))
    counts = lined.groupBy("shard", "__part").agg(F.min("__at").alias("first"), F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    out = lined.join(F.broadcast(counts.select("shard", "__part", (F.col("first") - before).alias("from"))), ["shard", "__part"])  # at most a row per partition and shard
    return out.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("__at") - F.col("from")).cast("long").alias("slot"), "grown_shard")
