"""Weighted rendezvous hashing of stable record keys, with gapless places inside each shard.

A record goes to the shard with the largest score ``-weight / ln(u)``, ``u`` being a hash of the
record's key and the shard's number in (0, 1). The score of one pair depends on nothing else, so
one more shard takes rows only into itself, and a change of a weight moves rows only to or from
that shard.

Places (``slot``) are numbered in two levels: each shard is divided into buckets by a hash of the
row, buckets are counted, and a row's slot is its bucket's first slot plus its rank in the bucket.
So no task ever holds a whole shard. The counts are ``shards * buckets`` rows, a number set by
parameters, and are broadcast.

Defined results: a null text has no bytes; null keys all go to the shard of the null key; rows that
repeat are numbered one after another; columns beyond ``doc_id`` and ``text`` are ignored; an empty
table gives an empty result. Of a very long text only its bytes are counted and hashed.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unischema.llm.common import cut, read_table

SHARDS = 40
#: Bytes that each record needs beside its text.
RECORD_BYTES = 16


def score(key: Column, shard: Column, weight: Column) -> Column:
    """The rendezvous score; 53 bits of the hash give ``u`` strictly between 0 and 1."""
    u = (F.shiftrightunsigned(F.xxhash64(key, shard), 11).cast("double") + F.lit(0.5)) / F.lit(float(1 << 53))
    return -weight / F.ln(u)


def best_shard(key: Column, weights: Sequence[float]) -> Column:
    """``struct(score, shard)`` of the winning shard; equal scores go to the smaller number."""
    options = [F.struct(score(key, F.lit(s), F.lit(float(w))).alias("score"), F.lit(-s).alias("minus")) for s, w in enumerate(weights) if w > 0]
    return F.greatest(*options) if len(options) > 1 else options[0]


def shard_of(key: Column, weights: Sequence[float]) -> Column:
    return -best_shard(key, weights)["minus"]


def rendezvous_shards(docs: DataFrame, weights: Sequence[float], grown_weight: float = 1.0, buckets: int = 64) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` for each row of ``docs``."""
    text = F.coalesce(F.col("text"), F.lit(""))
    more = len(weights)
    rows = docs.select(
        "doc_id",
        (F.octet_length(text) + RECORD_BYTES).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
    )
    extra = F.struct(score(F.col("doc_id"), F.lit(more), F.lit(float(grown_weight))).alias("score"), F.lit(-more).alias("minus"))
    placed = (
        rows.withColumn("best", best_shard(F.col("doc_id"), weights))
        .withColumn("grown_shard", -F.greatest(F.col("best"), extra)["minus"])
        .withColumn("shard", -F.col("best")["minus"])
        .withColumn("bucket", F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(buckets)).cast("int"))
        .drop("best")
    )
    placed = cut(placed)
    counts = placed.groupBy("shard", "bucket").agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = counts.select("shard", "bucket", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("first"))
    inside = Window.partitionBy("shard", "bucket").orderBy("doc_id", "size", "text_crc32")
    return (
        placed.withColumn("rank", F.row_number().over(inside))
        .join(F.broadcast(first), ["shard", "bucket"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("key").alias("law"),
            "shard",
            (F.col("first") + F.col("rank") - 1).alias("slot"),
            "grown_shard",
        )
    )


def op8_rendezvous_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rendezvous_shards(read_table(spark, sf_dir, "documents"), [1.0] * SHARDS)
