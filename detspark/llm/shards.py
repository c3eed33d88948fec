"""Rendezvous hashing of stable record keys over weighted shards."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: parts of a shard that are numbered on their own; the table of their sizes has shards x BUCKETS rows
BUCKETS = 1024


def choose(key: Column, weights: Sequence[float], seed: int = 7) -> Column:
    """Shard of a key: every shard draws an exponential with rate = its weight from (key, shard), the smallest draw wins.

    A shard's draw does not depend on the others, so a new shard takes records only into itself and a removed one gives
    up only its own.  A null key is a key like any other.
    """
    draws = []
    for shard, weight in enumerate(weights):
        if not weight > 0:
            continue
        bits = F.shiftrightunsigned(F.xxhash64(key, F.lit(shard), F.lit(seed)), 11).cast("double")
        draws.append(F.struct((-F.log((bits + 0.5) / float(1 << 53)) / float(weight)).alias("d"), F.lit(shard).alias("s")))
    if not draws:
        raise ValueError("no shard has a positive weight")
    return (F.least(*draws) if len(draws) > 1 else draws[0])["s"]


def numbered(frame: DataFrame, shard: str, order: Sequence[Column], bucket: Column, out: str = "slot") -> DataFrame:
    """Number the rows of each shard from 0 without a gap.  Buckets of a shard are numbered in parallel and then offset."""
    placed = frame.withColumn("_b", F.pmod(bucket, F.lit(BUCKETS)).cast("int"))
    sizes = placed.groupBy(shard, "_b").agg(F.count("*").alias("_n"))
    before = F.sum("_n").over(Window.partitionBy(shard).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select(F.col(shard).alias("_s"), F.col("_b").alias("_k"), F.coalesce(before, F.lit(0)).alias("_o"))
    local = F.row_number().over(Window.partitionBy(shard, "_b").orderBy(*order)) - 1
    ranked = placed.withColumn("_r", local)
    joined = ranked.join(F.broadcast(offsets), (F.col(shard) == F.col("_s")) & (F.col("_b") == F.col("_k")))
    return joined.withColumn(out, (F.col("_o") + F.col("_r")).cast("long")).drop("_b", "_s", "_k", "_o", "_r")


def op5_shards(spark, sf_dir: str, shards: int = 8) -> DataFrame:
    """``documents`` over ``shards`` equal shards by the law ``key``.  A null text has size 1 and the checksum of no bytes; null ids are one key; rows that
    repeat an id share its shard, each with a slot; an empty table gives no rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    placed = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1).alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        F.lit("key").alias("law"),
        choose(F.col("doc_id"), [1.0] * shards).alias("shard"),
        choose(F.col("doc_id"), [1.0] * (shards + 1)).alias("grown_shard"),
    )
    order = [F.col("doc_id"), F.col("size"), F.col("text_crc32")]
    out = numbered(placed, "shard", order, F.xxhash64("doc_id", F.lit("bucket")))
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
