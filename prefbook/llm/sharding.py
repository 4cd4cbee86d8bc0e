"""Rendezvous hashing of stable record keys over weighted shards.

A record goes to the shard with the highest score, -weight / ln(u), where u is a uniform
number made of the record key and the shard's name. A shard that is added takes records
only into itself, and one that is taken away gives up only its own; a shard's share is its
weight. Places within a shard are counted from sizes of key buckets and a rank within each
bucket, so no task holds a shard.

Edge cases: a null text has no bytes; a null key is a key of its own, the empty string.
Rows with equal keys go to one shard, whatever their texts; their places are counted by the
partitions that they come from, so that one task doesn't rank them all. Extra columns don't matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import column, settle


def uniform(*parts: Column | str) -> Column:
    """Uniform in (0, 1) from the first 13 hex digits of an md5, exact in a double."""
    columns = [F.lit(x) if isinstance(x, str) else x for x in parts]
    digits = F.conv(F.substring(F.md5(F.concat_ws("|", *columns)), 1, 13), 16, 10).cast("double")
    return (digits + 0.5) / float(1 << 52)


def rendezvous(key: Column, weights: dict[int, float]) -> Column:
    """The shard of a key; all scores are one codegen expression."""
    scores = [F.struct((F.lit(-float(w)) / F.ln(uniform(key, str(shard)))).alias("score"), F.lit(-shard).alias("shard")) for shard, w in sorted(weights.items()) if w > 0]
    best = F.greatest(*scores) if len(scores) > 1 else scores[0]
    return (-best["shard"]).cast("int")


def shard_documents(docs: DataFrame, shards: int = 24, weights: dict[int, float] | None = None, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """id, size, text_crc32, law, shard, slot, and grown_shard: the shard if there were one shard more, of mean weight."""
    held = weights or dict.fromkeys(range(shards), 1.0)
    grown = held | {max(held) + 1: sum(held.values()) / len(held)}
    key = F.coalesce(column(id_column).cast("string"), F.lit(""))
    text = F.coalesce(column(text_column), F.lit(""))
    rows = docs.select(
        column(id_column).alias("id"),
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
        rendezvous(key, held).alias("shard"),
        F.pmod(F.xxhash64(key, F.spark_partition_id()), F.lit(4096)).cast("int").alias("bucket"),
        key.alias("key"),
    )
    added = max(grown)
    beats = F.lit(-float(grown[added])) / F.ln(uniform(F.col("key"), str(added)))
    mine = F.lit(-1.0)
    for shard, w in sorted(held.items(), reverse=True):
        mine = F.when(F.col("shard") == shard, F.lit(-float(w)) / F.ln(uniform(F.col("key"), str(shard)))).otherwise(mine)
    rows = rows.withColumn("grown_shard", F.when(beats > mine, F.lit(added)).otherwise(F.col("shard")).cast("int"))
    rows = settle(rows)
    sizes = rows.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(F.col("shard").alias("s"), F.col("bucket").alias("b"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    within = Window.partitionBy("shard", "bucket").orderBy("key", "text_crc32", "size")
    placed = rows.withColumn("at", F.row_number().over(within) - 1).join(starts, (F.col("shard") == F.col("s")) & (F.col("bucket") == F.col("b")))
    return placed.select(F.col("id").alias(id_column), "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("start") + F.col("at")).cast("long").alias("slot"), "grown_shard")
