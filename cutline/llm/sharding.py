"""Weighted rendezvous sharding: the shard with the best draw for a record's stable key owns the record.

Each pair of key and shard has a draw u in (0, 1) from the first 48 bits of an md5. The owner is the shard
with the least -ln(u) / weight, so a shard gets rows in proportion to its weight; adding a shard moves only
the rows that the new shard wins, and removing one moves only its own rows. All of it is one projection in
the JVM: no shuffle, no state, and the same answer wherever and whenever it is computed (Spark's ln is strict).

Defined results: a null key is a key of its own; equal keys share a shard; an empty table gives an empty
result; columns of the input that clash with the added names are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import numbered, table, text_key

DRAW_BITS = 48


def cost(key: Column, shard: Column, weight: Column) -> Column:
    """-ln(draw) / weight for a key and a shard."""
    draw = F.conv(F.substring(F.md5(F.concat(key, F.lit(":"), shard.cast("string"))), 1, DRAW_BITS // 4), 16, 10).cast("double")
    return -F.log((draw + 0.5) / float(2**DRAW_BITS)) / weight


def owner(key: Column, weights: list[float]) -> Column:
    """The owning shard (0 .. len(weights) - 1) of a key; shards of weight 0 own nothing."""
    if not any(w > 0 for w in weights):
        raise ValueError("some shard must have a positive weight")
    draws = [F.struct(cost(key, F.lit(s), F.lit(float(w))).alias("c"), F.lit(s).alias("s")) for s, w in enumerate(weights) if w > 0]
    return F.array_min(F.array(*draws))["s"]


def shard_records(df: DataFrame, key: str, weights: list[float], name: str = "shard") -> DataFrame:
    """df with the owning shard of each row's key."""
    return df.withColumn(name, owner(text_key(F.col(key)), weights))


def reshard(df: DataFrame, key: str, before: list[float], after: list[float]) -> DataFrame:
    """df with the shards under two sets of weights, and whether a row moves."""
    both = df.withColumn("shard_before", owner(text_key(F.col(key)), before)).withColumn("shard_after", owner(text_key(F.col(key)), after))
    return both.withColumn("moves", F.col("shard_before") != F.col("shard_after"))


def write_shards(df: DataFrame, key: str, weights: list[float], path: str, files_per_shard: int = 8) -> None:
    """Writes df as one folder per shard. A shard's rows go to files_per_shard tasks, so no shard is one task."""
    spread = F.pmod(F.xxhash64(text_key(F.col(key))), F.lit(files_per_shard))
    sharded = shard_records(df, key, weights)
    sharded.repartition(len(weights) * files_per_shard, "shard", spread).write.partitionBy("shard").mode("overwrite").parquet(path)


def op2_rendezvous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 equal shards by doc_id, each row's place in its shard, and its shard among 25."""
    n = 24
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    raw = F.encode(F.col("text"), "UTF-8")
    sized = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.coalesce(raw, F.encode(F.lit(""), "UTF-8"))).cast("long").alias("text_crc32"),
    )
    placed = shard_records(shard_records(sized, "doc_id", [1.0] * n), "doc_id", [1.0] * (n + 1), "grown_shard")
    slotted = numbered(placed, ["shard"], ["doc_id", "size", "text_crc32"], "slot")
    return slotted.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
