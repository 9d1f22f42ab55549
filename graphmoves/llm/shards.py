"""Sharding by jump consistent hashing: no ring table; one more shard takes rows only into itself.

Only DataFrame functions. A key's chain of jumps is a pure function of the key; shard counts n and
n + 1 read the same chain, so both come from one walk.
Edge cases: a null key is one key of its own; null text has size `overhead`; equal rows get
neighbouring slots; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TWO31 = 2**31


def _digits(text: Column, start: int) -> Column:
    """Eight hex digits of an md5, as a number."""
    return F.conv(F.substring(F.md5(text), start, 8), 16, 10).cast("long")


def jump(key: Column, shards: int) -> Column:
    """struct(b, j): b is the key's shard of `shards`; j, the next stop, is `shards` itself if a further shard would take the key."""
    def step(s, i):
        draw = F.floor(_digits(F.concat_ws(":", key, i.cast("string")), 1) / 2).cast("long") + 1
        there = F.floor((s["j"] + 1) * F.lit(TWO31).cast("decimal(20,0)") / draw).cast("long")
        return F.when(s["j"] < shards, F.struct(s["j"].alias("b"), there.alias("j"))).otherwise(s)

    start = F.struct(F.lit(-1).cast("long").alias("b"), F.lit(0).cast("long").alias("j"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(shards)), start, step)


def shard_documents(docs: DataFrame, shards: int = 40, overhead: int = 16, buckets: int = 1024) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row.

    Slots are gapless within a shard: a row's rank within (shard, bucket) plus the sizes of the
    buckets before it. So no task sorts a whole shard, and what is broadcast has at most
    shards * buckets rows.
    """
    raw = F.encode(F.coalesce("text", F.lit("")), "utf-8")
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))
    rows = docs.select("doc_id", (F.octet_length(F.coalesce("text", F.lit(""))).cast("long") + overhead).alias("size"),
                       F.crc32(raw).alias("text_crc32"), key.alias("_key"))
    rows = rows.withColumn("_jump", jump(F.col("_key"), shards))
    rows = rows.select("doc_id", "size", "text_crc32", F.col("_jump.b").cast("int").alias("shard"),
                       F.when(F.col("_jump.j") == shards, shards).otherwise(F.col("_jump.b")).cast("int").alias("grown_shard"),
                       ((_digits(F.col("_key"), 9) + F.col("text_crc32")) % buckets).alias("_bucket"))
    counts = rows.groupBy("shard", "_bucket").agg(F.count("*").alias("_n"))
    before = Window.partitionBy("shard").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("shard", "_bucket", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    within = Window.partitionBy("shard", "_bucket").orderBy("doc_id", "text_crc32", "size")
    ranked = rows.withColumn("_rank", F.row_number().over(within) - 1)
    return ranked.join(F.broadcast(starts), ["shard", "_bucket"]).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard",
        (F.col("_start") + F.col("_rank")).cast("long").alias("slot"), "grown_shard")
