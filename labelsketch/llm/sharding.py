"""Rendezvous hashing of stable record keys over weighted shards (law ``key``).

Each key draws a number for every shard and goes to the largest weighted draw, so one more shard takes rows only into
itself. Slots number the rows of a shard without gaps: rows are dealt into sub-buckets by a hash, numbered inside them, and
the sub-buckets' counts (one small row each) give the offsets, so no shard is sorted in one task.

Null texts have size 1 and checksum 0, a null key hashes like the empty string. Very long texts are only measured.
Repeated rows get slots of their own, extra columns are ignored, an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows of a sub-bucket on average.
BUCKET_ROWS = 2000


def draw(key: Column, shard: int) -> Column:
    """A number in (0, 1) from key and shard: 52 bits of a hash of both."""
    h = F.shiftrightunsigned(F.xxhash64(F.coalesce(key.cast("string"), F.lit("")), F.lit(f"shard-{shard}")), 12)
    return (h.cast("double") + 0.5) / float(1 << 52)


def rendezvous(key: Column, weights: list[float]) -> Column:
    """The shard of a key: largest weight / -log(draw); the lower shard on a tie."""
    scores = [F.struct((F.lit(-float(w)) / F.log(draw(key, i))).alias("score"), F.lit(-i).alias("minus")) for i, w in enumerate(weights)]
    best = scores[0] if len(scores) == 1 else F.greatest(*scores)
    return (-best["minus"]).cast("int")


def sharded(docs: DataFrame, weights: list[float], added: float = 1.0) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard (the shard if one of weight ``added`` is added)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    key = F.col("doc_id")
    rows = docs.select(
        "doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.lit("key").alias("law"),
        rendezvous(key, weights).alias("shard"), rendezvous(key, [*weights, added]).alias("grown_shard"),
    )
    n = docs.count()
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(max(1, n // (BUCKET_ROWS * len(weights))))))
    counts = rows.groupBy("shard", "bucket").count()
    # A few bytes per BUCKET_ROWS rows; one task sums the counts of a shard.
    before = counts.select("shard", "bucket", (F.sum("count").over(Window.partitionBy("shard").orderBy("bucket")) - F.col("count")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("shard", "bucket").orderBy("doc_id", "size", "text_crc32")) - 1
    placed = rows.withColumn("inside", inside).join(before, ["shard", "bucket"])
    return placed.select("doc_id", "size", "text_crc32", "law", "shard", (F.col("before") + F.col("inside")).cast("long").alias("slot"), "grown_shard")


def write_shards(docs: DataFrame, weights: list[float], path: str) -> None:
    """The documents as Parquet, one folder per shard."""
    docs.withColumn("__shard", rendezvous(F.col("doc_id"), weights)).write.partitionBy("__shard").parquet(path)
