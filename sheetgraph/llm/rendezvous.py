"""Sharding by weighted rendezvous hashing of stable record keys.

Every (key, shard) pair gets a uniform number u from a 64-bit hash; the shard with the smallest
-ln(u) / weight holds the key. A shard is so chosen with a chance in proportion to its weight, and a
further shard only takes keys for itself: the others' numbers do not change.

All of it is column expressions: a fixed fold over the shards, no join. Slots (the gapless order inside
each shard) are numbered in two levels, rows inside a hash bucket of a shard and buckets inside the
shard, so that no task holds a shard as a whole.

Defined results: a null key hashes like any other value; equal keys share a shard and get slots of their
own; null text has size 8 and the checksum of no bytes; an empty table gives an empty table; other columns
of the input are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Bytes counted for each record besides its text.
RECORD_OVERHEAD = 8
#: Rows that a task numbers at a time, on average.
BUCKET_ROWS = 2_000_000


def _cost(key: F.Column, shard: int, weight: float) -> F.Column:
    h = F.shiftrightunsigned(F.xxhash64(key, F.lit(shard)), 11).cast("double")
    return -F.log((h + 0.5) / float(2**53)) / F.lit(float(weight))


def _winner(key: F.Column, weights: list[float]) -> F.Column:
    costs = [F.struct(_cost(key, i, w).alias("cost"), F.lit(i).alias("shard")) for i, w in enumerate(weights)]
    return F.array_min(F.array(*costs)).getField("shard")


def assign(docs: DataFrame, weights: list[float], new_weight: float = 1.0, key: str = "doc_id", text: str = "text", buckets: int | None = None) -> DataFrame:
    """One row per record: key, size, text_crc32, law, shard, slot, grown_shard.

    weights: one per shard, all above 0. new_weight: of the shard that grown_shard adds.
    buckets: slot numbering works on shards * buckets parts, and the offsets table has that many rows; by
    default so many that a part has some BUCKET_ROWS rows, and 64 at least.
    """
    if not weights or min(weights) <= 0 or new_weight <= 0:
        raise ValueError("shard weights must be above 0")
    if buckets is None:
        buckets = max(64, -(-docs.count() // (len(weights) * BUCKET_ROWS)))
    body = F.coalesce(F.encode(F.col(text), "UTF-8"), F.lit(b""))
    rows = docs.select(
        F.col(key).alias("doc_id"),
        (F.octet_length(body) + F.lit(RECORD_OVERHEAD)).cast("long").alias("size"),
        F.crc32(body).cast("long").alias("text_crc32"),
    )
    rows = rows.withColumn("shard", _winner(F.col("doc_id"), weights)).withColumn("grown_shard", _winner(F.col("doc_id"), [*weights, new_weight]))
    rows = rows.withColumn("part", F.pmod(F.xxhash64("doc_id", "size", "text_crc32", F.lit("slot")), F.lit(buckets)).cast("int"))
    # shards * buckets rows at most: 64 a shard, or one for BUCKET_ROWS rows
    sizes = rows.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("shard", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("shard", "part").orderBy("doc_id", "size", "text_crc32")
    ranked = rows.withColumn("rank", F.row_number().over(inside) - 1)
    return ranked.join(F.broadcast(offsets), ["shard", "part"]).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("key").alias("law"),
        F.col("shard").cast("int").alias("shard"),
        (F.col("offset") + F.col("rank")).cast("long").alias("slot"),
        F.col("grown_shard").cast("int").alias("grown_shard"),
    )
