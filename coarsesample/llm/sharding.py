"""Weighted rendezvous hashing of stable record keys over shards, on built-in functions only.

Every shard draws a uniform number from (key, shard); the shard with the largest
``-weight / ln(draw)`` takes the record. A new shard only competes with its own draw, so it takes
records into itself and moves none between the others.

Slots come from counts, not from one long order: records are numbered inside (shard, bucket) groups,
and what one key or text repeats is spread over all buckets by a salt, which is written down first so
that a lost task draws the same one.

Defined results: a null key hashes as the text ``\\N``; null text counts no bytes and has checksum 0;
repeated keys land in one shard; an empty table gives an empty result; only the named key and text
columns are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from coarsesample.runtime import materialize

ROW_OVERHEAD = 8


def draw(key: Column, shard: int) -> Column:
    """Uniform in (0, 1) from the key and the shard number."""
    bits = F.shiftrightunsigned(F.xxhash64(key, F.lit(shard)), 11)
    return (bits + F.lit(0.5)) / F.lit(float(1 << 53))


def shard_of(key: Column, weights: Sequence[float]) -> Column:
    """The winning shard; equal scores go to the lower shard."""
    if not weights or min(weights) <= 0:
        raise ValueError("weights must be positive")
    bids = [F.struct((F.lit(-float(w)) / F.ln(draw(key, i))).alias("bid"), F.lit(-i).alias("at")) for i, w in enumerate(weights)]
    best = F.greatest(*bids) if len(bids) > 1 else bids[0]
    return (-best["at"]).cast("int")


def assign_shards(
    records: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    weights: Sequence[float] = (1.0,) * 24,
    new_weight: float = 1.0,
    slot_buckets: int = 256,
) -> DataFrame:
    """key, size, text_crc32, shard, slot, grown_shard for every record.

    ``slot`` numbers a shard's records from 0 without gaps: a record's place in its (shard, bucket)
    group, a small share of a shard, moved up by the count of the buckets before; those counts are
    ``len(weights) * slot_buckets`` rows at most, which is what is broadcast.
    """
    stable = F.coalesce(F.col(key).cast("string"), F.lit("\\N"))
    placed = records.select(
        F.col(key),
        (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + F.lit(ROW_OVERHEAD)).cast("long").alias("size"),
        F.coalesce(F.crc32(F.col(text).cast("binary")), F.lit(0)).cast("long").alias("text_crc32"),
        shard_of(stable, weights).alias("shard"),
        shard_of(stable, [*weights, new_weight]).alias("grown_shard"),
        F.pmod(F.xxhash64(stable, F.monotonically_increasing_id()), F.lit(slot_buckets)).cast("int").alias("__bucket"),
    )
    placed = materialize(placed, "placed")
    before = Window.partitionBy("shard").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = (
        placed.groupBy("shard", "__bucket")
        .agg(F.count(F.lit(1)).alias("__n"))
        .select("shard", "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__base"))
    )
    inside = Window.partitionBy("shard", "__bucket").orderBy(F.col(key), "text_crc32", "size")
    numbered = placed.withColumn("__at", F.row_number().over(inside) - 1)
    return (
        numbered.join(F.broadcast(bases), ["shard", "__bucket"])
        .select(key, "size", "text_crc32", "shard", (F.col("__base") + F.col("__at")).cast("long").alias("slot"), "grown_shard")
    )
