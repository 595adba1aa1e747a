"""Sealing partitions from a stream: windows, idempotent sketches, state, late rows, joins.

Streams read with ``availableNow`` and write through foreachBatch into numbered folders of shared
scratch, so a batch that is replayed overwrites its own folder and nothing is counted twice. A
partition is sealed once the watermark has passed its end; rows that come later go to a delta.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.runtime import read_table, scratch_path

INSTANT = "timestamp_seconds(timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts))"


def events_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream; ``at`` is the row's time as an instant, whatever the session's zone."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    glob = f"{sf_dir}/event[s].parquet"  # a glob may be one file or a folder of files
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(glob).withColumn("at", F.expr(INSTANT))


def drain(stream: DataFrame, mode: str, tag: str, step: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Run a stream over all that is there. In complete mode the last batch is the result, else all batches are."""
    spark = stream.sparkSession
    out = scratch_path(spark, tag)
    seen: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        (step(batch) if step else batch).write.mode("overwrite").parquet(f"{out}/data/batch={number}")
        seen.append(number)

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{out}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    if mode == "complete":
        return spark.read.parquet(f"{out}/data/batch={max(seen)}")
    return spark.read.parquet(*[f"{out}/data/batch={n}" for n in sorted(set(seen))])


def windowed(stream: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """Partition-sized windows with their measures; ``start`` in seconds since the epoch."""
    w = F.window("at", length, slide) if slide else F.window("at", length)
    agg = stream.withWatermark("at", "1 hour").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("low"), F.max("value").alias("high"), F.sum("value").alias("total"))
    return agg.select(F.unix_timestamp("w.start").alias("start"), "event_type", "n", "low", "high", "total")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    """A user's runs of events with no pause of ``gap`` or more, for complete mode.

    Spark joins an event that begins just where a session ends, so a session ends a microsecond before
    the gap. Complete mode keeps every session; a watermark would only drop rows of later files behind it.
    """
    agg = stream.groupBy("user_id", F.session_window("at", f"{gap} -1 microseconds").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return agg.select("user_id", F.unix_timestamp("w.start").alias("start"), "n", "total")


def sealed(stream: DataFrame, length: str = "1 day", delay: str = "1 hour") -> DataFrame:
    """part_id, n_rows, mean, max of the windows that the watermark has passed; each is given once, when it is whole."""
    agg = stream.withWatermark("at", delay).groupBy(F.window("at", length).alias("w")).agg(F.count(F.lit(1)).alias("n_rows"), F.avg("value").alias("mean"), F.max("value").alias("max"))
    return agg.select(F.floor(F.unix_timestamp("w.start") / 86400).alias("part_id"), "n_rows", "mean", "max")


def deltas(spark: SparkSession, sf_dir: str, late: str, delay: int = 3600) -> DataFrame:
    """event_id, day, value, part_key of the events in two deliveries; the second brings the rows that ``late`` names.

    A batch's watermark is the latest time of all batches before it less ``delay`` seconds, kept in
    shared scratch beside them. Rows of a day that had ended by then find it sealed and get a delta
    partition of their own; other rows, late or not, still join their day.
    """
    out, events = scratch_path(spark, "deltas"), read_table(spark, sf_dir, "events")

    def write(batch: DataFrame, number: int) -> None:
        held = batch.withColumn("at", F.expr(INSTANT)).withColumn("day", F.floor(F.unix_timestamp("at") / 86400)).persist()
        before = spark.read.parquet(*[f"{out}/mark/batch={n}" for n in range(number)]).agg(F.max("latest")).first()[0] if number else None
        is_late = F.lit(before is not None) & ((F.col("day") + 1) * 86400 <= F.lit((before or 0) - delay))
        key = F.when(is_late, F.concat_ws("-", F.col("day").cast("string"), F.lit("delta"))).otherwise(F.col("day").cast("string"))
        held.select("event_id", "day", "value", key.alias("part_key")).write.mode("overwrite").parquet(f"{out}/data/batch={number}")
        held.agg(F.max(F.unix_timestamp("at")).alias("latest")).write.mode("overwrite").parquet(f"{out}/mark/batch={number}")
        held.unpersist()

    for delivery in (f"NOT ({late})", late):
        events.where(delivery).write.mode("append").parquet(f"{out}/arrivals")
        stream = spark.readStream.schema(events.schema).parquet(f"{out}/arrivals")
        stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{out}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{out}/data").drop("batch")


class StatefulMeasures:
    """Counts, extremes and k smallest hashes of each key, kept in state and bounded by k."""

    OUTPUT = "key int, n long, low double, high double, total double, hashes array<long>"
    STATE = "n long, low double, high double, total double, hashes array<long>"

    def __init__(self, k: int = 16):
        self.k = k

    def __call__(self, key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, low, high, total, hashes = state.get if state.exists else (0, float("inf"), float("-inf"), 0.0, [])
        kept = set(hashes)
        for b in batches:
            n += len(b)
            low, high, total = min(low, float(b["value"].min())), max(high, float(b["value"].max())), total + float(b["value"].sum())
            kept = set(sorted(kept | set(b["h"].tolist()))[: self.k])
        state.update((n, low, high, total, sorted(kept)))
        yield pd.DataFrame({"key": [int(key[0])], "n": [n], "low": [low], "high": [high], "total": [total], "hashes": [sorted(kept)]})


def stateful(stream: DataFrame, keys: int = 10) -> DataFrame:
    """Measures per key bucket in state; every batch emits the keys it touched."""
    from coarsesample.functions.portable import hash32

    given = stream.select(F.pmod("user_id", F.lit(keys)).cast("int").alias("key"), "value", hash32(F.col("user_id").cast("string")).alias("h"))
    s = StatefulMeasures()
    return given.groupBy("key").applyInPandasWithState(s, s.OUTPUT, s.STATE, "update", "NoTimeout")
