"""Partition ids: physical ones as found, and layouts derived for experiments.

No layout uses a window over the whole table. A total order is made by one range shuffle; a row's
number is its place inside its task plus the count of the tasks before.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coarsesample.functions.portable import draw_order
from coarsesample.runtime import materialize


def with_physical_part_id(df: DataFrame) -> DataFrame:
    """Dense part_id from the files and splits of a Parquet scan; the file list is small and broadcast."""
    tagged = df.select("*", F.col("_metadata.file_path").alias("__f"), F.col("_metadata.file_block_start").alias("__b"))
    files = tagged.select("__f", "__b").distinct()
    listed = sorted((r[0], r[1]) for r in files.collect())
    ids = df.sparkSession.createDataFrame([(f, b, i) for i, (f, b) in enumerate(listed)], "__f string, __b long, part_id int")
    return tagged.join(F.broadcast(ids), ["__f", "__b"]).drop("__f", "__b")


def assign_stored(df: DataFrame, rows_per_part: int) -> DataFrame:
    """Equal runs of rows in stored order, for a table of one file."""
    return df.select("*", F.floor(F.col("_metadata.row_index") / rows_per_part).cast("int").alias("part_id"))


def assign_bucketed(df: DataFrame, value: Column, width: float, origin: float = 0) -> DataFrame:
    """Value buckets, as ingest by day makes them; no shuffle."""
    return df.withColumn("part_id", F.floor((value - origin) / width).cast("int"))


def global_row_number(df: DataFrame, *order: str | Column) -> DataFrame:
    """Column ``__rn`` from 0 in total order, by one range shuffle and a broadcast of one count per task."""
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__mid", F.monotonically_increasing_id())
    held = materialize(ranged, "ordered")
    counts = sorted((r[0], r[1]) for r in held.groupBy(F.shiftright("__mid", 33).alias("t")).count().collect())
    rows, at = [], 0
    for task, n in counts:
        rows.append((task, at))
        at += n
    bases = df.sparkSession.createDataFrame(rows, "__t long, __base long")
    place = F.col("__mid").bitwiseAND(F.lit((1 << 33) - 1))
    joined = held.withColumn("__t", F.shiftright("__mid", 33)).join(F.broadcast(bases), "__t")
    return joined.withColumn("__rn", F.col("__base") + place).drop("__t", "__base", "__mid")


def assign_sorted(df: DataFrame, order: list[str], n_parts: int) -> DataFrame:
    """Sort, then cut in ``n_parts`` runs whose sizes differ by one at most, the longer first; ids from 1."""
    numbered = global_row_number(df, *order)
    n = numbered.count()
    q, r = divmod(n, n_parts)
    rn = F.col("__rn")
    long_rows = r * (q + 1)
    part = F.when(rn < long_rows, F.floor(rn / (q + 1))).otherwise(r + F.floor((rn - long_rows) / max(1, q)))
    return numbered.withColumn("part_id", (part + 1).cast("int")).drop("__rn")


def assign_random(df: DataFrame, key: Column, n_parts: int, seed: int = 0) -> DataFrame:
    """Random layout: an arithmetic shuffle of a key decides; no shuffle of rows."""
    return df.withColumn("part_id", F.pmod(draw_order(key, seed) * 31 + key * 17, F.lit(n_parts)).cast("int"))


def write_layout(df: DataFrame, path: str, whole: bool = False) -> None:
    """One directory and file per part_id, so that a partition is what a scan reads or skips.

    With ``whole``, rows of a partition already lie in one task and are not dealt again.
    """
    (df if whole else df.repartition("part_id").sortWithinPartitions("part_id")).write.partitionBy("part_id").parquet(path)
