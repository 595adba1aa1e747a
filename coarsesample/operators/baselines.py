"""Baselines: uniform, uniform after the filter, strata by score, row samples."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from coarsesample.functions.portable import draw_order


def select_uniform(parts: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """n partitions in the order of an arithmetic shuffle, each with weight N/n. ``parts`` has one row per partition."""
    total = parts.agg(F.count(F.lit(1)).alias("__N"))
    first = parts.orderBy(draw_order(F.col("part_id"), seed), "part_id").limit(n)
    return first.crossJoin(F.broadcast(total)).select("part_id", (F.col("__N") / F.least(F.lit(n), F.col("__N"))).alias("weight"))


def select_strata(scored: DataFrame, n: int, strata: int, seed: int = 0) -> DataFrame:
    """Runs of consecutive scores of equal count; in each a share of n, one at least; weight is size over sample.

    ``scored`` has part_id and score, one row per partition (sketch-sized), so its ranking is one small task.
    """
    run = F.ntile(strata).over(Window.orderBy("score", "part_id"))
    held = scored.select("part_id", "score", run.alias("stratum"))
    own = Window.partitionBy("stratum")
    held = held.withColumn("size", F.count(F.lit(1)).over(own)).withColumn("all", F.lit(scored.count()))
    reads = F.least(F.col("size"), F.greatest(F.lit(1), F.floor(F.col("size") * n / F.col("all")))).cast("int")
    place = F.row_number().over(own.orderBy(draw_order(F.col("part_id"), seed), "part_id"))
    return held.withColumn("reads", reads).withColumn("at", place).where("at <= reads").select("part_id", (F.col("size") / F.col("reads")).alias("weight"), "stratum")


def uniform_rows(parts: np.ndarray, n: int, seed: int = 0) -> list[tuple[int, float]]:
    """select_uniform for partition ids on the driver."""
    order = parts[np.lexsort((parts, (parts * 7919 + seed * 104729) % 10007))][:n]
    return [(int(p), len(parts) / max(1, len(order))) for p in order]


def strata_rows(parts: np.ndarray, score: np.ndarray, n: int, strata: int, seed: int = 0) -> list[tuple[int, float]]:
    """select_strata for partition ids on the driver."""
    order = np.lexsort((parts, score))
    out = []
    runs = [r for r in np.array_split(order, max(1, min(strata, n, len(order)))) if len(r)]
    spare = n - sum(max(1, n * len(r) // len(order)) for r in runs)
    for r in runs:
        reads = min(len(r), max(1, n * len(r) // len(order)) + (spare > 0))
        spare -= 1
        out += [(p, len(r) / reads) for p, _ in uniform_rows(parts[r], reads, seed)]
    return out


def sample_rows(df: DataFrame, key: F.Column, per_thousand: int) -> DataFrame:
    """A row sample by an arithmetic hash of a key; touches nearly all partitions."""
    return df.where(F.pmod(key * 7919 + 13, F.lit(1000)) < per_thousand)


def blocks_touched(fraction: float, rows_per_block: int | Column) -> float | Column:
    """Expected share of blocks that a row sample reads; of a column of rows, the chance of each block."""
    return 1 - (1 - fraction) ** rows_per_block
