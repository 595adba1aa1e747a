"""Choosing weighted partitions: filter, outliers, importance levels, budget, clusters.

The statistics table has one row per partition, so the choice is a planning step: features of the
candidates come to the driver, some hundred doubles for each partition, large levels are clustered in
halves of halves, and the result is a small list of (partition, weight). Tables whose partitions are
too many even for that are sampled on the executors by clustering.cell_sample.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from coarsesample.operators.clustering import split_sample

SELECTION = "part_id int, weight double, role string, level int, cluster int"


def outlier_groups(bitmaps: DataFrame, most: int = 10, share: float = 0.1) -> DataFrame:
    """part_id of partitions whose pattern of grouping items is rare: under ``most`` partitions and ``share`` of the commonest."""
    sizes = bitmaps.groupBy("bits").agg(F.count(F.lit(1)).alias("size"))
    largest = sizes.agg(F.max("size").alias("largest"))
    rare = sizes.crossJoin(F.broadcast(largest)).where((F.col("size") < most) & (F.col("size") < share * F.col("largest")))
    return bitmaps.join(F.broadcast(rare.select("bits", "size")), "bits").select("part_id", "bits", "size")


def cap_outliers(outliers: DataFrame, most: int) -> DataFrame:
    """Whole patterns, rarest first, while their partitions fit the cap."""
    sizes = outliers.select("bits", "size").distinct()
    running = F.sum("size").over(Window.orderBy("size", "bits").rowsBetween(Window.unboundedPreceding, 0))
    return outliers.join(F.broadcast(sizes.withColumn("sum", running).where(F.col("sum") <= most).select("bits")), "bits")


def allocate(sizes: list[int], n: int, alpha: float = 2.0) -> list[int]:
    """Reads per level (least important first): the rate grows by ``alpha`` a level and never exceeds one."""
    sizes_, k = np.array(sizes, float), len(sizes)
    n = int(min(n, sizes_.sum()))
    capped = np.zeros(k, bool)
    rate = np.zeros(k)
    for _ in range(k + 1):
        left = n - sizes_[capped].sum()
        base = (alpha ** np.arange(k) * sizes_)[~capped].sum()
        rate = np.where(capped, 1.0, (left / base if base > 0 else 0.0) * alpha ** np.arange(k))
        over = (rate > 1 + 1e-12) & ~capped & (sizes_ > 0)
        if not over.any():
            break
        capped |= over
    want = rate * sizes_
    out = np.floor(want + 1e-9).astype(int)
    for i in sorted(range(k), key=lambda i: (-round(want[i] - out[i], 9), -i)):
        if out.sum() >= n:
            break
        if out[i] < sizes[i]:
            out[i] += 1
    for i in sorted(range(k), key=lambda i: -i):
        while out.sum() < n and out[i] < sizes[i]:
            out[i] += 1
    filled = [i for i in range(k) if sizes[i] > 0]
    if n >= len(filled):
        for i in filled:
            if out[i] == 0:
                out[int(out.argmax())] -= 1
                out[i] = 1
    return out.tolist()


def importance_levels(scores: list[np.ndarray]) -> np.ndarray:
    """Level of each partition: how many models pass it in a row, from the first."""
    level, alive = np.zeros(len(scores[0]) if scores else 0, int), None
    for s in scores:
        passed = s > 0
        alive = passed if alive is None else alive & passed
        level += alive
    return level


def merge_levels(level: np.ndarray, most: int) -> np.ndarray:
    """Levels renumbered without gaps, the least important ones united until at most ``most`` are left.

    A level without a read would be missing from the answer, so a small budget needs few levels.
    """
    kept, out = np.unique(level, return_inverse=True)
    return np.maximum(out - max(0, len(kept) - most), 0)


@dataclass
class Candidates:
    """What the picker knows of a query's partitions, on the driver: ids, features, outlier key, selectivities."""

    parts: np.ndarray
    features: np.ndarray
    keys: list
    upper: np.ndarray
    indep: np.ndarray
    raw: np.ndarray = None
    timing: dict = field(default_factory=dict)


def select_full(
    c: Candidates,
    n: int,
    models=None,
    alpha: float = 2.0,
    outlier_share: float = 0.1,
    algo: str = "kmeans",
    exemplar: str = "median",
    seed: int = 0,
    use_filter: bool = True,
    use_outliers: bool = True,
    use_models: bool = True,
    use_clusters: bool = True,
    keep: np.ndarray | None = None,
    near_unique: bool = False,
) -> list[tuple[int, float, str, int, int]]:
    """(part, weight, role, level, cluster) of ``n`` reads at most. The flags switch parts off for ablations."""
    began = time.perf_counter()
    alive = np.flatnonzero(c.upper > 0) if use_filter else np.arange(len(c.parts))
    if n >= len(alive):
        return [(int(c.parts[i]), 1.0, "all", 0, 0) for i in alive]
    out = []
    if use_outliers and any(k is not None for k in c.keys):
        sizes: dict = {}
        for i in alive:
            sizes[c.keys[i]] = sizes.get(c.keys[i], 0) + 1
        largest, taken = max(sizes.values(), default=0), 0
        chosen = set()
        for size, key in sorted((s, k) for k, s in sizes.items() if s < 10 and s < 0.1 * largest):
            if taken + size > int(outlier_share * n):
                break
            taken += size
            chosen.add(key)
        out = [(int(c.parts[i]), 1.0, "outlier", 0, 0) for i in alive if c.keys[i] in chosen]
        alive = np.array([i for i in alive if c.keys[i] not in chosen], int)
    left = n - len(out)
    level = importance_levels([m(c.raw[alive]) for m in models]) if use_models and models else np.zeros(len(alive), int)
    level = merge_levels(level, max(1, left // 3))
    top = int(level.max()) + 1 if len(level) else 1
    reads = allocate([int((level == j).sum()) for j in range(top)], left, alpha)
    fallback = near_unique or (len(alive) and float(np.median(c.indep[alive])) < 0.01)
    clock = time.perf_counter()
    for j in range(top):
        own = alive[level == j]
        if use_clusters and not fallback:
            x = c.features[own] if keep is None else c.features[own][:, keep]
            out += [(p, w, "cluster", j, k) for p, w, k in split_sample(c.parts[own], x, reads[j], algo, exemplar, seed)]
        elif reads[j]:
            order = own[np.lexsort((c.parts[own], (c.parts[own] * 7919 + seed * 104729) % 10007))][: reads[j]]
            out += [(int(c.parts[i]), len(own) / reads[j], "random", j, 0) for i in order]
    c.timing = {"total_ms": 1000 * (time.perf_counter() - began), "cluster_ms": 1000 * (time.perf_counter() - clock)}
    return out


def selection_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """A selection as a DataFrame."""
    return spark.createDataFrame(rows, SELECTION)
