"""Clustering of partition features, exemplars and weights.

A level is clustered as a whole up to ``CELL_MOST`` partitions and in halves of halves beyond
(split_sample), so the driver plans over hundreds of thousands of them. Where even their features are
too many for the driver, cells of a coarse signature are clustered by a task each (cell_sample).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CELL_MOST = 2_000
HAC_MOST = 5_000


def kmeans(x: np.ndarray, k: int, seed: int = 0, rounds: int = 30) -> np.ndarray:
    """Labels of Lloyd's method from spread-out seeds; may use fewer than k where points repeat."""
    rng = np.random.default_rng(seed)
    centres = [x[rng.integers(len(x))]]
    d = ((x - centres[0]) ** 2).sum(1)
    while len(centres) < k and d.max() > 1e-18:
        centres.append(x[rng.choice(len(x), p=d / d.sum())])
        d = np.minimum(d, ((x - centres[-1]) ** 2).sum(1))
    c = np.array(centres)
    label = np.full(len(x), -1)
    for _ in range(rounds):
        dist = (x**2).sum(1)[:, None] - 2 * x @ c.T + (c**2).sum(1)
        new = dist.argmin(1)
        if (new == label).all():
            break
        label = new
        for j in np.unique(label):
            c[j] = x[label == j].mean(0)
    return np.unique(label, return_inverse=True)[1]


def ward(x: np.ndarray, k: int) -> np.ndarray:
    """Agglomeration by least growth of the within-cluster squares, along nearest-neighbour chains."""
    n = len(x)
    if n > HAC_MOST:
        raise ValueError(f"HAC takes {HAC_MOST} points at most")
    d = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    size, alive = np.ones(n), np.ones(n, bool)
    merges, chain = [], []
    for _ in range(n - 1):
        if not chain:
            chain = [int(np.flatnonzero(alive)[0])]
        while True:
            a = chain[-1]
            b = int(np.where(alive, d[a], np.inf).argmin())
            if len(chain) > 1 and d[a, chain[-2]] <= d[a, b]:
                b = chain[-2]
                break
            chain.append(b)
        chain = chain[:-2]
        a, b = min(a, b), max(a, b)
        merges.append((d[a, b], a, b))
        s = size + size[a] + size[b]
        row = ((size + size[a]) * d[a] + (size + size[b]) * d[b] - size * d[a, b]) / s
        d[a], d[:, a] = row, row
        d[a, a] = np.inf
        size[a] += size[b]
        alive[b] = False
        d[b], d[:, b] = np.inf, np.inf
    return _cut(n, merges, k)


def single(x: np.ndarray, k: int) -> np.ndarray:
    """Components of the minimum spanning tree without its k-1 longest edges."""
    n = len(x)
    if n > HAC_MOST:
        raise ValueError(f"HAC takes {HAC_MOST} points at most")
    far, near = np.full(n, np.inf), np.zeros(n, int)
    out, at, merges = np.ones(n, bool), 0, []
    for _ in range(n - 1):
        out[at] = False
        step = ((x - x[at]) ** 2).sum(1)
        closer = out & (step < far)
        far[closer], near[closer] = step[closer], at
        at = int(np.where(out, far, np.inf).argmin())
        merges.append((far[at], near[at], at))
    return _cut(n, merges, k)


def _cut(n: int, merges: list[tuple], k: int) -> np.ndarray:
    """Labels after the n-k lowest merges."""
    root = list(range(n))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for _, a, b in sorted(merges)[: n - k]:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    return np.unique([find(i) for i in range(n)], return_inverse=True)[1]


ALGORITHMS = {"kmeans": kmeans, "hac_ward": lambda x, k, seed=0: ward(x, k), "hac_single": lambda x, k, seed=0: single(x, k)}


def cluster_sample(parts: np.ndarray, x: np.ndarray, n: int, algo: str = "kmeans", exemplar: str = "median", seed: int = 0) -> list[tuple[int, float, int]]:
    """(part, weight, cluster) of ``n`` reads out of one level; weights sum to the level's size.

    The exemplar is the member nearest to the cluster's median features, or the first of an
    arithmetic shuffle. Where points repeat and clusters are fewer than reads, the largest clusters
    are read more than once, and their weight is shared.
    """
    if n <= 0 or not len(parts):
        return []
    if n >= len(parts):
        return [(int(p), 1.0, i) for i, p in enumerate(parts)]
    order = np.argsort(parts, kind="stable")
    parts, x = parts[order], x[order][:, x.std(0) > 1e-12]
    label = ALGORITHMS[algo](x, n, seed=seed) if x.shape[1] else np.zeros(len(parts), int)
    sizes = np.bincount(label)
    reads = np.ones(len(sizes), int)
    for _ in range(n - len(sizes)):
        reads[np.where(reads < sizes, sizes / reads, -1).argmax()] += 1
    out = []
    for j in range(len(sizes)):
        own = np.flatnonzero(label == j)
        if exemplar == "median":
            far = ((x[own] - np.median(x[own], axis=0)) ** 2).sum(1)
        else:
            far = (parts[own] * 7919 + seed * 104729) % 10007
        best = own[np.lexsort((parts[own], far))][: reads[j]]
        out += [(int(parts[i]), float(sizes[j] / reads[j]), int(j)) for i in best]
    return out


def split_sample(parts: np.ndarray, x: np.ndarray, n: int, algo: str = "kmeans", exemplar: str = "median", seed: int = 0, most: int = CELL_MOST) -> list[tuple[int, float, int]]:
    """cluster_sample of many partitions: halved at the median of the widest feature until ``most`` are left.

    A half gets its share of the reads and one at least, so the reads add up to ``n`` and the weights to
    the number of partitions; work grows with partitions times ``most`` instead of with their square.
    """
    if len(parts) <= most or n < 2 or n >= len(parts):
        return cluster_sample(parts, x, n, algo, exemplar, seed)
    wide = int(x.var(0).argmax()) if x.shape[1] else 0
    order = np.lexsort((parts, x[:, wide])) if x.shape[1] else np.argsort(parts)
    low, high = order[: len(order) // 2], order[len(order) // 2 :]
    reads = min(max(1, round(n * len(low) / len(parts))), n - 1)
    out = split_sample(parts[low], x[low], reads, algo, exemplar, seed, most)
    more = split_sample(parts[high], x[high], n - reads, algo, exemplar, seed, most)
    shift = 1 + max(c for _, _, c in out)
    return out + [(p, w, c + shift) for p, w, c in more]


def share_out(sizes: dict[int, int], n: int) -> dict[int, int]:
    """Reads of each cell by largest remainders: ``n`` together, one at least where ``n`` allows, none beyond a cell's size."""
    total = sum(sizes.values())
    n = min(n, total)
    want = {c: n * s / total for c, s in sizes.items()}
    out = {c: int(w) for c, w in want.items()}
    for c in sorted(sizes, key=lambda c: (out[c] - want[c], -sizes[c], c))[: n - sum(out.values())]:
        out[c] += 1
    for c in sorted(sizes):
        rich = max(out, key=lambda d: (out[d], -d))
        if out[c] == 0 and out[rich] > 1:
            out[c], out[rich] = 1, out[rich] - 1
    return out


def cell_sample(features: DataFrame, n: int, cells: int, algo: str = "kmeans", seed: int = 0) -> DataFrame:
    """part_id, weight, cluster for more partitions than one driver holds; ``n`` reads, weights sum to the partitions.

    ``features`` has part_id and f (array). Cells are hash buckets of a coarse signature (the signs of
    a few random projections), never more than ``n`` of them; a cell's reads are its share of ``n`` by
    largest remainders, from one count per cell, and cells are clustered in parallel, halved inside
    where they are large. One shuffle of partition-sized rows.
    """
    first = features.select(F.size("f")).first()
    planes = np.random.default_rng(seed).normal(size=(first[0] if first else 1, 8))
    signs = F.lit(0)
    for j in range(planes.shape[1]):
        dot = F.aggregate(F.zip_with("f", F.array(*[F.lit(float(v)) for v in planes[:, j]]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
        signs = signs + F.when(dot > 0, 1 << j).otherwise(0)
    dealt = features.withColumn("cell", F.pmod(F.xxhash64(signs), F.lit(max(1, min(cells, n)))).cast("int"))
    reads = share_out({r["cell"]: r["count"] for r in dealt.groupBy("cell").count().collect()}, n)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        parts, x = group["part_id"].to_numpy(), np.stack(group["f"].to_numpy())
        return pd.DataFrame(split_sample(parts, x, reads[int(group["cell"].iloc[0])], algo, seed=seed), columns=["part_id", "weight", "cluster"])

    return dealt.groupBy("cell").applyInPandas(run, "part_id int, weight double, cluster int")
