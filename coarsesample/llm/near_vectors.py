"""Near-duplicate vectors by sorted projection passes.

Vectors are compared inside a group (same label, same dimension). Equal vectors form a class of
which one goes on, with its count. In every pass the vectors of a group are ordered by the
concatenated signs of random projections, the order is cut into blocks, and each block is compared
with itself and the block before it, as one matrix product in double precision; where a task's order
ends, its last block meets the next task's first. A window gives a spanning forest, one edge per
vector at most, and the passes' forests are united by connected components.

Links are then counted exactly inside each component, whatever its size: its members are dealt to
blocks by a hash, each pair of blocks is one task, and only a count per vector leaves it. So the
work in a component grows with the square of its members, but no pair is listed.

What is left to chance is whether the passes join two vectors that only each other's link connects.
At cosine 0.98 two vectors differ in a projection's sign with probability 0.064, and they have to
agree in about as many signs as the group has doublings of ``block``; ``passes`` is raised with the
largest group until that fails for at most one such pair in 10^5.

Cosines are taken of vectors scaled by their largest component first, so squares neither vanish nor
overflow.

Defined results: null, zero or empty vectors, vectors with null or non-finite components, and null
labels or ids link with nothing and are their own component; every row is a vector, so rows that
repeat an id count as others, with its value or with another, and a component is named by its least
id; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.llm.components import connected_components, local_roots
from coarsesample.runtime import materialize

BITS = 60


def _keys(vectors: np.ndarray, seed: int, turn: int) -> np.ndarray:
    """Signs of random projections, first projection in the highest bit."""
    planes = np.random.default_rng([seed, turn, vectors.shape[1]]).normal(size=(vectors.shape[1], BITS))
    return ((vectors @ planes) > 0) @ (1 << np.arange(BITS - 1, -1, -1, dtype=np.int64))


def _units(rows: pd.Series) -> np.ndarray:
    v = np.stack([np.asarray(r, np.float64) for r in rows])
    v = v / np.abs(v).max(axis=1)[:, None]
    return v / np.linalg.norm(v, axis=1)[:, None]


def _hash_passes(seed: int, passes: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            keys = np.zeros((len(batch), passes), np.int64)
            dims = batch["dim"].to_numpy()
            for dim in np.unique(dims):
                own = np.flatnonzero(dims == dim)
                unit = _units(batch["embedding"].iloc[own])
                for turn in range(passes):
                    keys[own, turn] = _keys(unit, seed, turn)
            yield batch.assign(keys=list(keys))

    return run


def passes_for(largest: int, block: int, threshold: float, miss: float = 1e-5) -> int:
    """Passes after which a pair at the threshold in a group of ``largest`` has met, but for a chance of ``miss``."""
    signs = max(0.0, math.log2(max(1, largest) / block))
    meet = (1 - math.acos(max(-1.0, min(1.0, threshold))) / math.pi) ** signs
    return 1 if meet >= 1 else math.ceil(math.log(miss) / math.log1p(-meet))


def _ties(a: pd.DataFrame, b: pd.DataFrame, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links between two blocks, or inside one if they are the same."""
    ua = _units(a["embedding"])
    ids = a["vec_id"].to_numpy(np.int64)
    if a is b:
        i, j = np.nonzero(ua @ ua.T >= threshold)
        i, j = i[i < j], j[i < j]
    else:
        i, j = np.nonzero(ua @ _units(b["embedding"]).T >= threshold)
        j = j + len(ids)
        ids = np.concatenate([ids, b["vec_id"].to_numpy(np.int64)])
    root = local_roots(len(ids), i, j)
    tied = root != np.arange(len(root))
    return ids[tied], ids[root[tied]]


def _group_of(rows: pd.DataFrame) -> tuple:
    return rows["label"].iloc[0], rows["dim"].iloc[0]


#: Links u, v of a pass, or (with u null) the rows at a task's borders: side 0 ends it, side 1 begins it.
PASS_SCHEMA = "u long, v long, part int, side int, vec_id long, label string, dim int, embedding array<double>"


def _compare_pass(threshold: float, block: int):
    """Blocks of ordered rows against themselves and the one before, as links, and the task's border rows."""

    def rows_of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Blocks that hold one group each."""
        held: list[pd.DataFrame] = []
        size, group = 0, None
        for batch in batches:
            change = (batch[["label", "dim"]] != batch[["label", "dim"]].shift()).any(axis=1).to_numpy().copy()
            change[0] = True
            for part in np.split(np.arange(len(batch)), np.flatnonzero(change)[1:]):
                rows = batch.iloc[part]
                here = _group_of(rows)
                if here != group and held:
                    yield pd.concat(held)
                    held, size = [], 0
                group = here
                while len(rows):
                    take = rows.iloc[: block - size]
                    held.append(take)
                    size, rows = size + len(take), rows.iloc[len(take) :]
                    if size == block:
                        yield pd.concat(held)
                        held, size = [], 0
        if held:
            yield pd.concat(held)

    def found(u: np.ndarray, v: np.ndarray) -> pd.DataFrame:
        none = pd.Series([None] * len(u), dtype=object)
        whole = pd.Series([pd.NA] * len(u), dtype="Int64")
        return pd.DataFrame({"u": u, "v": v, "part": whole, "side": whole, "vec_id": whole, "label": none, "dim": whole, "embedding": none})

    def border(rows: pd.DataFrame, part: int, side: int) -> pd.DataFrame:
        whole = pd.array([pd.NA] * len(rows), dtype="Int64")
        return rows[["vec_id", "label", "dim", "embedding"]].assign(u=whole, v=whole, part=part, side=side)[["u", "v", "part", "side", "vec_id", "label", "dim", "embedding"]]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, last, tail = TaskContext.get().partitionId(), None, None
        for rows in rows_of(batches):
            yield found(*_ties(rows, rows, threshold))
            if last is None:
                yield border(rows, part, 1)
            tail = rows
            if last is not None and _group_of(last) == _group_of(rows):
                yield found(*_ties(last, rows, threshold))
                tail = pd.concat([last, rows]).iloc[-block:]
            last = rows
        if tail is not None:
            yield border(tail, part, 0)

    return run


def _border_links(rows: DataFrame, threshold: float) -> DataFrame:
    """Links between the end of each task and the begin of the next that had rows, in each pass."""
    spark = rows.sparkSession
    parts = sorted(tuple(r) for r in rows.where("side = 1").select("turn", "part").distinct().collect())
    follows = [(t, p, i) for i, (t, p) in enumerate(parts)]
    order = F.broadcast(spark.createDataFrame(follows, "turn int, part int, place long"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        ends, begins = group[group["side"] == 0], group[group["side"] == 1]
        if len(ends) and len(begins) and _group_of(ends) == _group_of(begins):
            u, v = _ties(ends, begins, threshold)
            return pd.DataFrame({"u": u, "v": v})
        return pd.DataFrame({"u": [], "v": []}, dtype="int64")

    met = rows.join(order, ["turn", "part"]).withColumn("border", F.col("place") - F.col("side"))
    return met.groupBy("turn", "border").applyInPandas(run, "u long, v long")


def _count_links(threshold: float, step: int = 512):
    """Links of each member of a component, or of a block with another one, weighted by copies."""

    def counts(a: pd.DataFrame, b: pd.DataFrame, same: bool) -> tuple[np.ndarray, np.ndarray]:
        ua, ub = _units(a["embedding"]), _units(b["embedding"])
        ca, cb = a["copies"].to_numpy(np.float64), b["copies"].to_numpy(np.float64)
        of_a, of_b = np.zeros(len(a)), np.zeros(len(b))
        for at in range(0, len(a), step):
            linked = ua[at : at + step] @ ub.T >= threshold
            if same:
                i = np.arange(len(linked))
                linked[i, at + i] = False
            linked = linked.astype(np.float64)
            of_a[at : at + step] = linked @ cb
            of_b += ca[at : at + step] @ linked
        return of_a, of_b

    def run(group: pd.DataFrame) -> pd.DataFrame:
        out = []
        for _, rows in group.groupby("component", sort=False):
            low, high = rows["low"].iloc[0], rows["high"].iloc[0]
            a, b = rows[rows["own"] == low], rows[rows["own"] == high]
            of_a, of_b = counts(a, b, low == high)
            out.append(pd.DataFrame({"vec_id": a["vec_id"], "links": of_a.astype(np.int64)}))
            if low != high:
                out.append(pd.DataFrame({"vec_id": b["vec_id"], "links": of_b.astype(np.int64)}))
        return pd.concat(out)

    return run


def _links_inside(vectors: DataFrame, components: DataFrame, threshold: float, small: int = 256, most: int = 4096, spread: int = 16, per_task: int = 2000) -> DataFrame:
    """vec_id, n_links: all links inside the components, each pair of blocks in one task.

    Up to ``spread`` blocks of ``small`` members, then blocks grow to ``most``. Components of one
    block share tasks.
    """
    sizes = components.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
    blocks = F.greatest(F.ceil(F.col("n") / most), F.least(F.ceil(F.col("n") / small), F.lit(spread))).cast("int")
    placed = components.join(sizes.select("component", blocks.alias("blocks")), "component").withColumnRenamed("node", "vec_id")
    placed = materialize(placed.withColumn("own", F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int")), "placed")
    tasks = placed.count() // per_task + 1
    alone = F.col("blocks") == 1
    dealt = placed.join(vectors.select("vec_id", "embedding", "copies"), "vec_id")
    dealt = dealt.withColumn("shared", F.when(alone, F.pmod(F.xxhash64("component"), F.lit(tasks))).otherwise(-1)).withColumn("cloud", F.when(alone, 0).otherwise(F.col("component")))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumn("low", F.least("own", "other")).withColumn("high", F.greatest("own", "other")).drop("other", "blocks")
    found = dealt.groupBy("shared", "cloud", "low", "high").applyInPandas(_count_links(threshold), "vec_id long, links long")
    return found.groupBy("vec_id").agg(F.sum("links").alias("n_links"))


def near_vectors(table: DataFrame, threshold: float = 0.98, passes: int = 8, block: int = 1024, seed: int = 11, key: str = "vec_id", vector: str = "embedding", label: str = "label") -> DataFrame:
    """vec_id, n_links, component_id, kept for every row."""
    given = table.select(F.col(key).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("embedding"), F.col(label).cast("string").alias("label"))
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    fine = F.coalesce(F.col("vec_id").isNotNull() & F.col("label").isNotNull() & ~bad & F.exists("embedding", lambda x: x != 0), F.lit(False))
    given = given.withColumn("fine", fine)
    print_of = F.struct(F.xxhash64("embedding"), F.md5(F.array_join(F.transform("embedding", lambda x: x.cast("string")), ",").cast("binary")))
    valid = given.where("fine").withColumn("print", print_of)
    counted = valid.groupBy("label", "print").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    classes = materialize(counted.withColumn("node", F.monotonically_increasing_id()), "classes")
    firsts = valid.join(classes, ["label", "print"]).where("vec_id = rep").dropDuplicates(["node"])
    vectors = firsts.select(F.col("node").alias("vec_id"), "label", F.size("embedding").alias("dim"), "embedding", "copies")
    largest = classes.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    passes = max(passes, passes_for(largest, block, threshold))
    shape = "vec_id long, label string, dim int, embedding array<double>, copies long, keys array<bigint>"
    vectors = materialize(vectors.mapInPandas(_hash_passes(seed, passes), shape), "vectors")
    met = None
    for turn in range(passes):
        order = ["label", "dim", "key", "vec_id"]
        ordered = vectors.select("label", "dim", F.element_at("keys", turn + 1).alias("key"), "vec_id", "embedding").repartitionByRange(*order).sortWithinPartitions(*order)
        found = materialize(ordered.mapInPandas(_compare_pass(threshold, block), PASS_SCHEMA), "pass").withColumn("turn", F.lit(turn))
        met = found if met is None else met.unionByName(found)
    links = met.where("u is not null").select("u", "v").unionByName(_border_links(met.where("u is null").drop("u", "v"), threshold))
    components = materialize(connected_components(links), "components")
    inside = _links_inside(vectors, components, threshold)
    named = components.join(classes.select("node", "rep"), "node").groupBy("component").agg(F.min("rep").alias("name"))
    found = classes.join(inside.withColumnRenamed("vec_id", "node"), "node", "left").join(components.join(named, "component"), "node", "left").withColumn("n_links", F.coalesce("n_links", F.lit(0)))
    found = found.select("label", "print", (F.col("n_links") + F.col("copies") - 1).alias("links"), F.coalesce("name", "rep").alias("component"))
    rows = given.withColumn("print", F.when(F.col("fine"), print_of)).drop("embedding").join(found, ["label", "print"], "left")
    out = rows.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
