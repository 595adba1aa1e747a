"""Near-duplicate documents by bottom-k sketches from one hash function.

A document's set of word shingles is hashed once; the ``k`` smallest hashes are its sketch. Documents
with equal sets form a class and only its first member goes on, so thousands of copies cost one.
Candidates come from inverted lists of retained values in two steps:

1. Lists keyed by two neighbouring retained values link every member to the list's first member.
   That is linear in a list's length and joins groups of near copies.
2. For what is not yet joined, each document enters the lists of its rarest retained values, as many
   as a pair at the threshold must share one of (prefix filter over the sketch). Only lists that
   hold more than one component count, and only pairs between components. Short lists give pairs;
   members of long ones are compared inside tasks, block against block.

The sketch of the union estimates the similarity and drops pairs that are clearly below; the exact
Jaccard on full shingle sets, rebuilt from the whole texts, decides. The union of all links gives
components; a component's first document is kept.

Defined results: null or empty text has an empty set, is linked with nothing and kept; a text of
fewer words than a shingle is one shingle; rows that repeat a key are one document, with its text or
with several, and whatever one of them is linked with, all are; a null key is never linked and its
component is null; an empty table gives an empty result. Only key and text are read.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.llm import worker
from coarsesample.llm.components import connected_components, local_roots
from coarsesample.runtime import broadcast_if_small, materialize

_U = np.uint64
_MIX = (_U(0x9E3779B97F4A7C15), _U(0xBF58476D1CE4E5B9), _U(0x94D049BB133111EB))


class _WordHashes(dict):
    """Word to its 64-bit hash; emptied when full."""

    def __missing__(self, word: bytes) -> int:
        value = xxhash.xxh3_64_intdigest(word)
        if len(word) < 64:
            self[word] = value
        return value


_known = _WordHashes()


def _finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _MIX[1]
    x = (x ^ (x >> _U(27))) * _MIX[2]
    return x ^ (x >> _U(31))


def shingle_set(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's word shingles.

    Words are runs without ASCII white space, A to Z in lower case.
    """
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, _U)
    worker.claim("near_text", _known.clear)
    if len(_known) > 300_000:
        _known.clear()
    h = np.fromiter(map(_known.__getitem__, words), _U, len(words))
    n = max(1, len(h) - width + 1)
    take = min(width, len(h))
    with np.errstate(over="ignore"):
        x = np.full(n, _U(take), _U)
        for i in range(take):
            x = _finish(x * _MIX[0] + h[i : i + n])
    return np.unique(x)


def _signed(x: np.ndarray) -> np.ndarray:
    """Same order in Spark's longs."""
    return (x ^ _U(1 << 63)).view(np.int64)


def sketches(docs: DataFrame, width: int, k: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, fingerprint of the whole set, sketch (ascending)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in (whole.iloc[at : at + 500] for whole in batches for at in range(0, len(whole), 500)):
            sets = [shingle_set(t, width) for t in batch["text"]]
            yield pd.DataFrame({"doc_id": batch["doc_id"], "n_shingles": [len(s) for s in sets], "fingerprint": [hashlib.md5(s.tobytes()).digest() for s in sets], "sketch": [_signed(s[:k]) for s in sets]})

    given = docs.select(F.col(key).cast("string").alias("doc_id"), F.col(text).alias("text"))
    return given.mapInPandas(run, "doc_id string, n_shingles long, fingerprint binary, sketch array<long>").withColumn("doc_id", F.col("doc_id").cast("long"))


def prefix_length(threshold: float, k: int) -> int:
    """Retained values of which a pair at the threshold shares one, but for a chance below one in 10^5."""
    miss = 1 - threshold
    return min(k, math.ceil(miss * k + 5 * math.sqrt(miss * threshold * k)) + 1)


def _sizes_fit(a, b, num: int, den: int):
    """Sets whose sizes differ too much can't reach the threshold."""
    return F.least(a, b) * den >= F.greatest(a, b) * num


def _once(rows: DataFrame) -> DataFrame:
    """Rows that repeat a key and its text, once."""
    return rows.withColumn("__text", F.xxhash64("text")).dropDuplicates(["doc_id", "__text"]).drop("__text")


def _confirm(pairs: DataFrame, reps: DataFrame, docs: DataFrame, width: int, num: int, den: int, k: int, tag: str) -> DataFrame:
    """Those of ``pairs`` (a, b) that reach the threshold on full sets, as edges u, v."""
    threshold = num / den
    side = lambda name: reps.select(F.col("doc_id").alias(name), F.col("sketch").alias(f"s{name}"))
    held = pairs.join(side("a"), "a").join(side("b"), "b")
    union = F.slice(F.array_sort(F.array_union("sa", "sb")), 1, k)
    held = held.withColumn("u", union).withColumn("shared", F.size(F.array_intersect(F.array_intersect("u", "sa"), "sb")) / F.size("u"))
    slack = F.lit(4.5 * math.sqrt(threshold * (1 - threshold))) / F.sqrt(F.size("u"))
    likely = materialize(held.where(F.col("shared") >= F.lit(threshold) - slack).select("a", "b"), f"likely-{tag}")
    wanted = materialize(likely.select(F.col("a").alias("doc_id")).unionByName(likely.select(F.col("b").alias("doc_id"))).distinct(), f"wanted-{tag}")
    texts = _once(docs.join(broadcast_if_small(wanted), "doc_id", "left_semi"))
    both = likely.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in (whole.iloc[at : at + 1000] for whole in batches for at in range(0, len(whole), 1000)):
            made: dict = {}
            found = []
            for a, b, ta, tb in batch[["a", "b", "ta", "tb"]].itertuples(index=False):
                if len(made) > 2000:
                    made.clear()
                for t in (ta, tb):
                    if t not in made:
                        made[t] = shingle_set(t, width)
                x, y = made[ta], made[tb]
                shared = len(np.intersect1d(x, y, assume_unique=True))
                if shared * den >= (len(x) + len(y) - shared) * num:
                    found.append((a, b))
            yield pd.DataFrame(found, columns=["u", "v"], dtype="int64")

    return materialize(both.mapInPandas(run, "u long, v long"), f"links-{tag}")


def _long_lists(lists: DataFrame, docs: DataFrame, width: int, num: int, den: int, block: int = 512) -> DataFrame:
    """Links between components inside lists of many members, without listing pairs.

    Clouds of near copies fill many long lists with the same members. Members that long lists tie
    together form a group; a group is dealt to blocks by a hash, and each pair of blocks is one task
    that counts shared shingles by a matrix product and gives back a spanning forest.
    """
    ties = lists.where("doc_id <> head").select(F.col("doc_id").alias("u"), F.col("head").alias("v")).distinct()
    groups = connected_components(ties).withColumnRenamed("node", "doc_id").withColumnRenamed("component", "bunch")
    sizes = groups.groupBy("bunch").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    members = lists.groupBy("doc_id").agg(F.min("component").alias("component")).join(groups, "doc_id").join(sizes, "bunch")
    members = materialize(members.withColumn("own", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int")), "bunches")
    texts = _once(docs.join(broadcast_if_small(members), "doc_id"))
    dealt = texts.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.withColumn("low", F.least("own", "other")).withColumn("high", F.greatest("own", "other"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        empty = pd.DataFrame({"u": [], "v": []}, dtype="int64")
        if group["component"].nunique() < 2:
            return empty
        group = group.sort_values("doc_id")
        ids, comp, own = group["doc_id"].to_numpy(np.int64), group["component"].to_numpy(np.int64), group["own"].to_numpy()
        sets = [shingle_set(t, width) for t in group["text"]]
        n = np.array([len(s) for s in sets], np.int64)
        _, where, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        row = np.repeat(np.arange(len(ids)), n)
        seat = np.cumsum(count > 1) - 1
        held = count[where] > 1
        row, col = row[held], seat[where[held]]
        order = np.argsort(col, kind="stable")
        row, col = row[order], col[order]
        shared = np.zeros((len(ids), len(ids)), np.float32)
        for at in range(0, int(seat[-1]) + 1 if len(seat) else 0, 4096):
            a, b = np.searchsorted(col, [at, at + 4096])
            part = np.zeros((len(ids), 4096), np.float32)
            part[row[a:b], col[a:b] - at] = 1
            shared += part @ part.T
        linked = shared * den >= (n[:, None] + n[None] - shared) * num
        linked &= comp[:, None] != comp[None]
        if group["low"].iloc[0] != group["high"].iloc[0]:
            linked &= own[:, None] != own[None]
        i, j = np.nonzero(linked)
        root = local_roots(len(ids), i, j)
        tied = root != np.arange(len(ids))
        return pd.DataFrame({"u": ids[tied], "v": ids[root[tied]]})

    return materialize(dealt.select("bunch", "low", "high", "own", "doc_id", "component", "text").groupBy("bunch", "low", "high").applyInPandas(run, "u long, v long"), "links-long")


def _same_key(usable: DataFrame, classes: DataFrame) -> DataFrame:
    """Links between the classes of a key that has several texts, as edges u, v of their first members."""
    several = usable.groupBy("doc_id").agg(F.min("fingerprint").alias("low"), F.max("fingerprint").alias("high")).where("low <> high").select("doc_id")
    tied = usable.select("doc_id", "fingerprint").join(several, "doc_id", "left_semi").join(classes, "fingerprint").select("doc_id", "rep").distinct()
    heads = tied.groupBy("doc_id").agg(F.min("rep").alias("u"))
    return tied.join(heads, "doc_id").where("u <> rep").select("u", F.col("rep").alias("v"))


def near_duplicates(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100, k: int = 64, first_keys: int = 10, short_list: int = 32, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row; links where den * shared >= num * union."""
    given = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    sets = materialize(sketches(given, width, k), "sketches")
    usable = sets.where("n_shingles > 0 and doc_id is not null")
    classes = materialize(usable.groupBy("fingerprint").agg(F.min("doc_id").alias("rep")), "classes")
    firsts = classes.select("fingerprint", F.col("rep").alias("doc_id"))
    reps = materialize(usable.join(firsts, ["doc_id", "fingerprint"], "left_semi").dropDuplicates(["doc_id", "fingerprint"]).select("doc_id", "n_shingles", "sketch"), "reps")

    # Step 1: every member of a two-value list against the list's first member.
    two = F.zip_with(F.slice("sketch", 1, first_keys), F.slice("sketch", 2, first_keys), lambda x, y: F.xxhash64(x, F.coalesce(y, F.lit(0))))
    keyed = reps.select(F.explode(two).alias("list"), F.col("doc_id").alias("b"), F.col("n_shingles").alias("nb"))
    heads = keyed.groupBy("list").agg(F.min(F.struct("b", "nb")).alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1").select("list", F.col("head.b").alias("a"), F.col("head.nb").alias("na"))
    stars = keyed.join(heads, "list").where((F.col("a") < F.col("b")) & _sizes_fit(F.col("na"), F.col("nb"), num, den)).select("a", "b").distinct()
    links = _confirm(stars, reps, given, width, num, den, k, "stars")
    joined = connected_components(links.unionByName(_same_key(usable, classes)))

    # Step 2: lists of rare retained values, between components only.
    posted = reps.select(F.explode("sketch").alias("value"), "doc_id")
    shared = posted.groupBy("value").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    rare = posted.join(shared, "value").groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("df", "value"))).alias("found"))
    prefix = F.lit(prefix_length(num / den, k))
    rare = rare.join(reps.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")), "doc_id")
    alone = F.least("n_shingles", F.lit(k)) - F.size("found")
    whole = F.floor(F.col("n_shingles") * (den - num) / den) + 1
    # The short prefix holds where every partner that can reach the threshold has its whole set for a sketch.
    longest = F.when(F.col("n_shingles") * den <= k * num, F.least(whole, prefix)).otherwise(prefix)
    entered = rare.select("doc_id", "n_shingles", F.explode(F.slice("found", F.lit(1), F.greatest(longest - alone, F.lit(0)).cast("int"))).alias("at"))
    entered = entered.join(joined.withColumnRenamed("node", "doc_id"), "doc_id", "left").select(F.col("at.value").alias("value"), "doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component"))
    entered = materialize(entered, "entered")
    whole_lists = entered.groupBy("value").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min("doc_id").alias("head"), F.count(F.lit(1)).alias("n")).where("low < high")
    lists = materialize(entered.join(whole_lists.select("value", "head", "n"), "value"), "lists")
    short = lists.where(F.col("n") <= short_list)
    other = short.select("value", F.col("doc_id").alias("b"), F.col("n_shingles").alias("nb"), F.col("component").alias("cb"))
    met = short.select("value", F.col("doc_id").alias("a"), F.col("n_shingles").alias("na"), F.col("component").alias("ca")).join(other, "value")
    rest = met.where((F.col("a") < F.col("b")) & (F.col("ca") != F.col("cb")) & _sizes_fit(F.col("na"), F.col("nb"), num, den)).select("a", "b").distinct()
    more = _confirm(rest, reps, given, width, num, den, k, "rare").unionByName(_long_lists(lists.where(F.col("n") > short_list), given, width, num, den))
    bridged = more.join(joined.select(F.col("node").alias("u"), F.col("component").alias("cu")), "u", "left").join(joined.select(F.col("node").alias("v"), F.col("component").alias("cv")), "v", "left")
    bridges = bridged.select(F.coalesce("cu", "u").alias("u"), F.coalesce("cv", "v").alias("v"))
    merged = connected_components(bridges)

    # A class takes its first member's component, a component that of the bridges.
    label = (
        classes.join(joined.withColumnRenamed("node", "rep"), "rep", "left")
        .select("fingerprint", F.coalesce("component", "rep").alias("node"))
        .join(merged, "node", "left")
        .select("fingerprint", F.coalesce("component", "node").alias("component_id"))
    )
    out = sets.select("doc_id", "n_shingles", "fingerprint").join(label, "fingerprint", "left")
    mine = F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), mine).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
