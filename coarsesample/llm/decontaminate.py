"""Benchmark decontamination: a BM25 inverted index of test items, searched with block-max WAND.

Every passage of every document is a query. An item's score is its BM25 sum over the passage's
distinct terms, divided by the sum over the item's own terms, so 1 means that all of it is there.
Posting lists are cut into blocks of items that hold their largest impact. For all passages of a text
at once these block maxima are summed: a passage where no block reaches the threshold has no match,
and most end there. The rest go through WAND, which skips by the same maxima. Items above the
threshold are verified: five-word shingles of the item's question and of its answer must lie in the
passage. Passages are two steps long and start at every step, which is the longest item's length,
so each occurrence lies whole in one.

The index holds the benchmark only. Its size is checked; a benchmark over ``slice_chars`` is searched
in slices. Scores and passages don't depend on the slices: item count, mean and longest length and the
document frequencies are those of the whole benchmark, counted on the executors, and a slice gets the
frequencies of its own words only.

Defined results: null and empty texts match nothing; items without words are left out; repeated
items each match; an item shorter than five words must occur as a whole; a null key is null in the
result, and a document without a key is dropped by drop_leaks like any other; an empty table gives an
empty result.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.runtime import materialize

_WORD = re.compile(r"\w+")
_SENTENCE = re.compile(r"(?<=[.!?])\s+|\n")


def words_of(text: str | None) -> list[str]:
    """Lower-case words."""
    return _WORD.findall((text or "").lower())


def question_and_answer(text: str) -> tuple[list[str], list[str]]:
    """An item's last sentence is its answer; a single sentence is cut at three quarters."""
    parts = [w for w in (words_of(p) for p in _SENTENCE.split(text)) if w]
    if len(parts) > 1:
        return [w for p in parts[:-1] for w in p], parts[-1]
    words = parts[0] if parts else []
    cut = max(1, len(words) * 3 // 4)
    return words[:cut], words[cut:]


def shingles(words: list[str], width: int = 5) -> set[tuple]:
    """Distinct runs of ``width`` words; a shorter text is one run."""
    if not words:
        return set()
    width = min(width, len(words))
    return set(zip(*(words[i:] for i in range(width)), strict=False))


@dataclass
class Totals:
    """What a slice has to know of the whole benchmark: items, their mean and longest length, items by word."""

    items: int
    mean: float
    longest: int
    df: dict[str, int] = field(default_factory=dict)


class BlockMaxIndex:
    """Impact-ordered bounds over document-ordered posting lists."""

    def __init__(self, items: list[tuple[int, str]], threshold: float = 0.65, k1: float = 1.2, b: float = 0.75, block: int = 4, totals: Totals | None = None):
        self.threshold, self.block = threshold, block
        split = [(i, question_and_answer(t)) for i, t in items]
        split = [(i, q, a) for i, (q, a) in split if q or a]
        self.ids = [i for i, _, _ in split]
        self.parts = [(q, a, shingles(q), shingles(a)) for _, q, a in split]
        counts = [Counter(q + a) for _, q, a in split]
        sizes = [c.total() for c in counts]
        totals = totals or Totals(len(counts), sum(sizes) / max(1, len(counts)), max(sizes, default=0), Counter(t for c in counts for t in c))
        n, mean, self.longest = totals.items, totals.mean, totals.longest
        idf = {t: math.log(1 + (n - d + 0.5) / (d + 0.5)) for t, d in totals.df.items()}
        lists: dict[str, list[tuple[int, float]]] = {}
        for at, c in enumerate(counts):
            norm = k1 * (1 - b + b * c.total() / mean)
            impact = {t: idf[t] * f * (k1 + 1) / (f + norm) for t, f in c.items()}
            own = sum(impact.values()) or 1.0
            for t, x in impact.items():
                lists.setdefault(t, []).append((at, x / own))
        self.lists = {t: (np.array([d for d, _ in p]), np.array([s for _, s in p])) for t, p in lists.items()}
        self.row = {t: i for i, t in enumerate(sorted(lists))}
        self.most = np.zeros((len(self.row) + 1, max(1, math.ceil(len(self.ids) / block))), np.float32)
        for t, (d, s) in self.lists.items():
            np.maximum.at(self.most[self.row[t]], d // block, s)
        self.bounds = {t: (s.max(), np.maximum.reduceat(s, np.arange(0, len(s), block))) for t, (_, s) in self.lists.items()}

    def search(self, terms: set[str]) -> list[tuple[int, float]]:
        """Places of all items whose score reaches the threshold, with the score."""
        cursors = [[0, t, *self.lists[t], *self.bounds[t]] for t in terms if t in self.lists]
        found = []
        while True:
            cursors = [c for c in cursors if c[0] < len(c[2])]
            cursors.sort(key=lambda c: c[2][c[0]])
            bound, pivot = 0.0, -1
            for i, c in enumerate(cursors):
                bound += c[4]
                if bound >= self.threshold:
                    pivot = i
                    break
            if pivot < 0:
                return found
            item = cursors[pivot][2][cursors[pivot][0]]
            while pivot + 1 < len(cursors) and cursors[pivot + 1][2][cursors[pivot + 1][0]] == item:
                pivot += 1
            head = cursors[: pivot + 1]
            near = [c[0] + int(np.searchsorted(c[2][c[0] :], item)) for c in head]
            local = sum(c[5][p // self.block] for c, p in zip(head, near, strict=True) if p < len(c[2]))
            if local < self.threshold:
                ends = [c[2][min(len(c[2]) - 1, (p // self.block + 1) * self.block - 1)] for c, p in zip(head, near, strict=True) if p < len(c[2])]
                after = min([min(ends, default=item) + 1, *(c[2][c[0]] for c in cursors[pivot + 1 : pivot + 2])])
                after = max(after, item + 1)
            else:
                score = sum(c[3][p] for c, p in zip(head, near, strict=True) if p < len(c[2]) and c[2][p] == item)
                if score >= self.threshold:
                    found.append((int(item), float(score)))
                after = item + 1
            for c in head:
                c[0] += int(np.searchsorted(c[2][c[0] :], after))

    def verify(self, item: int, passage: list[str], least: float) -> tuple[float, float] | None:
        """Overlap of question and answer with a passage, if together they reach ``least`` and both are there."""
        q, a, qs, as_ = self.parts[item]
        by_width: dict[int, set] = {}

        def overlap(own: set) -> float:
            if not own:
                return 1.0
            width = len(next(iter(own)))
            if width not in by_width:
                by_width[width] = shingles(passage, width) if len(passage) >= width else set()
            return len(own & by_width[width]) / len(own)

        oq, oa = overlap(qs), overlap(as_)
        both = (oq * len(qs) + oa * len(as_)) / max(1, len(qs) + len(as_))
        return (oq, oa) if both >= least and oq > 0 and oa >= 0.5 else None

    def _bound_passages(self, words: list[str], step: int) -> np.ndarray:
        """First words of the passages (two steps long) of which some block of items may reach the threshold.

        The sum of a block's largest impacts over a passage's terms, once for each half of it, bounds
        every item of the block.
        """
        if not self.row:
            return np.zeros(0, np.int64)
        rows = np.fromiter(map(self.row.get, words, repeat(len(self.row))), np.int64, len(words))
        starts = np.arange(0, len(rows), step)
        once = np.unique(np.arange(len(rows)) // step * len(self.most) + rows)
        half = np.add.reduceat(self.most[once % len(self.most)], np.searchsorted(once, np.arange(len(starts)) * len(self.most)), axis=0)
        if len(half) > 1:
            half = half[:-1] + half[1:]
        return starts[: len(half)][(half >= self.threshold - 1e-4).any(axis=1)]

    def matches(self, text: str | None, least: float) -> list[tuple[int, float, float, float, int]]:
        """Best verified passage of each item found in a text, the first of equal ones: place, score, overlaps, first word."""
        words = words_of(text)
        if not words:
            return []
        step = max(32, self.longest)
        best: dict[int, tuple] = {}
        for start in self._bound_passages(words, step).tolist():
            passage = words[start : start + 2 * step]
            for item, score in self.search(set(passage)):
                seen, score = self.verify(item, passage, least), round(score, 9)
                if seen and (item not in best or (seen, score) > (best[item][2:4], best[item][1])):
                    best[item] = (item, score, *seen, start)
        return sorted(best.values())


def _item_words(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        found = [words_of(t) for t in batch["t"]]
        yield pd.DataFrame({"slice": batch["slice"], "n": [len(w) for w in found], "words": [sorted(set(w)) for w in found]})


def _indexes(benchmark: DataFrame, threshold: float, slice_chars: int, item: str) -> Iterator[tuple]:
    """Arguments of each slice's index: one for a benchmark up to ``slice_chars``."""
    items = benchmark.select(F.col(item).cast("long").alias("i"), F.coalesce(F.col("text"), F.lit("")).alias("t"))
    total = items.agg(F.sum(F.length("t"))).first()[0] or 0
    slices = max(1, math.ceil(total / slice_chars))
    held = lambda rows: sorted((-1 if r["i"] is None else r["i"], r["t"]) for r in rows.collect())
    if slices == 1:
        yield held(items), threshold, None
        return
    dealt = items.withColumn("slice", F.pmod(F.xxhash64("i", "t"), F.lit(slices)).cast("int"))
    counted = materialize(dealt.mapInPandas(_item_words, "slice int, n int, words array<string>").where("n > 0"), "benchmark")
    n, mean, longest = counted.agg(F.count(F.lit(1)), F.avg("n"), F.max("n")).first()
    words = counted.select("slice", F.explode("words").alias("word"))
    df = materialize(words.groupBy("word").agg(F.count(F.lit(1)).alias("df")), "frequencies")
    for s in range(slices):
        own = words.where(F.col("slice") == s).select("word").distinct().join(df, "word")
        yield held(dealt.where(F.col("slice") == s)), threshold, Totals(n or 0, mean or 0.0, longest or 0, {r["word"]: r["df"] for r in own.collect()})


def find_leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.65, least: float = 0.8, slice_chars: int = 4_000_000, key: str = "doc_id", text: str = "text", item: str = "item_id") -> DataFrame:
    """doc_id, item_id, score, question_overlap, answer_overlap, first_word: one row per document and item."""
    given = docs.select(F.col(key).cast("string").alias("doc_id"), F.col(text).alias("text"))
    out = None
    for args in _indexes(benchmark, threshold, slice_chars, item):
        found = given.mapInPandas(_search(*args, least), "doc_id string, item_id long, score double, question_overlap double, answer_overlap double, first_word long")
        out = found if out is None else out.unionByName(found)
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def _search(items: list[tuple[int, str]], threshold: float, totals: Totals | None, least: float):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        index = BlockMaxIndex(items, threshold, totals=totals)
        for batch in batches:
            rows = [(doc, index.ids[m[0]], *m[1:]) for doc, t in zip(batch["doc_id"], batch["text"], strict=True) for m in index.matches(t, least)]
            yield pd.DataFrame(rows, columns=["doc_id", "item_id", "score", "question_overlap", "answer_overlap", "first_word"])

    return run


def _clean(items: list[tuple[int, str]], threshold: float, totals: Totals | None, least: float):
    """A column function of the text: whether no item of a slice is in it. Never null."""

    @F.pandas_udf("boolean")
    def clean(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        index = BlockMaxIndex(items, threshold, totals=totals)
        for texts in batches:
            yield pd.Series([not index.matches(t, least) for t in texts], dtype=bool)

    return clean


def drop_leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.65, least: float = 0.8, slice_chars: int = 4_000_000, text: str = "text", item: str = "item_id") -> DataFrame:
    """The documents in which no benchmark item was found: a filter on the text, without a join or shuffle."""
    for args in _indexes(benchmark, threshold, slice_chars, item):
        docs = docs.where(_clean(*args, least)(F.col(text)))
    return docs
