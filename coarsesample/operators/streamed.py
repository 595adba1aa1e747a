"""Statistics of partitions whose rows come one after the other: sorted runs of Arrow columns instead of a sketch update a value.

As aggregates of a Spark job, thirty columns cost some ten sketch updates each for every row. Here a
block's rows of a partition are counted by value in one sort a column. State is bounded: a column
holds its distinct values with their counts, and past ``MOST`` of them the most frequent, ``MOST``
points of its distribution and the lowest hashes.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

MOST = 65_536  # distinct values of a column in a partition that are counted exactly
HASHES = 4096
TOP = 100
BLOCK_ROWS = 65_536


def _joined(values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values once each, in order, with their counts added."""
    found, at = np.unique(values, return_inverse=True)
    return found, np.bincount(at, counts, len(found))


def _mixed(x: np.ndarray) -> np.ndarray:
    """Numbers as even 64-bit hashes."""
    h = (x + 0.0).view(np.uint64).copy()
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        h = (h ^ (h >> np.uint64(shift))) * np.uint64(factor)
    return h ^ (h >> np.uint64(31))


class Numbers:
    """Numbers of a column in one partition."""

    def __init__(self, most: int = MOST):
        self.most, self.n, self.sum, self.sum_sq = most, 0, 0.0, 0.0
        self.low, self.high, self.logs = None, None, np.array([0.0, 0.0])
        self.values, self.counts = np.empty(0), np.empty(0)
        self.points = self.hashes = None

    def add(self, x: np.ndarray) -> None:
        """Some more values, none of them null."""
        if len(x):
            self.sum, self.sum_sq = self.sum + float(x.sum()), self.sum_sq + float((x * x).sum())
            self.add_counts(*np.unique(x + 0.0, return_counts=True))

    def add_counts(self, values: np.ndarray, counts: np.ndarray) -> None:
        """Distinct values in order and how often each comes."""
        self.n += int(counts.sum())
        low, high = float(values[0]), float(values[-1])
        self.low = low if self.low is None or low < self.low or np.isnan(self.low) else self.low
        self.high = high if self.high is None or high > self.high or np.isnan(high) else self.high
        if self.low > 0:
            logs = np.log(values)
            self.logs += (logs * counts).sum(), (logs * logs * counts).sum()
        if self.points is not None:
            self._spill(values, counts)
        whole = _joined(np.concatenate([self.values, values]), np.concatenate([self.counts, counts])) if len(self.values) else (values, counts.astype(float))
        if len(whole[0]) > self.most:
            if self.points is None:
                self.points, self.hashes = (np.empty(0), np.empty(0)), np.empty(0, np.uint64)
                self._spill(*whole)
            kth = np.partition(whole[1], -self.most - 1)[-self.most - 1]
            kept = whole[1] > kth
            whole = whole[0][kept], whole[1][kept] - kth
        self.values, self.counts = whole

    def _spill(self, values: np.ndarray, counts: np.ndarray) -> None:
        """To the points of the distribution and the lowest hashes, once values are too many."""
        self.hashes = np.unique(np.concatenate([self.hashes, _mixed(values)]))[:HASHES]
        points = _joined(np.concatenate([self.points[0], values]), np.concatenate([self.points[1], counts]))
        if len(points[0]) > 2 * self.most:
            ends = np.linspace(0, points[1].sum(), self.most + 1)[1:]
            last = np.unique(np.minimum(np.searchsorted(np.cumsum(points[1]), ends), len(points[0]) - 1))
            points = points[0][last], np.diff(np.cumsum(points[1])[last], prepend=0.0)
        self.points = points

    def distinct(self) -> float:
        if self.hashes is None:
            return float(len(self.values))
        return float(len(self.hashes)) if len(self.hashes) < HASHES else (HASHES - 1) * 2.0**64 / float(self.hashes[-1])

    def cuts(self, buckets: int) -> list[float]:
        """The values that end a bucket's share of the rows, but for the last."""
        values, counts = self.points or (self.values, self.counts)
        upto = np.cumsum(counts)
        ranks = np.ceil(np.arange(1, buckets) * upto[-1] / buckets - 1e-9)
        return values[np.searchsorted(upto, ranks)].tolist()

    def top(self) -> list[dict]:
        order = np.lexsort((self.values, -self.counts))[:TOP]
        return [{"item": v, "count": int(n)} for v, n in zip(self.values[order].tolist(), self.counts[order].tolist(), strict=True)]


class Texts:
    """Strings of a column in one partition; their order and distribution are those of their hashes."""

    def __init__(self, most: int = MOST):
        self.most, self.counts, self.lost = most, {}, False
        self.codes = Numbers(most)

    @property
    def n(self) -> int:
        return self.codes.n

    def add(self, words: list[str], codes: np.ndarray, counts: np.ndarray) -> None:
        if not words:
            return
        for w, n in zip(words, counts.tolist(), strict=True):
            self.counts[w] = self.counts.get(w, 0) + n
        self.codes.add_counts(*_joined(codes, counts))
        if len(self.counts) > self.most:
            kth = sorted(self.counts.values())[-self.most - 1]
            self.counts, self.lost = {w: n - kth for w, n in self.counts.items() if n > kth}, True

    def distinct(self) -> float:
        return self.codes.distinct() if self.lost else float(len(self.counts))

    def top(self) -> list[dict]:
        return [{"item": w, "count": int(n)} for w, n in sorted(self.counts.items(), key=lambda e: (-e[1], e[0]))[:TOP]]


class Codes:
    """First 32 bits of the md5 of strings, as hash32() has them; some are kept."""

    def __init__(self):
        self.known: dict[str, float] = {}

    def of(self, words: list[str]) -> np.ndarray:
        if len(self.known) > 500_000:
            self.known.clear()
        for w in words:
            if w not in self.known:
                self.known[w] = float(int.from_bytes(md5(w.encode(), usedforsecurity=False).digest()[:4], "big"))
        return np.array([self.known[w] for w in words], float)


def fields(numeric: tuple[str, ...], strings: tuple[str, ...]) -> str:
    """Schema of a partition's row."""
    out = ["part_id int", "n_rows long"]
    for c in (*numeric, *strings):
        item = "string" if c in strings else "double"
        out += [f"{c}__min double", f"{c}__max double", f"{c}__n long", f"{c}__cuts array<double>", f"{c}__ndv double", f"{c}__top array<struct<item:{item},count:long>>"]
        if c not in strings:
            out += [f"{c}__rows long", *[f"{c}__{m} double" for m in ("mean", "mean_sq", "log_min", "log_max", "log_mean", "log_mean_sq")]]
    return ", ".join(out)


def statistics(numeric: tuple[str, ...], strings: tuple[str, ...], buckets: int, batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """A row for each run of equal part_id. Log columns are empty where a partition has a value that isn't above zero."""
    now, n_rows, held, codes = None, 0, {}, Codes()

    def row() -> pa.RecordBatch:
        out = {"part_id": now, "n_rows": n_rows}
        for c, s in held.items():
            x = s.codes if isinstance(s, Texts) else s
            out |= {f"{c}__min": x.low, f"{c}__max": x.high, f"{c}__n": x.n, f"{c}__cuts": x.cuts(buckets) if x.n else None, f"{c}__ndv": s.distinct(), f"{c}__top": s.top()}
            if x is s:
                out |= {f"{c}__rows": n_rows, f"{c}__mean": x.sum / x.n if x.n else None, f"{c}__mean_sq": x.sum_sq / x.n if x.n else None}
                if x.n and x.low > 0:
                    out |= {f"{c}__log_min": float(np.log(x.low)), f"{c}__log_max": float(np.log(x.high)), f"{c}__log_mean": x.logs[0] / x.n, f"{c}__log_mean_sq": x.logs[1] / x.n}
        return pa.RecordBatch.from_pylist([out], schema)

    for block in _blocks(batches):
        part = block.column("part_id").to_numpy(zero_copy_only=False)
        ends = np.append(np.flatnonzero(np.diff(part)) + 1, len(part))
        spans = list(zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True))
        numbers, texts = {}, {}
        for c in numeric:
            x = block.column(c)
            numbers[c] = pc.fill_null(x, 0.0).to_numpy(zero_copy_only=False), x.is_valid().to_numpy(zero_copy_only=False) if x.null_count else None
        for c in strings:
            coded = block.column(c).dictionary_encode()
            words = coded.dictionary.to_pylist()
            texts[c] = np.array(words, object), codes.of(words), pc.fill_null(coded.indices, len(words)).to_numpy(zero_copy_only=False)
        for begin, end in spans:
            if now is None or part[begin] != now:
                if now is not None:
                    yield row()
                now, n_rows = int(part[begin]), 0
                held = {c: Numbers() for c in numeric} | {c: Texts() for c in strings}
            n_rows += end - begin
            for c, (x, valid) in numbers.items():
                held[c].add(x[begin:end] if valid is None else x[begin:end][valid[begin:end]])
            for c, (words, code, at) in texts.items():
                counts = np.bincount(at[begin:end], minlength=len(words))[: len(words)]
                some = np.flatnonzero(counts)
                held[c].add(words[some].tolist(), code[some], counts[some])
    if now is not None:
        yield row()


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held, n = [], 0
    for b in batches:
        if b.num_rows:
            held.append(b)
            n += b.num_rows
        if n >= BLOCK_ROWS:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, n = [], 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
