"""Partial answers of many queries in one scan: rows meet all queries in blocks of Arrow columns.

As columns of an SQL aggregation, queries cost a job for every few of them, however small the table.
Here a scan hands its rows to Python tasks, which evaluate each distinct leaf of the predicates once a
block and count by codes of partition and group. Predicates keep SQL's logic with nulls; a leaf of
another kind than number or text against constants is a boolean column that Spark computes.
"""

from __future__ import annotations

import json
import math
import pickle
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from coarsesample.plans.query import And, Clause, In, Like, Not, Or, QuerySpec, to_sql

BLOCK_ROWS = 65_536
SEEN = -1
COMPARE = {"=": pc.equal, "<>": pc.not_equal, "<": pc.less, "<=": pc.less_equal, ">": pc.greater, ">=": pc.greater_equal}
SMALL_NUMBERS = (T.ByteType, T.ShortType, T.IntegerType, T.FloatType, T.DoubleType)


class Scan:
    """The columns that some queries need of a row, as SQL, and what to count with them; can be sent to tasks."""

    def __init__(self, df: DataFrame, queries: list[tuple[int, QuerySpec]]):
        self.types = {f.name: f.dataType for f in df.schema}
        self.names: dict[str, str] = {"part_id": "part_id"}
        self.leaves: dict = {}
        self.sets: dict[tuple, list[int]] = {}
        self.groups: dict[tuple, list[str]] = {}
        self.asked: dict[int, tuple] = {}
        for i, q in queries:
            self.sets.setdefault(q.group_by, []).append(i)
            self.groups[q.group_by] = [self._column(self._as_text(c)) for c in q.group_by]
            parts = []
            for a in q.aggs:
                x = None if a.expr == "*" else self._column(f"CAST({a.expr} AS DOUBLE)")
                kinds = {"sum": ("sum",), "count": ("count",), "avg": ("sum", "count")}[a.fn]
                parts += [(kind, x, a.where) for kind in kinds]
            self.asked[i] = (q.where, parts)
            for p in (q.where, *(a.where for a in q.aggs)):
                self._note(p)

    def rows(self, df: DataFrame) -> DataFrame:
        return df.selectExpr(*[f"{sql} AS {name}" for sql, name in self.names.items()])

    def _column(self, sql: str) -> str:
        return self.names.setdefault(sql, f"c{len(self.names)}")

    def _as_text(self, c: str) -> str:
        real = isinstance(self.types.get(c), T.FloatType | T.DoubleType)
        return f"CAST(CASE WHEN {c} = 0 THEN 0 ELSE {c} END AS STRING)" if real else f"CAST({c} AS STRING)"

    def _note(self, p) -> None:
        match p:
            case None:
                return
            case And(of) | Or(of):
                for x in of:
                    self._note(x)
            case Not(of):
                self._note(of)
            case _ if p not in self.leaves:
                self.leaves[p] = self._leaf(p)

    def _leaf(self, p) -> tuple[str, str]:
        """How a leaf is evaluated, and on which column."""
        kind = self.types.get(getattr(p, "col", None))
        values = (p.value,) if isinstance(p, Clause) else p.values if isinstance(p, In) else (p.pattern,) if isinstance(p, Like) else ()
        if values and isinstance(kind, T.StringType) and all(isinstance(v, str) and "\\" not in v for v in values):
            return "text", self._column(p.col)
        if values and all(isinstance(v, int | float) and not isinstance(v, bool) and math.isfinite(v) and abs(v) < 2**63 for v in values):
            if isinstance(kind, SMALL_NUMBERS):
                return "number", self._column(f"CAST({p.col} AS DOUBLE)")
            if isinstance(kind, T.LongType) and (getattr(p, "op", "=") not in ("=", "<>") or all(float(v).is_integer() for v in values)):
                return "whole", self._column(p.col)
        return "sql", self._column(f"({to_sql(p)})")


def compact(code: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes in order and each row's place among them; by a table unless ``n``, above all codes, is far more than the rows."""
    if n > 16 * len(code) + 1024:
        return np.unique(code, return_inverse=True)
    seen = np.zeros(n, bool)
    seen[code] = True
    found = np.flatnonzero(seen)
    place = np.empty(n, np.int64)
    place[found] = np.arange(len(found))
    return found, place[code]


class Block:
    """Some rows as Arrow columns; a leaf's truth and a columnset's groups are found once."""

    def __init__(self, scan: Scan, rows: pa.RecordBatch):
        self.scan, self.rows, self.n = scan, rows, rows.num_rows
        self.part = rows.column("part_id").to_numpy(zero_copy_only=False).astype(np.int64)
        self._truths: dict = {}
        self._encoded: dict = {}
        self._numbers: dict = {}
        self._places = None

    def rising(self) -> Iterator[Block]:
        """The block in pieces in which partitions rise: files may follow each other in any order."""
        cuts = [0, *(np.flatnonzero(np.diff(self.part) < 0) + 1).tolist(), self.n]
        for low, high in zip(cuts, cuts[1:], strict=False):
            yield self if high - low == self.n else Block(self.scan, self.rows.slice(low, high - low))

    def places(self) -> tuple[np.ndarray, np.ndarray]:
        """The partitions in order, and each row's place among them."""
        if self._places is None:
            low = int(self.part.min())
            found, place = compact(self.part - low, int(self.part.max()) - low + 1)
            self._places = found + low, place
        return self._places

    def truth(self, p):
        if p not in self._truths:
            self._truths[p] = self._truth(p)
        return self._truths[p]

    def _truth(self, p):
        match p:
            case And(of) | Or(of):
                both = isinstance(p, And)
                return reduce(pc.and_kleene if both else pc.or_kleene, map(self.truth, of), pa.scalar(both)) if of else pa.array(np.full(self.n, both))
            case Not(of):
                return pc.invert(self.truth(of))
        kind, name = self.scan.leaves[p]
        if kind == "sql":
            return self.rows.column(name)
        if kind == "text":
            code, words = self._codes(name)
            return pc.take(self._holds(p, words, str), code)
        # whole numbers are compared as such: between two of them, a constant stands for the next one that is on its side
        return self._holds(p, self.rows.column(name), float if kind == "number" else math.ceil if getattr(p, "op", "=") in ("<", ">=") else math.floor)

    def _holds(self, p, x: pa.Array, constant) -> pa.Array:
        if isinstance(p, Like):
            out = pc.match_like(x, p.pattern)
        elif isinstance(p, In):
            out = reduce(pc.or_, (pc.equal(x, constant(v)) for v in p.values))
        else:
            out = COMPARE[p.op](x, constant(p.value))
            if p.op in (">", ">=") and pa.types.is_floating(x.type):  # to Spark, no number is above NaN
                out = pc.or_(out, pc.is_nan(x))
        return pc.invert(out) if getattr(p, "negated", False) else out

    def where(self, p) -> np.ndarray | None:
        """Whether a predicate is true of each row; None if it is of all."""
        return None if p is None else pc.fill_null(self.truth(p), False).to_numpy(zero_copy_only=False)

    def _codes(self, name: str) -> tuple[pa.Array, pa.Array]:
        if name not in self._encoded:
            held = self.rows.column(name).dictionary_encode()
            self._encoded[name] = held.indices, held.dictionary
        return self._encoded[name]

    def groups(self, cols: tuple) -> tuple[list[str], np.ndarray]:
        """The groups' keys, and each row's place among them."""
        keys, code = [()], np.zeros(self.n, np.int64)
        for name in self.scan.groups[cols]:
            index, words = self._codes(name)
            values = [*words.to_pylist(), None]
            code = code * len(values) + pc.fill_null(index, len(words)).to_numpy(zero_copy_only=False)
            found, code = compact(code, len(keys) * len(values))
            keys = [(*keys[u // len(values)], values[u % len(values)]) for u in found.tolist()]
        return [json.dumps(k, ensure_ascii=False) for k in keys], code

    def _number(self, name: str) -> tuple[np.ndarray, np.ndarray | None]:
        """A column's values, nulls as zero, and where they are not null (None: everywhere)."""
        if name not in self._numbers:
            x = self.rows.column(name)
            valid = x.is_valid().to_numpy(zero_copy_only=False) if x.null_count else None
            self._numbers[name] = pc.fill_null(x, 0.0).to_numpy(zero_copy_only=False), valid
        return self._numbers[name]

    def sums(self, i: int, code: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Matching rows of a query by code, and its parts."""
        where, parts = self.scan.asked[i]
        keep = self.where(where)
        at = None if keep is None else np.flatnonzero(keep)
        own = code if at is None else code[at]
        rows, out = np.bincount(own, minlength=n), np.empty((n, len(parts)))
        for j, (kind, name, test) in enumerate(parts):
            if test is None:
                here, to = at, own
            else:
                here = np.flatnonzero(self.where(test) if keep is None else keep & self.where(test))
                to = code[here]
            if name is None:
                out[:, j] = rows if test is None else np.bincount(to, minlength=n)
                continue
            x, valid = self._number(name)
            if kind == "sum":
                out[:, j] = np.bincount(to, x if here is None else x[here], n)
            elif valid is None:
                out[:, j] = rows if test is None else np.bincount(to, minlength=n)
            else:
                out[:, j] = np.bincount(to[valid if here is None else valid[here]], minlength=n)
        return rows, out


def blocks(scan: Scan, batches: Iterator[pa.RecordBatch]) -> Iterator[Block]:
    """A task's rows, ``BLOCK_ROWS`` at a time or a little more."""
    held, n = [], 0
    whole = lambda: Block(scan, pa.Table.from_batches(held).combine_chunks().to_batches()[0])
    for b in batches:
        if b.num_rows:
            held.append(b)
            n += b.num_rows
        if n >= BLOCK_ROWS:
            yield whole()
            held, n = [], 0
    if held:
        yield whole()


class Totals:
    """Parts by group of a columnset's queries, added up."""

    def __init__(self):
        self.index: dict[str, int] = {}
        self.x: dict[int, np.ndarray] = {}

    def add(self, keys: list[str], each: dict[int, np.ndarray]) -> None:
        at = np.array([self.index.setdefault(k, len(self.index)) for k in keys], int)
        for i, x in each.items():
            held = self.x.get(i)
            if held is None or len(held) < len(self.index):
                more = np.zeros((2 * len(self.index), x.shape[1]))
                if held is not None:
                    more[: len(held)] = held
                held = self.x[i] = more
            held[at] += x

    def pack(self) -> bytes:
        return pickle.dumps((list(self.index), {i: x[: len(self.index)] for i, x in self.x.items()}))


def totals_of(scan: Scan, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, bytes]]:
    """Number and packed Totals of each columnset, over a task's rows."""
    held = [Totals() for _ in scan.sets]
    for block in blocks(scan, batches):
        for t, (cols, ids) in zip(held, scan.sets.items(), strict=True):
            keys, code = block.groups(cols)
            t.add(keys, {i: block.sums(i, code, len(keys))[1] for i in ids})
    for s, t in enumerate(held):
        if t.index:
            yield s, t.pack()


def _shares(x: np.ndarray, total: np.ndarray) -> np.ndarray:
    return np.maximum(0, np.where(total != 0, x / np.where(total == 0, 1, total), 0).max(1))


def shares_of(scan: Scan, totals: list[tuple[dict, dict]], batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """query, partitions and their largest shares of any group's total, of rows that are whole partitions one after the other.

    A block's last partition may go on in the next: its parts are kept by group until it ends. Partitions
    are told as they begin, under the query ``SEEN``, so that one that lies in several places can be found.
    """
    open_part, kept = None, {i: np.zeros_like(x) for _, each in totals for i, x in each.items()}
    for block in (b for whole in blocks(scan, batches) for b in whole.rising()):
        parts, place = block.places()
        goes_on = open_part == parts[0]
        yield SEEN, parts[int(goes_on) :], np.ones(len(parts) - int(goes_on))
        for (cols, ids), (index, total) in zip(scan.sets.items(), totals, strict=True):
            keys, code = block.groups(cols)
            found, at = compact(place * len(index) + np.array([index[k] for k in keys])[code], len(parts) * len(index))
            group = found % len(index)
            begins = np.searchsorted(found // len(index), np.arange(len(parts) + 1))
            for i in ids:
                x, low, high = block.sums(i, at, len(found))[1], begins[int(goes_on)], begins[-2]
                if goes_on:
                    kept[i][group[:low]] += x[:low]
                    if len(parts) == 1:
                        continue
                if open_part is not None:
                    yield i, np.array([open_part]), _shares(kept[i], total[i]).max(keepdims=True)
                if low < high:
                    own = slice(int(goes_on), len(parts) - 1)
                    yield i, parts[own], np.maximum.reduceat(_shares(x[low:high], total[i][group[low:high]]), begins[own] - low)
                kept[i][:] = 0
                kept[i][group[high:]] = x[high:]
        open_part = parts[-1]
    if open_part is not None:
        for _, total in totals:
            for i, t in total.items():
                yield i, np.array([open_part]), _shares(kept[i], t).max(keepdims=True)


def parts_by_group(scan: Scan, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, bytes]]:
    """query and its packed keys, group numbers, partitions, rows and parts, of every block's partitions and groups that match."""
    for block in blocks(scan, batches):
        parts, place = block.places()
        for cols, ids in scan.sets.items():
            keys, code = block.groups(cols)
            found, at = compact(place * len(keys) + code, len(parts) * len(keys))
            for i in ids:
                rows, x = block.sums(i, at, len(found))
                own = np.flatnonzero(rows)
                if len(own):
                    used, group = np.unique(found[own] % len(keys), return_inverse=True)
                    yield i, pickle.dumps(([keys[u] for u in used], group.astype(np.int32), parts[found[own] // len(keys)], rows[own], x[own]))


def united(packed: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Groups by the order of their keys, partitions, rows and parts of a query, once for each partition and group, in that order."""
    each = [pickle.loads(p) for p in packed]
    keys = sorted(set().union(*(e[0] for e in each)))
    rank = {k: r for r, k in enumerate(keys)}
    group = np.concatenate([np.array([rank[k] for k in e[0]])[e[1]] for e in each])
    part = np.concatenate([e[2] for e in each])
    parts, place = np.unique(part, return_inverse=True)
    found, at = np.unique(place * len(keys) + group, return_inverse=True)
    rows, x = np.concatenate([e[3] for e in each]), np.concatenate([e[4] for e in each])
    total = np.stack([np.bincount(at, x[:, j], len(found)) for j in range(x.shape[1])], axis=1)
    return found % len(keys), parts[found // len(keys)], np.bincount(at, rows, len(found)), total
