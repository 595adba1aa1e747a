"""Share of a partition's rows that a predicate keeps, from sketches alone.

Every leaf gets three numbers: a share that surely matches, an estimate, and a bound no partition
exceeds. The bound is zero only if the partition holds no matching row, so dropping partitions whose
bound is zero loses nothing. All are column expressions over one row per partition, in which
``<col>__hist`` is an array of buckets (lo, hi, n_rows, ndv), ``<col>__dict`` a complete dictionary
(value, n) or null, ``<col>__min`` / ``<col>__max`` exact extremes and ``n_rows`` the row count.
"""

from __future__ import annotations

import re
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coarsesample.plans.query import INF, And, In, Intervals, Like, Or, normalize


def _number(x: float) -> Column:
    return F.lit(float(x))


def _span_rows(hist: Column, span: tuple) -> tuple[Column, Column, Column]:
    """Rows surely inside, estimated and possibly inside one interval."""
    a, a_open, b, b_open = span

    def fold(value):
        return F.aggregate(hist, F.lit(0.0), lambda acc, h: acc + value(h))

    def touched(h: Column) -> Column:
        left = (h["hi"] > a) if a_open else (h["hi"] >= a)
        right = (h["lo"] < b) if b_open else (h["lo"] <= b)
        return left & right

    def covered(h: Column) -> Column:
        left = (h["lo"] > a) if a_open else (h["lo"] >= a)
        right = (h["hi"] < b) if b_open else (h["hi"] <= b)
        return left & right

    def share(h: Column) -> Column:
        if a == b:
            return h["n_rows"] / h["ndv"]
        width = h["hi"] - h["lo"]
        inside = F.least(h["hi"], _number(b)) - F.greatest(h["lo"], _number(a))
        return F.when(width == 0, h["n_rows"].cast("double")).otherwise(h["n_rows"] * inside / width)

    sure = fold(lambda h: F.when(covered(h), h["n_rows"].cast("double")).otherwise(0.0))
    guess = fold(lambda h: F.when(covered(h), h["n_rows"].cast("double")).when(touched(h), share(h)).otherwise(0.0))
    may = fold(lambda h: F.when(touched(h), h["n_rows"].cast("double")).otherwise(0.0))
    return sure, guess, may


def _intervals(leaf: Intervals) -> tuple[Column, Column, Column]:
    hist, n = F.col(f"{leaf.col}__hist"), F.col("n_rows")
    if not leaf.spans:
        return F.lit(0.0), F.lit(0.0), F.lit(0.0)
    each = [_span_rows(hist, s) for s in leaf.spans]
    sums = [reduce(lambda x, y: x + y, [e[i] for e in each]) for i in range(3)]
    low, high = F.col(f"{leaf.col}__min"), F.col(f"{leaf.col}__max")
    out = F.lit(True)
    for a, a_open, b, b_open in leaf.spans:
        miss = ((high <= a) if a_open else (high < a)) if a > -INF else F.lit(False)
        miss = miss | (((low >= b) if b_open else (low > b)) if b < INF else F.lit(False))
        miss = miss | F.coalesce(low == high, F.lit(False)) & ((low == a) & F.lit(a_open) | (low == b) & F.lit(b_open))
        out = out & F.coalesce(miss, F.lit(True))
    sure, guess, may = (F.least(F.coalesce(s, F.lit(0.0)) / n, F.lit(1.0)) for s in sums)
    clean = lambda x: F.when(out, 0.0).otherwise(x)
    return clean(sure), clean(guess), clean(may)


def _strings(col: str, test) -> tuple[Column, Column, Column]:
    """Exact where the dictionary is complete; else a tenth, and all that isn't null may match."""
    held, n = F.col(f"{col}__dict"), F.col("n_rows")
    rows = F.aggregate(F.filter(held, lambda d: test(d["value"])), F.lit(0.0), lambda acc, d: acc + d["n"])
    known = rows / n
    return F.coalesce(known, F.lit(0.0)), F.coalesce(known, F.lit(0.1)), F.coalesce(known, F.lit(1.0))


def bounds(leaf) -> tuple[Column, Column, Column]:
    """(surely, estimate, at most) of one leaf."""
    match leaf:
        case Intervals():
            return _intervals(leaf)
        case In(col, values, negated):
            listed = list(values)
            return _strings(col, lambda v: ~v.isin(listed) if negated else v.isin(listed))
        case Like(col, pattern, negated):
            return _strings(col, lambda v: ~v.like(pattern) if negated else v.like(pattern))
    raise TypeError(leaf)


def _like_regex(pattern: str) -> re.Pattern:
    """A LIKE pattern as a regular expression; a backslash takes the next sign as it is."""
    out, signs = [], iter(pattern)
    for c in signs:
        out.append(re.escape(next(signs, "")) if c == "\\" else {"%": ".*", "_": "."}.get(c, re.escape(c)))
    return re.compile("".join(out), re.S)


class ColumnArrays:
    """One column's sketches of all partitions as arrays: what bounds() says of a leaf, for many leaves at once.

    A batch of queries shares its columns, so each column's sketches are read once and a leaf is some
    array operations instead of an expression to plan.
    """

    def __init__(self, stats: DataFrame, col: str, parts: np.ndarray):
        held = [c for c in ("hist", "min", "max", "dict") if f"{col}__{c}" in stats.columns]
        rows = {r["part_id"]: r for r in stats.select("part_id", "n_rows", *[f"{col}__{c}" for c in held]).collect()}
        rows = [rows[int(p)] for p in parts]
        self.n = np.array([r["n_rows"] for r in rows], float)
        get = lambda c: [r[f"{col}__{c}"] if c in held else None for r in rows]
        self.low, self.high = (np.array([np.nan if v is None else v for v in get(c)], float) for c in ("min", "max"))
        hists = [h or [] for h in get("hist")]
        shape = (len(rows), max([1, *map(len, hists)]))
        self.lo, self.hi, self.rows, self.ndv = np.full(shape, np.nan), np.full(shape, np.nan), np.zeros(shape), np.ones(shape)
        for i, h in enumerate(hists):
            for j, b in enumerate(h):
                self.lo[i, j], self.hi[i, j], self.rows[i, j], self.ndv[i, j] = b["lo"], b["hi"], b["n_rows"], b["ndv"]
        dictionaries = get("dict")
        self.known = np.array([d is not None for d in dictionaries])
        seat: dict[str, int] = {}
        entries = [(i, seat.setdefault(e["value"], len(seat)), e["n"]) for i, d in enumerate(dictionaries) for e in d or ()]
        self.values = list(seat)
        self.at, self.value, self.count = (np.array([e[j] for e in entries], int) for j in range(3))

    def bounds(self, leaf) -> tuple[np.ndarray, np.ndarray]:
        """(estimate, at most) of a leaf in every partition."""
        if isinstance(leaf, Intervals):
            return self._intervals(leaf)
        if isinstance(leaf, In):
            held = set(leaf.values)
            hits = np.array([(v in held) != leaf.negated for v in self.values], bool)
        else:
            shape = _like_regex(leaf.pattern)
            hits = np.array([bool(shape.fullmatch(v)) != leaf.negated for v in self.values], bool)
        share = np.bincount(self.at, self.count * hits[self.value] if len(self.at) else None, len(self.n)) / self.n
        return np.where(self.known, share, 0.1), np.where(self.known, share, 1.0)

    def _intervals(self, leaf: Intervals) -> tuple[np.ndarray, np.ndarray]:
        guess, may, out = np.zeros(len(self.n)), np.zeros(len(self.n)), np.ones(len(self.n), bool)
        for a, a_open, b, b_open in leaf.spans:
            touched = ((self.hi > a) if a_open else (self.hi >= a)) & ((self.lo < b) if b_open else (self.lo <= b))
            covered = ((self.lo > a) if a_open else (self.lo >= a)) & ((self.hi < b) if b_open else (self.hi <= b))
            width = self.hi - self.lo
            with np.errstate(invalid="ignore", divide="ignore"):
                part = self.rows / self.ndv if a == b else np.where(width == 0, self.rows, self.rows * (np.minimum(self.hi, b) - np.maximum(self.lo, a)) / width)
            guess += np.where(covered, self.rows, np.where(touched, part, 0.0)).sum(1)
            may += np.where(touched, self.rows, 0.0).sum(1)
            miss = ((self.high <= a) if a_open else (self.high < a)) | ((self.low >= b) if b_open else (self.low > b))
            miss |= (self.low == self.high) & ((self.low == a) & a_open | (self.low == b) & b_open)
            out &= miss | np.isnan(self.low)
        clean = lambda x: np.where(out, 0.0, np.minimum(x / self.n, 1.0))
        return clean(guess), clean(may)


def leaves_of(p) -> list:
    """Leaves of a normalized predicate, in order."""
    return [x for c in p.of for x in leaves_of(c)] if isinstance(p, And | Or) else [p]


def upper(p) -> Column:
    """AND takes the least bound, OR their sum up to one."""
    if not isinstance(p, And | Or):
        return bounds(p)[2]
    each = [upper(x) for x in p.of]
    if len(each) == 1:
        return each[0]
    return F.least(*each) if isinstance(p, And) else F.least(F.lit(1.0), reduce(lambda x, y: x + y, each))


def independent(p, or_rule: str = "min") -> Column:
    """AND multiplies. OR takes the least share, or with ``complement`` one minus the product of the rest."""
    if not isinstance(p, And | Or):
        return bounds(p)[1]
    each = [independent(x, or_rule) for x in p.of]
    if len(each) == 1:
        return each[0]
    if isinstance(p, And):
        return reduce(lambda x, y: x * y, each)
    return F.least(*each) if or_rule == "min" else 1 - reduce(lambda x, y: x * y, [1 - e for e in each])


def four_features(p, or_rule: str = "min") -> dict[str, Column]:
    """sel_upper, sel_indep, sel_min, sel_max; all one without a predicate."""
    p = normalize(p)
    if p is None:
        return {k: F.lit(1.0) for k in ("sel_upper", "sel_indep", "sel_min", "sel_max")}
    each = [bounds(x)[1] for x in leaves_of(p)]
    least, most = (each[0], each[0]) if len(each) == 1 else (F.least(*each), F.greatest(*each))
    return {"sel_upper": upper(p), "sel_indep": independent(p, or_rule), "sel_min": least, "sel_max": most}


def with_selectivity(stats: DataFrame, p, or_rule: str = "min") -> DataFrame:
    """The partition table with the four features of a predicate."""
    return stats.withColumns(four_features(p, or_rule))


def filter_by_predicate(stats: DataFrame) -> DataFrame:
    """Partitions that may hold matching rows."""
    return stats.where("sel_upper > 0")
