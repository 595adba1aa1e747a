"""Offline preparation: statistics, partial answers, contributions, boosted trees, feature selection.

Everything that reads data is a Spark job over all of it. Of training queries the driver gets one
number per partition, its contribution, which is reduced over the groups on the executors. The trees
learn from a bounded sample of (query, partition) pairs, one task a model, which builds the pairs'
features itself; feature selection runs one task a restart. Answers by group never come to the driver:
they are a table with a row for each query (AnswerTable), and whatever is measured on them is measured
in the task that holds the row.
"""

from __future__ import annotations

import pickle
import random
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.operators import features as X
from coarsesample.operators.clustering import cluster_sample
from coarsesample.operators.execute import weighted_scan
from coarsesample.operators.metrics import cutoff_fractions
from coarsesample.operators.picker import Candidates, selection_frame
from coarsesample.operators.selectivity import ColumnArrays, leaves_of
from coarsesample.plans import partials
from coarsesample.plans.query import And, Or, QuerySpec, normalize, parts_of, to_sql
from coarsesample.plans.workload import WORKLOADS, Workload, laid_out
from coarsesample.runtime import large_batches, materialize, scratch_path, settle, ship_package
from coarsesample.sources.layouts import write_layout


class BoostedTrees:
    """Least-squares gradient boosting over binned features; gain by feature is kept."""

    def __init__(self, trees: int = 20, depth: int = 3, rate: float = 0.3, bins: int = 32, ridge: float = 5.0):
        self.trees, self.depth, self.rate, self.bins, self.ridge = trees, depth, rate, bins, ridge

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> BoostedTrees:
        self.edges = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        b = self._binned(x)
        self.gain = np.zeros(x.shape[1])
        self.base = float(np.average(y, weights=weight))
        self.model, f = [], np.full(len(y), self.base)
        used = [j for j in range(x.shape[1]) if len(self.edges[j]) and b[:, j].min() != b[:, j].max()]
        for _ in range(self.trees):
            tree = self._grow(b, y - f, weight, np.arange(len(y)), self.depth, used)
            self.model.append(tree)
            f += self.rate * self._walk(tree, b)
        return self

    def _binned(self, x: np.ndarray) -> np.ndarray:
        out = np.empty(x.shape, np.int16, order="F")
        for j, e in enumerate(self.edges):
            out[:, j] = np.searchsorted(e, x[:, j], side="right")
        return out

    def _grow(self, b, r, w, own, depth, used):
        sw, sr = w[own].sum(), (w[own] * r[own]).sum()
        leaf = sr / (sw + self.ridge)
        if depth == 0 or len(own) < 40:
            return leaf
        best, wo, ro = (1e-9, None, None), w[own], w[own] * r[own]
        for j in used:
            bins = b[own, j].astype(np.intp)
            cw = np.cumsum(np.bincount(bins, wo, self.bins))
            cr = np.cumsum(np.bincount(bins, ro, self.bins))
            gain = cr**2 / (cw + self.ridge) + (sr - cr) ** 2 / (sw - cw + self.ridge) - sr**2 / (sw + self.ridge)
            k = int(gain[:-1].argmax())
            if gain[k] > best[0]:
                best = (gain[k], j, k)
        if best[1] is None:
            return leaf
        self.gain[best[1]] += best[0]
        low = b[own, best[1]] <= best[2]
        if low.all() or not low.any():
            return leaf
        return (best[1], best[2], self._grow(b, r, w, own[low], depth - 1, used), self._grow(b, r, w, own[~low], depth - 1, used))

    def _walk(self, tree, b: np.ndarray) -> np.ndarray:
        if not isinstance(tree, tuple):
            return np.full(len(b), tree)
        j, k, low, high = tree
        return np.where(b[:, j] <= k, self._walk(low, b), self._walk(high, b))

    def predict(self, x: np.ndarray) -> np.ndarray:
        b = self._binned(x)
        return self.base + self.rate * sum(self._walk(t, b) for t in self.model)

    __call__ = predict


QUERIES_A_JOB = 400  # of a scan that hands its rows to Python tasks
COLUMNS_A_JOB = 10  # queries of an SQL aggregation
JOBS_A_SETTLE = 5  # after so many, the driver's JVM frees their plans
MOST_TOTALS = 64_000_000  # bytes of a job's totals by group that are sent to every task


def _batches(queries: list[QuerySpec]) -> Iterator[tuple[tuple, list[tuple[int, QuerySpec]]]]:
    """Queries of the same group-by columns, some at a time, since each adds columns to one aggregation."""
    for cols in sorted({q.group_by for q in queries}):
        own = [(i, q) for i, q in enumerate(queries) if q.group_by == cols]
        for at in range(0, len(own), COLUMNS_A_JOB):
            yield cols, own[at : at + COLUMNS_A_JOB]


def _parts_table(df: DataFrame, cols: tuple, own: list[tuple[int, QuerySpec]]) -> DataFrame:
    """part_id, the group and each query's parts, by conditional aggregates in one scan."""
    exprs = []
    for i, q in own:
        keep = f"({to_sql(q.where)})"
        exprs.append(f"count(CASE WHEN {keep} THEN 1 END) AS q{i}__rows")
        for a in q.aggs:
            test = keep if a.where is None else f"{keep} AND ({to_sql(a.where)})"
            x = f"CASE WHEN {test} THEN {'1' if a.expr == '*' else a.expr} END"
            count, total = f"CAST(count({x}) AS DOUBLE)", f"coalesce(sum(CAST({x} AS DOUBLE)), 0D)"
            exprs.append(f"{count if a.fn == 'count' else total} AS q{i}__{a.alias}__s")
            if a.fn == "avg":
                exprs.append(f"{count} AS q{i}__{a.alias}__c")
    return df.groupBy("part_id", *cols).agg(*map(F.expr, exprs))


def batch_partials(df: DataFrame, queries: list[QuerySpec]) -> list[pd.DataFrame]:
    """Per-partition parts of all queries by group, on the driver: for checks on small tables. answers_table() is the one at scale."""
    out: list = [None] * len(queries)
    for cols, own in _batches(queries):
        table = _parts_table(df, cols, own).toPandas()
        for i, q in own:
            names = [n for _, n, _, _ in parts_of(q)]
            rows = table[table[f"q{i}__rows"] > 0]
            out[i] = rows[["part_id", *cols]].assign(n_rows=rows[f"q{i}__rows"], **{n: rows[f"q{i}__{n}"] for n in names})
    return out


def batch_contributions(df: DataFrame, queries: list[QuerySpec]) -> DataFrame:
    """part_id, query, contribution (above zero): a partition's largest share of any group's total.

    Groups never leave the executors: a group's total is a window over its per-partition parts, and
    shares are reduced to one number per partition and query.
    """
    out = None
    for cols, own in _batches(queries):
        table = _parts_table(df, cols, own)
        names = {i: [f"q{i}__{n}" for _, n, _, _ in parts_of(q)] for i, q in own}
        group = f"PARTITION BY {', '.join(cols)}" if cols else ""
        held = table.selectExpr("part_id", *[f"try_divide({n}, sum({n}) OVER ({group})) AS {n}" for ns in names.values() for n in ns])
        wide = held.groupBy("part_id").agg(*[F.expr(f"max(greatest(0D, {', '.join(ns)})) AS c{i}") for i, ns in names.items()])
        each = wide.selectExpr("part_id", f"stack({len(names)}, {', '.join(f'{i}, c{i}' for i in names)}) AS (query, contribution)").where("contribution > 0")
        out = each if out is None else out.unionByName(each)
    return out


def contributions_of(df: DataFrame, queries: list[QuerySpec], parts: np.ndarray, whole: bool = False) -> list[np.ndarray]:
    """Each query's contributions as an array over partitions, by two scans for every ``QUERIES_A_JOB`` queries.

    The first adds up totals by group on the executors, a few hundred groups a query; with these every
    task of the second has the shares of the partitions it holds whole. With ``whole``, the table's rows
    are taken to lie like that; else, and if a partition turns out to lie in two places, they are dealt by partition. Totals over ``MOST_TOTALS`` bytes
    stay on the executors: then batch_contributions() has the shares.
    """
    spark, out = df.sparkSession, np.zeros((len(queries), len(parts)))
    ship_package(spark)
    for job, at in enumerate(range(0, len(queries), QUERIES_A_JOB), 1):
        own = list(enumerate(queries[at : at + QUERIES_A_JOB], at))
        some = _shares_frame(df, own, whole)
        if some is None:
            for _, few in _batches([q for _, q in own]):
                some = batch_contributions(df, [q for _, q in few]).toPandas()
                out[np.array([own[i][0] for i, _ in few])[some["query"].to_numpy(int)], np.searchsorted(parts, some["part_id"].to_numpy(int))] = some["contribution"]
        else:
            out[some["query"].to_numpy(int), np.searchsorted(parts, some["part_id"].to_numpy(int))] = some["contribution"]
        if job % JOBS_A_SETTLE == 0:
            settle(spark)
    return list(out)


def _by_partition(rows: DataFrame) -> DataFrame:
    """Whole partitions to a task, one after the other, so that its blocks of rows hold few of them each, whatever the layout."""
    return rows.repartition("part_id").sortWithinPartitions("part_id")


def _shares_frame(df: DataFrame, own: list[tuple[int, QuerySpec]], whole: bool = False) -> pd.DataFrame | None:
    """query, part_id, contribution (above zero) of numbered queries; None if their totals are too large to be sent."""
    scan = partials.Scan(df, own)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for s, packed in partials.totals_of(scan, batches):
            yield pa.RecordBatch.from_pydict({"s": pa.array([s], pa.int32()), "packed": [packed]})

    def add(table: pd.DataFrame) -> pd.DataFrame:
        whole = partials.Totals()
        for packed in table["packed"]:
            whole.add(*pickle.loads(packed))
        return pd.DataFrame({"s": table["s"].iloc[:1], "packed": [whole.pack()]})

    schema = "s int, packed binary"
    with large_batches(df.sparkSession):
        held = materialize(scan.rows(df).mapInArrow(count, schema).groupBy("s").applyInPandas(add, schema), "totals")
    if (held.agg(F.sum(F.octet_length("packed"))).first()[0] or 0) > MOST_TOTALS:
        return None
    found = {r["s"]: pickle.loads(bytes(r["packed"])) for r in held.collect()}
    if not found:
        return pd.DataFrame({"query": [], "part_id": [], "contribution": []})
    totals = [({k: n for n, k in enumerate(found[s][0])}, found[s][1]) for s in range(len(scan.sets))]
    sent = df.sparkSession.sparkContext.broadcast(pickle.dumps(totals))

    def share(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, part, x in partials.shares_of(scan, pickle.loads(sent.value), batches):
            some = x > 0
            if some.any():
                yield pa.RecordBatch.from_pydict({"query": pa.array(np.full(some.sum(), i, np.int32)), "part_id": pa.array(part[some].astype(np.int32)), "contribution": x[some]})

    for rows in (scan.rows(df), None) if whole else (None,):
        with large_batches(df.sparkSession):
            out = (_by_partition(scan.rows(df)) if rows is None else rows).mapInArrow(share, "query int, part_id int, contribution double").toPandas()
        seen = out["query"] == partials.SEEN
        if not out["part_id"][seen].duplicated().any():
            break
    sent.unpersist()
    return out[~seen]


class Answers:
    """One query's parts as arrays, a row for each partition and group that has any."""

    def __init__(self, q: QuerySpec, table: pd.DataFrame, parts: np.ndarray):
        self.q = q
        names = [n for _, n, _, _ in parts_of(q)]
        self.where = {int(p): i for i, p in enumerate(parts)}
        if len(q.group_by) and len(table):
            self.group = pd.factorize(pd.MultiIndex.from_frame(table[list(q.group_by)].astype(str)))[0]
        else:
            self.group = np.zeros(len(table), int)
        self.at = table["part_id"].map(self.where).to_numpy(int)
        self.x = table[names].to_numpy(float)
        self.rows = np.bincount(self.at, table["n_rows"].to_numpy(float), len(parts))
        self._settle()

    @classmethod
    def unpack(cls, q: QuerySpec, parts: np.ndarray, packed: bytes) -> Answers:
        """What pack() has put into a row of an answer table."""
        out = object.__new__(cls)
        out.q, out.where = q, {int(p): i for i, p in enumerate(parts)}
        out.group, out.at, out.x, out.rows = pickle.loads(packed)
        out._settle()
        return out

    def pack(self) -> bytes:
        return pickle.dumps((self.group.astype(np.int32), self.at.astype(np.int32), self.x, self.rows))

    def _settle(self) -> None:
        self.n_groups = int(self.group.max()) + 1 if len(self.group) else 0
        self.total = self._sum(self.group, self.x)

    def _sum(self, group: np.ndarray, x: np.ndarray) -> np.ndarray:
        return np.stack([np.bincount(group, x[:, j], self.n_groups) for j in range(x.shape[1])], axis=1)

    def of_parts(self, keep: np.ndarray) -> Answers:
        """The query over some partitions only, as if they were the table."""
        out = object.__new__(Answers)
        own = keep[self.at]
        out.q, out.where, out.rows = self.q, self.where, np.where(keep, self.rows, 0.0)
        out.at, out.x = self.at[own], self.x[own]
        out.group = np.unique(self.group[own], return_inverse=True)[1]
        out._settle()
        return out

    def _final(self, total: np.ndarray) -> np.ndarray:
        cols, i = [], 0
        for a in self.q.aggs:
            if a.fn == "avg":
                cols.append(total[:, i] / np.where(total[:, i + 1] != 0, total[:, i + 1], 1))
                i += 2
            else:
                cols.append(total[:, i])
                i += 1
        return np.stack(cols, axis=1)

    def errors(self, selection: list[tuple]) -> dict[str, float]:
        """missed, rel, abs of a weighted selection."""
        if not self.n_groups:
            return {"missed": 0.0, "rel": 0.0, "abs": 0.0}
        weight = np.zeros(len(self.rows))
        for s in selection:
            weight[self.where[s[0]]] = s[1]
        read = weight[self.at] > 0
        group, x = self.group[read], self.x[read] * weight[self.at[read]][:, None]
        truth, guess = self._final(self.total), self._final(self._sum(group, x))
        found = np.bincount(group, minlength=self.n_groups) > 0
        guess[~found] = 0
        rel = np.where(truth == 0, (guess != 0).astype(float), np.abs(guess - truth) / np.where(truth == 0, 1, np.abs(truth)))
        rel[~found] = 1.0
        base = np.abs(truth.mean(0))
        return {"missed": float(1 - found.mean()), "rel": float(rel.mean()), "abs": float((np.abs(guess - truth).mean(0) / np.where(base > 0, base, 1)).mean())}

    def contribution(self) -> np.ndarray:
        """Largest share of any group's aggregate, per partition."""
        out = np.zeros(len(self.rows))
        if self.n_groups:
            total = self.total[self.group]
            np.maximum.at(out, self.at, np.where(total != 0, self.x / np.where(total == 0, 1, total), 0).max(1))
        return out


@dataclass
class AnswerTable:
    """Answers of some queries, none of them on the driver: ``df`` has query and packed, ``ids`` the queries' numbers in order."""

    df: DataFrame
    ids: list[int]

    def __len__(self) -> int:
        return len(self.ids)

    def of(self, ids: list[int]) -> AnswerTable:
        return AnswerTable(self.df, ids)

    def rows(self) -> DataFrame:
        return self.df.where(F.col("query").isin(self.ids)) if self.ids else self.df.limit(0)


def answers_table(df: DataFrame, queries: list[QuerySpec], parts: np.ndarray, whole: bool = False) -> AnswerTable:
    """Answers of all queries that have a matching row, a row each, in shared scratch.

    A query's parts by partition and group meet in one task: at most its groups times ``parts``. Each
    ``QUERIES_A_JOB`` queries are a scan. Rows are dealt by partition first, unless they lie like that
    (``whole``); pieces of a partition are added up anyway.
    """
    spark, path, schema = df.sparkSession, scratch_path(df.sparkSession, "answers"), "query int, packed binary"
    paths = []

    def pack(table: pd.DataFrame) -> pd.DataFrame:
        a = object.__new__(Answers)
        a.group, part, rows, a.x = partials.united(list(table["packed"]))
        a.at = np.searchsorted(parts, part)
        a.rows = np.bincount(a.at, rows, len(parts))
        return pd.DataFrame({"query": table["query"].iloc[:1], "packed": [a.pack()]})

    ship_package(spark)
    for at in range(0, len(queries), QUERIES_A_JOB):
        own = list(enumerate(queries[at : at + QUERIES_A_JOB], at))
        scan = partials.Scan(df, own)

        def count(batches: Iterator[pa.RecordBatch], scan=scan) -> Iterator[pa.RecordBatch]:
            for i, packed in partials.parts_by_group(scan, batches):
                yield pa.RecordBatch.from_pydict({"query": pa.array([i], pa.int32()), "packed": [packed]})

        paths.append(f"{path}/{len(paths)}")
        rows = scan.rows(df) if whole else _by_partition(scan.rows(df))
        with large_batches(spark):
            rows.mapInArrow(count, schema).repartition(len(own), "query").groupBy("query").applyInPandas(pack, schema).write.parquet(paths[-1])
        if len(paths) % JOBS_A_SETTLE == 0:
            settle(spark)
    held = spark.read.schema(schema).parquet(*paths)
    return AnswerTable(held, sorted(r["query"] for r in held.select("query").collect()))


@dataclass
class Prepared:
    """A laid-out view with its statistics, and trained models once fit() has run.

    ``df`` has a directory a partition, for reads of some; ``flat`` holds the same rows in few files, for whole scans.
    """

    w: Workload
    df: DataFrame
    stats: DataFrame
    parts: np.ndarray
    static: np.ndarray
    schema: X.FeatureSchema
    items: dict
    norm: X.Normalizer = None
    models: list = field(default_factory=list)
    scorer: BoostedTrees = None
    keep: np.ndarray = None
    path: str = None
    flat: DataFrame = None

    def light(self) -> Prepared:
        """What planning needs, without the data: small enough to be sent to every task."""
        return replace(self, df=None, flat=None, stats=None, w=replace(self.w, view=None, layouts=None))

    def scan(self, rows: list[tuple]) -> DataFrame:
        """The chosen partitions' rows with their weights; the files of others are neither listed nor read."""
        return weighted_scan(self.df, selection_frame(self.df.sparkSession, rows), self.path)

    def selectivities(self, queries: list[QuerySpec]) -> list[np.ndarray]:
        """The four features of each query for all partitions.

        The sketches of every column that a predicate names are read once and every distinct leaf is
        evaluated on them once; predicate trees are then folded over those partition-level numbers.
        """
        trees = [normalize(q.where) for q in queries]
        leaves = list(dict.fromkeys(x for t in trees if t is not None for x in leaves_of(t)))
        known: dict = {}
        for col in sorted({x.col for x in leaves}):
            arrays = ColumnArrays(self.stats, col, self.parts)
            known |= {x: np.nan_to_num(np.stack(arrays.bounds(x), axis=1)) for x in leaves if x.col == col}

        def fold(t, at: int, both, either):
            if not isinstance(t, And | Or):
                return known[t][:, at]
            each = [fold(x, at, both, either) for x in t.of]
            return (both if isinstance(t, And) else either)(each)

        out = []
        for t in trees:
            if t is None:
                out.append(np.ones((len(self.parts), 4)))
                continue
            least = lambda e: np.minimum.reduce(e)
            each = np.stack([known[x][:, 0] for x in leaves_of(t)])
            upper = fold(t, 1, least, lambda e: np.minimum(1.0, np.add.reduce(e)))
            indep = fold(t, 0, lambda e: np.multiply.reduce(e), least)
            out.append(np.stack([upper, indep, each.min(0), each.max(0)], axis=1))
        return out

    def raw(self, q: QuerySpec, sel: np.ndarray, own: np.ndarray | slice = slice(None)) -> np.ndarray:
        """Masked, normalized features of all partitions, or of some, for a query."""
        full = np.concatenate([self.static[own], sel[own]], axis=1)
        norm = self.norm or X.Normalizer(self.schema).fit(full)
        return norm.transform(full) * self.schema.used(q, self.w.cfg)

    def _features(self, queries: list[QuerySpec], sels: list[np.ndarray], own: list[np.ndarray]) -> np.ndarray:
        """raw() of some partitions of each query below each other; ``sels`` hold those partitions only."""
        out, at, used = np.empty((sum(map(len, own)), len(self.schema)), np.float32), 0, self.w.cfg
        for q, s, o in zip(queries, sels, own, strict=True):
            out[at : at + len(o)] = self.norm.transform(np.concatenate([self.static[o], s], axis=1)) * self.schema.used(q, used)
            at += len(o)
        return out

    def candidates(self, q: QuerySpec, sel: np.ndarray) -> Candidates:
        x = self.raw(q, sel)
        bits = [i for i, (c, s) in enumerate(zip(self.schema.cols, self.schema.stats, strict=True)) if s.startswith("bit") and c in q.group_by]
        keys = [tuple(self.static[r, bits].astype(int)) if bits else None for r in range(len(self.parts))]
        kept = x if self.keep is None else x[:, self.keep]
        return Candidates(self.parts, kept, keys, sel[:, 0], sel[:, 1], x)

    def fit(self, queries: list[QuerySpec], contributions: list[np.ndarray], sels: list[np.ndarray], k: int = 4, top: float = 0.01, most_rows: int = 40_000, seed: int = 0) -> Prepared:
        """A copy with k regressors on centred, balanced targets with cut-offs at falling shares, and one on the contribution.

        They learn from ``most_rows`` pairs of query and partition at most, drawn evenly; each model is
        a task of its own, which builds the pairs' features from the partitions' and the selectivities.
        """
        n = len(self.parts)
        drawn = np.sort(np.random.default_rng(seed).permutation(n * len(queries))[:most_rows])
        own = [drawn[(drawn >= i * n) & (drawn < (i + 1) * n)] - i * n for i in range(len(queries))]
        some = [s[o] for o, s in zip(own, sels, strict=True)]
        out = replace(self, norm=X.Normalizer(self.schema).fit_chunks(lambda: (np.concatenate([self.static[o], s], axis=1) for o, s in zip(own, some, strict=True))))
        targets = []
        for i in range(k):
            target = []
            for c, o in zip(contributions, own, strict=True):
                first = float((c > 0).mean())
                share = cutoff_fractions(first, k, top)[i] if first > 0 else 0
                cut = np.sort(c)[::-1][max(0, int(np.ceil(share * len(c) - 1e-9)) - 1)] if share else np.inf
                target.append(np.where((c[o] >= cut) & (c[o] > 0), 1.0, -1.0))
            y = np.concatenate(target)
            n_pos = (y > 0).sum()
            targets.append((y, np.where(y > 0, 0.5 / max(1, n_pos), 0.5 / max(1, len(y) - n_pos)) * len(y)))
        targets.append((np.concatenate([c[o] for c, o in zip(contributions, own, strict=True)]), np.ones(len(drawn))))
        held = in_tasks(self.df.sparkSession, (out.light(), queries, some, own, targets), len(targets), lambda data, i: BoostedTrees().fit(data[0]._features(*data[1:4]), *data[4][i]))
        out.models, out.scorer = held[:k], held[k]
        return out

    def importance_by_kind(self) -> dict[str, float]:
        """Percent of the models' total gain by kind of statistic."""
        gain = sum(m.gain for m in self.models)
        total = gain.sum() or 1.0
        return {k: float(100 * gain[[i for i, x in enumerate(self.schema.kinds) if x == k]].sum() / total) for k in ("measure", "heavy_hitter", "distinct", "selectivity")}


def in_tasks(spark: SparkSession, shared, n: int, work: Callable) -> list:
    """``work(shared, i)`` for i below n, each in a task; ``shared`` is broadcast, so it has to be small."""
    ship_package(spark)
    held = spark.sparkContext.broadcast(pickle.dumps(shared))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        data = None
        for batch in batches:
            for i in batch["id"]:
                data = pickle.loads(held.value) if data is None else data
                yield pd.DataFrame({"id": [i], "found": [pickle.dumps(work(data, int(i)))]})

    rows = spark.range(0, n, 1, n).mapInPandas(run, "id long, found binary").collect()
    held.unpersist()
    settle(spark)
    return [pickle.loads(bytes(r["found"])) for r in sorted(rows, key=lambda r: r["id"])]


def prepare(spark: SparkSession, sf_dir: str, name: str, layout: str, n_parts: int) -> Prepared:
    """Lay out a workload's view as one directory per partition, sketch it in one pass, and bring the
    partition-level features to the driver.

    The rows are kept in few files as well: a whole scan of a directory a partition costs a job hundreds
    of tasks, and the driver the state of each. They are dealt by partition once, for these files; the
    directories are written from them, and all scans find a partition's rows together.
    """
    w = WORKLOADS[name]
    path = scratch_path(spark, f"view-{name}")
    rows = laid_out(spark, sf_dir, name, layout, n_parts)
    settle(spark)  # shuffles of joins and order go from the disk
    flat = materialize(_by_partition(rows), f"rows-{name}")
    write_layout(flat, path, whole=True)
    df = spark.read.parquet(path)
    stats = materialize(X.partition_stats_onepass(flat, w.cfg, whole=True), f"stats-{name}")
    items = X.global_items(stats, w.cfg)
    rows = X.static_features(stats, w.cfg, items).toPandas().sort_values("part_id")
    settle(spark)
    return Prepared(w, df, stats, rows["part_id"].to_numpy(int), np.stack(rows["f"].to_numpy()).astype(float), X.FeatureSchema.of(w.cfg), items, path=path, flat=flat)


def constants_of(p: Prepared, per_column: int = 20, most_values: int = 10_000) -> dict[str, list]:
    """Candidate constants from the sketches of all partitions: bucket edges of numbers, dictionary values of strings.

    Numbers are quantiles of a column's distinct edges. Of more than ``most_values`` strings, those of
    the lowest hash stand for all. The driver gets nothing else.
    """
    out: dict[str, list] = {}
    ranks = F.array(*[F.lit(i / (per_column - 1)) for i in range(per_column)])
    each = F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.col(f"{c}__hist.hi").alias("hi")) for c in p.w.cfg.numeric]))
    edges = p.stats.select(each.alias("x")).select("x.c", F.explode("x.hi").alias("edge")).select("c", F.round(F.col("edge").cast("double"), 4).alias("edge")).distinct()
    found = {r["c"]: r["q"] for r in edges.groupBy("c").agg(F.percentile_approx("edge", ranks, F.lit(10_000)).alias("q")).collect()}
    out |= {c: sorted(set(found.get(c) or [])) for c in p.w.cfg.numeric}
    for c in p.w.cfg.strings:
        values = p.stats.select(F.explode(F.col(f"{c}__dict.value")).alias("value")).where("value is not null").distinct()
        out[c] = sorted(r[0] for r in values.orderBy(F.xxhash64("value"), "value").limit(most_values).collect())
    return out


RESTART_TASKS = 16  # enough for the hashes of the first restarts to differ


def select_features(p: Prepared, queries: list[QuerySpec], answers: AnswerTable, sels: list[np.ndarray], restarts: int = 4, budgets: tuple[float, ...] = (0.1, 0.2), most_parts: int = 200, seed: int = 0) -> tuple[np.ndarray, list[float]]:
    """Greedy removal of statistic types for clustering: kept columns and the falling training error.

    A type goes from all columns at once. Passes in random order repeat until no removal helps; each
    restart is a task. The error is that of the given queries over ``most_parts`` partitions at most,
    drawn evenly, as if they were the table; only those partitions' answers go to the restarts.
    """
    spark = p.df.sparkSession
    ship_package(spark)
    kinds = ["bit" if s.startswith("bit") else s for s in p.schema.stats]
    drawn = np.zeros(len(p.parts), bool)
    drawn[np.random.default_rng(seed).permutation(len(p.parts))[:most_parts]] = True
    held = spark.sparkContext.broadcast(pickle.dumps((p.light(), dict(zip(answers.ids, zip(queries, sels, strict=True), strict=True)), kinds, budgets, drawn)))

    def restrict(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        light, known, *_, drawn = pickle.loads(held.value)
        for batch in batches:
            for i, packed in zip(batch["query"], batch["packed"], strict=True):
                yield pd.DataFrame({"query": [i], "packed": [Answers.unpack(known[i][0], light.parts, packed).of_parts(drawn).pack()]})

    def remove(copies: pd.DataFrame) -> pd.DataFrame:
        light, known, kinds, budgets, drawn = pickle.loads(held.value)
        data = []
        for i, packed in sorted(zip(copies["query"], copies["packed"], strict=True)):
            q, s = known[i]
            alive = np.flatnonzero((s[:, 0] > 0) & drawn)
            if len(alive):
                data.append((light._features([q], [s[alive]], [alive]), light.parts[alive], Answers.unpack(q, light.parts, packed)))
        r = int(copies["restart"].iloc[0])
        return pd.DataFrame({"restart": [r], "found": [pickle.dumps(_greedy(data, kinds, budgets, seed + r))]})

    given = answers.rows().mapInPandas(restrict, "query int, packed binary")
    copies = given.select("*", F.explode(F.array(*map(F.lit, range(restarts)))).alias("restart")).repartition(RESTART_TASKS, "restart")
    rows = copies.groupBy("restart").applyInPandas(remove, "restart int, found binary").collect()
    held.unpersist()
    settle(spark)
    found = [pickle.loads(bytes(r["found"])) for r in sorted(rows, key=lambda r: r["restart"])]
    if not found:
        return np.ones(len(kinds), bool), [0.0]
    best_error, trace, best = min(found, key=lambda f: f[0])
    return np.array([k in best for k in kinds]), trace


def _greedy(data: list[tuple], kinds: list[str], budgets: tuple, seed: int) -> tuple[float, list[float], frozenset]:
    """One restart of the removal: last error, its path, the types kept."""
    known: dict[frozenset, float] = {}

    def error(types: frozenset) -> float:
        if types not in known:
            cols = np.array([k in types for k in kinds])
            each = [a.errors(cluster_sample(parts, x[:, cols], max(1, int(b * len(parts)))))["rel"] for x, parts, a in data for b in budgets]
            known[types] = float(np.mean(each)) if each else 0.0
        return known[types]

    rng, now = random.Random(seed), frozenset(kinds)
    trace, improved = [error(now)], True
    while improved:
        improved = False
        for t in rng.sample(sorted(now), len(now)):
            if len(now) > 1 and error(now - {t}) < trace[-1]:
                now, improved = now - {t}, True
                trace.append(error(now))
    return trace[-1], trace, now


def needs_retrain(old: Prepared, features: np.ndarray, limit: float = 0.5) -> bool:
    """Whether new partitions' features have moved, on the normalized scale, by more than ``limit`` on average."""
    return bool(np.abs(old.norm.transform(features).mean(0)).mean() > limit)
