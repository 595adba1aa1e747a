"""One row per partition: sketches side by side, and the numeric feature vector drawn from them.

The schema of the vector follows from the table's columns alone, so all queries share it; a query
only masks what it doesn't use.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from coarsesample.operators import sketches as S
from coarsesample.operators import streamed
from coarsesample.plans.query import QuerySpec, query_columns
from coarsesample.runtime import large_batches, materialize, ship_package

SELECTIVITY = ("sel_upper", "sel_indep", "sel_min", "sel_max")


@dataclass(frozen=True)
class TableConfig:
    """Columns of a view by type, and which may be grouped by."""

    numeric: tuple[str, ...]
    strings: tuple[str, ...]
    groupable: tuple[str, ...]
    buckets: int = 10
    k: int = 128
    support: float = 0.01
    bitmap: int = 25

    @property
    def columns(self) -> set[str]:
        return {*self.numeric, *self.strings}


def partition_stats(df: DataFrame, cfg: TableConfig) -> DataFrame:
    """All sketches of a partition in one row: the statistics table that queries plan on.

    Two value-count aggregations (numbers, strings) and one for measures read the data; everything
    after works on sketch-sized tables. Columns without a value in a partition have empty sketches
    there; the partition stays. This is the exact form, for checks and small tables: rows multiply by
    columns in the value counts.
    """
    numeric, strings = list(cfg.numeric), list(cfg.strings)
    out = df.groupBy("part_id").agg(F.count(F.lit(1)).alias("n_rows"))
    pos = S.positive_columns(df, numeric)
    m = S.measures(df, numeric, pos)
    names = ["n_null", "min", "max", "mean", "mean_sq", "log_min", "log_max", "log_mean", "log_mean_sq"]
    wide = m.groupBy("part_id").agg(*[F.max(F.when(F.col("col_name") == c, F.col(n))).alias(f"{c}__{n}") for c in numeric for n in names])
    out = out.join(wide, "part_id")
    counts = {"double": S.value_counts(df, numeric, "double")} | ({"string": S.value_counts(df, strings, "string")} if strings else {})
    for kind, vc in counts.items():
        own = numeric if kind == "double" else strings
        hist = S.histogram(vc if kind == "double" else S.hashed(vc), cfg.buckets)
        kmv = S.kmv_features(S.kmv(vc, cfg.k), cfg.k)
        hh = S.heavy_hitters(vc, cfg.support)
        pick = lambda c, e: F.when(F.col("col_name") == c, e)
        bucket = F.struct("lo", "hi", "n_rows", "ndv")
        out = out.join(hist.groupBy("part_id").agg(*[F.sort_array(F.collect_list(pick(c, bucket))).alias(f"{c}__hist") for c in own]), "part_id", "left")
        out = out.join(kmv.groupBy("part_id").agg(*[F.max(pick(c, F.col(f))).alias(f"{c}__{f}") for c in own for f in ("ndv", "freq_avg", "freq_max", "freq_min", "freq_sum")]), "part_id", "left")
        item = F.struct(F.col("n").alias("n"), F.col("value").cast("string").alias("value"))
        out = out.join(hh.groupBy("part_id").agg(*[F.sort_array(F.collect_list(pick(c, item)), False).alias(f"{c}__hh") for c in own]), "part_id", "left")
        if kind == "string":
            word = F.struct(F.col("value").alias("value"), F.col("n").alias("n"))
            dictionary = S.exact_dictionary(vc)
            out = out.join(dictionary.groupBy("part_id").agg(*[F.sort_array(F.collect_list(pick(c, word))).alias(f"{c}__dict") for c in own]), "part_id", "left")
            out = out.withColumns({f"{c}__dict": F.when(F.size(f"{c}__dict") > 0, F.col(f"{c}__dict")) for c in own})
        bare = "array<struct<lo:double,hi:double,n_rows:bigint,ndv:bigint>>"
        out = out.withColumns({f"{c}__hist": F.coalesce(f"{c}__hist", F.array().cast(bare)) for c in own})
    return out


def _sketches(df: DataFrame, cfg: TableConfig) -> DataFrame:
    """Raw statistics of partitions by aggregates."""
    pos = S.positive_columns(df, list(cfg.numeric))
    cuts = [i / cfg.buckets for i in range(1, cfg.buckets)]
    aggs = [F.count(F.lit(1)).alias("n_rows")]
    for c in (*cfg.numeric, *cfg.strings):
        text = c in cfg.strings
        x = S.hash32(F.col(c)).cast("double") if text else F.col(c).cast("double")
        aggs += [F.min(x).alias(f"{c}__min"), F.max(x).alias(f"{c}__max"), F.count(c).alias(f"{c}__n"), F.percentile_approx(x, cuts, 1000).alias(f"{c}__cuts"), F.approx_count_distinct(c, 0.02).cast("double").alias(f"{c}__ndv")]
        aggs.append(F.expr(f"approx_top_k({c if text else f'CAST({c} AS DOUBLE)'}, 100, 10000)").alias(f"{c}__top"))
        if not text:
            aggs += [F.count(F.lit(1)).alias(f"{c}__rows"), F.avg(x).alias(f"{c}__mean"), F.avg(x * x).alias(f"{c}__mean_sq")]
            log = F.ln(x) if c in pos else F.lit(None).cast("double")
            aggs += [F.min(log).alias(f"{c}__log_min"), F.max(log).alias(f"{c}__log_max"), F.avg(log).alias(f"{c}__log_mean"), F.avg(log * log).alias(f"{c}__log_mean_sq")]
    return df.groupBy("part_id").agg(*aggs)


def _runs(df: DataFrame, cfg: TableConfig) -> DataFrame:
    """Raw statistics of partitions whose rows follow each other, as a table in scratch."""
    schema = streamed.fields(cfg.numeric, cfg.strings)
    chosen = df.select("part_id", *[F.col(c).cast("double").alias(c) for c in cfg.numeric], *[F.col(c).cast("string").alias(c) for c in cfg.strings])
    kind = to_arrow_schema(StructType.fromDDL(schema))
    numeric, strings, buckets = cfg.numeric, cfg.strings, cfg.buckets
    ship_package(df.sparkSession)

    def run(batches: Iterable) -> Iterable:
        yield from streamed.statistics(numeric, strings, buckets, batches, kind)

    with large_batches(df.sparkSession):
        held = materialize(chosen.mapInArrow(run, schema), "runs")
        if held.count() > held.select("part_id").distinct().count():
            held = materialize(chosen.repartition("part_id").sortWithinPartitions("part_id").mapInArrow(run, schema), "runs")
    above = S.positive_columns(held.select(*[F.col(f"{c}__min").alias(c) for c in cfg.numeric]), list(cfg.numeric))
    logs = ("log_min", "log_max", "log_mean", "log_mean_sq")
    return held.withColumns({f"{c}__{m}": F.lit(None).cast("double") for c in cfg.numeric if c not in above for m in logs} or {"n_rows": F.col("n_rows")})


def partition_stats_onepass(df: DataFrame, cfg: TableConfig, whole: bool = False) -> DataFrame:
    """The same table from one scan and one aggregation, by built-in sketches: for wide tables at scale.

    Nothing is unpivoted, so rows don't multiply by columns, and a partition's state is bounded:
    approximate quantiles cut buckets of equal rows, of which several may lie on one frequent value, a
    top-k sketch holds frequent values, HLL counts the rest. Extremes stay exact and buckets cover all
    between them, so the filter still loses nothing. A dictionary is kept only if its counts add up to
    all non-null rows.

    With ``whole``, rows of a partition are taken to lie in one task, one after the other: then they are
    counted in runs, without an aggregation, and a partition found in two tasks has its rows dealt anew.
    """
    held = _runs(df, cfg) if whole else _sketches(df, cfg)
    more: dict = {}
    for c in (*cfg.numeric, *cfg.strings):
        n, ndv, top = F.col(f"{c}__n"), F.col(f"{c}__ndv"), F.col(f"{c}__top")
        edges = F.concat(F.array(f"{c}__min"), F.col(f"{c}__cuts"), F.array(f"{c}__max"))
        low, high = F.slice(edges, 1, cfg.buckets), F.slice(edges, 2, cfg.buckets)
        more[f"{c}__hist"] = F.when(n > 0, F.zip_with(low, high, _bucket(n, ndv, F.lit(cfg.buckets)))).otherwise(F.array().cast("array<struct<lo:double,hi:double,n_rows:double,ndv:double>>"))
        more[f"{c}__hh"] = F.transform(F.filter(top, _frequent(n, cfg.support)), lambda h: F.struct(h["count"].alias("n"), h["item"].cast("string").alias("value")))
        more[f"{c}__freq_avg"] = n / F.greatest(ndv, F.lit(1.0))
        more[f"{c}__freq_max"] = F.get(top, 0)["count"]
        more[f"{c}__freq_min"], more[f"{c}__freq_sum"] = F.lit(1), n
        if c in cfg.strings:
            complete = F.aggregate(top, F.lit(0).cast("long"), lambda s, h: s + h["count"]) == n
            more[f"{c}__dict"] = F.when(complete & (F.size(top) <= 100) & (n > 0), F.transform(top, lambda h: F.struct(h["item"].alias("value"), h["count"].alias("n"))))
        else:
            more[f"{c}__n_null"] = F.col(f"{c}__rows") - n
    return held.withColumns(more).drop(*[f"{c}__{x}" for c in (*cfg.numeric, *cfg.strings) for x in ("top", "cuts", "n", "rows")])


def _bucket(n: F.Column, ndv: F.Column, share: F.Column):
    return lambda lo, hi: F.struct(lo.alias("lo"), hi.alias("hi"), (n / share).cast("double").alias("n_rows"), F.greatest(ndv / share, F.lit(1.0)).alias("ndv"))


def _frequent(n: F.Column, support: float):
    return lambda h: h["count"] >= n * support


def global_items(stats: DataFrame, cfg: TableConfig) -> dict[str, list[str]]:
    """The grouping columns' most frequent items over all partitions, at most ``cfg.bitmap`` each."""
    each = F.array(*[F.struct(F.lit(c).alias("col_name"), F.coalesce(F.col(f"{c}__hh"), F.array().cast("array<struct<n:bigint,value:string>>")).alias("hh")) for c in cfg.groupable])
    long = stats.select(F.inline(each)).select("col_name", F.inline("hh"))
    rows = S.global_heavy_hitters(long, cfg.bitmap).collect()
    out: dict[str, list[str]] = {c: [] for c in cfg.groupable}
    for r in sorted(rows, key=lambda r: (r["col_name"], r["bit"])):
        out[r["col_name"]].append(r["value"])
    return out


@dataclass(frozen=True)
class FeatureSchema:
    """Name, column, statistic and kind of every dimension."""

    names: tuple[str, ...]
    cols: tuple[str, ...]
    stats: tuple[str, ...]
    kinds: tuple[str, ...]

    @classmethod
    def of(cls, cfg: TableConfig) -> FeatureSchema:
        rows = []
        for c in cfg.numeric:
            rows += [(c, s, "measure") for s in ("mean", "min", "max", "mean_sq", "std", "log_mean", "log_mean_sq", "log_min", "log_max")]
        for c in (*cfg.numeric, *cfg.strings):
            rows += [(c, s, "distinct") for s in ("ndv", "freq_avg", "freq_max", "freq_min", "freq_sum")]
            rows += [(c, s, "heavy_hitter") for s in ("hh_count", "hh_avg", "hh_max")]
        for c in cfg.groupable:
            rows += [(c, f"bit{i}", "heavy_hitter") for i in range(cfg.bitmap)]
        rows += [("", s, "selectivity") for s in SELECTIVITY]
        return cls(tuple(f"{c}__{s}" if c else s for c, s, _ in rows), *(tuple(r[i] for r in rows) for i in range(3)))

    def __len__(self) -> int:
        return len(self.names)

    def used(self, q: QuerySpec, cfg: TableConfig) -> np.ndarray:
        """1 for the dimensions a query looks at."""
        cols = query_columns(q, cfg.columns)
        return np.array([k == "selectivity" or (c in q.group_by if s.startswith("bit") else c in cols) for c, s, k in zip(self.cols, self.stats, self.kinds, strict=True)], float)


def _holds(col: str, item: str) -> F.Column:
    """Whether an item is in a partition's own dictionary."""
    return F.exists(f"{col}__hh", lambda h: h["value"] == item)


def static_features(stats: DataFrame, cfg: TableConfig, items: dict[str, list[str]]) -> DataFrame:
    """The unmasked features but for selectivity, as an array per partition; a projection without shuffle."""
    schema = FeatureSchema.of(cfg)
    out = []  # as text: as many column objects would take seconds to make
    for name, c, s, kind in zip(schema.names, schema.cols, schema.stats, schema.kinds, strict=True):
        if kind == "selectivity":
            continue
        if s == "std":
            e = f"sqrt(greatest({c}__mean_sq - {c}__mean * {c}__mean, 0D))"
        elif s.startswith("bit"):
            i = int(s[3:])
            e = f"exists({c}__hh, h -> h.value = {_quoted(items[c][i])})" if i < len(items[c]) else "0D"
        elif s.startswith("hh_"):
            n = f"size({c}__hh)"
            e = {"hh_count": n, "hh_avg": f"CASE WHEN {n} > 0 THEN aggregate({c}__hh, 0D, (t, h) -> t + h.n) / {n} END", "hh_max": f"get({c}__hh, 0).n"}[s]
        else:
            e = name
        out.append(f"coalesce(CAST({e} AS DOUBLE), 0D)")
    return stats.selectExpr("part_id", f"array({', '.join(out)}) AS f")


def _quoted(item: str | None) -> str:
    """An item as SQL text of Spark, in which a backslash escapes."""
    return "CAST(NULL AS STRING)" if item is None else "'" + item.replace("\\", "\\\\").replace("'", "\\'") + "'"


def bitmap(stats: DataFrame, col: str, items: list[str]) -> DataFrame:
    """part_id and the packed bits of one grouping column."""
    bits = [_holds(col, v).cast("long") * (1 << i) for i, v in enumerate(items)]
    total = bits[0]
    for b in bits[1:]:
        total = total + b
    return stats.select("part_id", F.coalesce(total, F.lit(0)).alias("bits"))


class Normalizer:
    """Features relative to their training average, on a signed log scale; bits and selectivities stay as they are.

    A feature counts by its relative variation: one that only wobbles by sampling noise stays small,
    and one whose spread exceeds one is shrunk to it, so none dominates.
    """

    def __init__(self, schema: FeatureSchema):
        self.as_is = np.array([k == "selectivity" or s.startswith("bit") for k, s in zip(schema.kinds, schema.stats, strict=True)])
        self.scale, self.mean, self.std = np.ones(len(schema)), np.zeros(len(schema)), np.ones(len(schema))

    def _shrunk(self, x: np.ndarray) -> np.ndarray:
        return np.where(self.as_is, x, np.sign(x) * np.log1p(np.abs(x) / self.scale))

    def fit(self, x: np.ndarray) -> Normalizer:
        return self.fit_chunks(lambda: [x])

    def fit_chunks(self, chunks: Callable[[], Iterable[np.ndarray]]) -> Normalizer:
        """fit() of rows that come in chunks, three times over, so that they needn't all be held."""
        n, total = 0, 0.0
        for x in chunks():
            n, total = n + len(x), total + np.abs(x).sum(0)
        average = total / n
        self.scale = np.where(average > 1e-12, average, 1.0)
        mean = sum(self._shrunk(x).sum(0) for x in chunks()) / n
        std = np.sqrt(sum(((self._shrunk(x) - mean) ** 2).sum(0) for x in chunks()) / n)
        self.mean = np.where(self.as_is, 0, mean)
        self.std = np.where(self.as_is, 1, np.maximum(1.0, std))
        return self

    def transform(self, x: np.ndarray) -> np.ndarray:
        return (self._shrunk(x) - self.mean) / self.std
