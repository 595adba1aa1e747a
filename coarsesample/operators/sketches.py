"""Per-partition statistics: measures, equal-depth histograms, k-minimum-value sketches, heavy hitters.

Measures of all columns come from one aggregation. The other sketches start from value counts per
(partition, column), which partial aggregation shrinks before the shuffle; all later steps are
windows inside a (partition, column) pair, never over the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from coarsesample.functions.portable import HASH_SPACE, hash32


def measures(df: DataFrame, cols: list[str], log_cols: tuple[str, ...] = ()) -> DataFrame:
    """part_id, col_name, n_rows, n_null, min, max, mean, mean_sq and, for positive columns, their logs' moments."""
    null = F.lit(None).cast("double")

    def one(c: str) -> Column:
        x = F.col(c).cast("double")
        log = F.ln(x) if c in log_cols else None
        logs = [F.min(log), F.max(log), F.avg(log), F.avg(log * log)] if log is not None else [null] * 4
        fields = [F.lit(c), F.count(F.lit(1)), F.count(F.when(F.col(c).isNull(), 1)), F.min(x), F.max(x), F.avg(x), F.avg(x * x), *logs]
        names = ["col_name", "n_rows", "n_null", "min", "max", "mean", "mean_sq", "log_min", "log_max", "log_mean", "log_mean_sq"]
        return F.struct(*[f.alias(n) for f, n in zip(fields, names, strict=True)])

    return df.groupBy("part_id").agg(F.array(*map(one, cols)).alias("m")).select("part_id", F.inline("m"))


def positive_columns(df: DataFrame, cols: list[str]) -> tuple[str, ...]:
    """Columns whose least value over the whole table is above zero; so every partition has the same features."""
    row = df.agg(*[F.min(F.col(c).cast("double")).alias(c) for c in cols]).first()
    return tuple(c for c in cols if row[c] is not None and row[c] > 0)


def value_counts(df: DataFrame, cols: list[str], kind: str) -> DataFrame:
    """part_id, col_name, value, n over non-null values; ``kind`` is double or string."""
    each = F.array(*[F.struct(F.lit(c).alias("col_name"), F.col(c).cast(kind).alias("value")) for c in cols])
    long = df.select("part_id", F.inline(each))
    return long.where("value is not null").groupBy("part_id", "col_name", "value").agg(F.count(F.lit(1)).alias("n"))


_EACH = ("part_id", "col_name")


def histogram(counts: DataFrame, buckets: int = 10) -> DataFrame:
    """part_id, col_name, bucket, lo, hi, n_rows, ndv. Cuts move to the next change of value, so a value has one bucket."""
    ordered = Window.partitionBy(*_EACH).orderBy("value").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*_EACH)
    placed = counts.withColumn("bucket", F.floor(F.coalesce(F.sum("n").over(ordered), F.lit(0)) * buckets / F.sum("n").over(whole)).cast("int"))
    return placed.groupBy(*_EACH, "bucket").agg(F.min("value").alias("lo"), F.max("value").alias("hi"), F.sum("n").alias("n_rows"), F.count(F.lit(1)).alias("ndv"))


def hashed(counts: DataFrame) -> DataFrame:
    """String value counts as counts of their hashes."""
    return counts.groupBy(*_EACH, hash32(F.col("value")).cast("double").alias("value")).agg(F.sum("n").alias("n"))


def kmv(counts: DataFrame, k: int = 128) -> DataFrame:
    """part_id, col_name, hash, n: the k smallest distinct hashes and how often each occurred."""
    return kmv_shrink(counts.groupBy(*_EACH, hash32(F.col("value").cast("string")).alias("hash")).agg(F.sum("n").alias("n")), k)


def kmv_shrink(sketch: DataFrame, k: int) -> DataFrame:
    """The sketch of size ``k`` that a larger one holds."""
    rank = F.row_number().over(Window.partitionBy(*_EACH).orderBy("hash"))
    return sketch.withColumn("__r", rank).where(F.col("__r") <= k).drop("__r")


def kmv_merge(a: DataFrame, b: DataFrame, k: int = 128) -> DataFrame:
    """Sketch of the union of two pieces with the same part ids."""
    return kmv_shrink(a.unionByName(b).groupBy(*_EACH, "hash").agg(F.sum("n").alias("n")), k)


def kmv_features(sketch: DataFrame, k: int = 128) -> DataFrame:
    """Distinct estimate and the kept multiplicities' average, extremes and sum."""
    agg = sketch.groupBy(*_EACH).agg(F.count(F.lit(1)).alias("kept"), F.max("hash").alias("last"), F.avg("n").alias("freq_avg"), F.max("n").alias("freq_max"), F.min("n").alias("freq_min"), F.sum("n").alias("freq_sum"))
    ndv = F.when(F.col("kept") < k, F.col("kept").cast("double")).otherwise(F.lit((k - 1) * HASH_SPACE) / F.col("last"))
    return agg.select(*_EACH, ndv.alias("ndv"), "freq_avg", "freq_max", "freq_min", "freq_sum")


def heavy_hitters(counts: DataFrame, support: float = 0.01) -> DataFrame:
    """part_id, col_name, value, n of values with at least ``support`` of the partition's rows: exact."""
    whole = F.sum("n").over(Window.partitionBy(*_EACH))
    return counts.withColumn("__all", whole).where(F.col("n") >= F.col("__all") * support).drop("__all")


def exact_dictionary(counts: DataFrame, most: int = 100) -> DataFrame:
    """All values of columns that have at most ``most`` of them in a partition."""
    return counts.withColumn("__d", F.count(F.lit(1)).over(Window.partitionBy(*_EACH))).where(F.col("__d") <= most).drop("__d")


class LossyCounter:
    """Frequent values in one pass with bounded memory; see the guarantees in the tests."""

    def __init__(self, epsilon: float):
        self.width = max(1, round(1 / epsilon))
        self.seen, self.entries = 0, {}

    def add(self, value) -> None:
        self.seen += 1
        epoch = -(-self.seen // self.width)
        if value in self.entries:
            self.entries[value][0] += 1
        else:
            self.entries[value] = [1, epoch - 1]
        if self.seen % self.width == 0:
            self.entries = {v: e for v, e in self.entries.items() if e[0] + e[1] > epoch}

    def report(self, support: float, epsilon: float) -> list[tuple]:
        least = (support - epsilon) * self.seen
        found = sorted(((v, f, e) for v, (f, e) in self.entries.items() if f >= least), key=lambda x: (-x[1], str(x[0])))
        return found[: int(1 / support)]


def lossy_heavy_hitters(df: DataFrame, cols: list[str], support: float = 0.01, epsilon: float = 0.001) -> DataFrame:
    """part_id, col_name, value, freq, err by one pass over each partition, a batch at a time.

    Rows come sorted by partition, so a task streams through its partitions and holds one partition's
    counters, of bounded size, and one batch.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now, counters = None, {}

        def report() -> pd.DataFrame:
            rows = [(int(now), c, v, f, e) for c in cols for v, f, e in counters[c].report(support, epsilon)]
            return pd.DataFrame(rows, columns=["part_id", "col_name", "value", "freq", "err"])

        for batch in batches:
            for part, rows in batch.groupby("part_id", sort=True):
                if part != now:
                    if now is not None:
                        yield report()
                    now, counters = part, {c: LossyCounter(epsilon) for c in cols}
                for c in cols:
                    add = counters[c].add
                    for v in rows[c].dropna():
                        add(v)
        if now is not None:
            yield report()

    chosen = df.select("part_id", *[F.col(c).cast("string").alias(c) for c in cols])
    return chosen.repartition("part_id").sortWithinPartitions("part_id").mapInPandas(run, "part_id int, col_name string, value string, freq long, err long")


def frequent_items(df: DataFrame, col: str, k: int = 5) -> DataFrame:
    """The built-in top-k sketch per partition."""
    return df.groupBy("part_id").agg(F.expr(f"approx_top_k({col}, {k}, 1000)").alias("items"))


def global_heavy_hitters(hitters: DataFrame, cap: int = 25) -> DataFrame:
    """col_name, value, n, bit: each column's most frequent items over all partitions' dictionaries."""
    total = hitters.groupBy("col_name", "value").agg(F.sum("n").alias("n"))
    rank = F.row_number().over(Window.partitionBy("col_name").orderBy(F.desc("n"), "value"))
    return total.withColumn("bit", (rank - 1).cast("int")).where(F.col("bit") < cap)


def sketch_bytes(measure: DataFrame, hist: DataFrame, sketch: DataFrame, hitters: DataFrame) -> DataFrame:
    """kind, bytes per partition on average: eight bytes a number, a value's own bytes, four for a count."""
    parts = measure.agg(F.countDistinct("part_id").alias("parts"))
    kinds = [
        measure.select(F.lit("measures").alias("kind"), F.lit(8 * 8).alias("b")),
        hist.select(F.lit("histogram").alias("kind"), F.lit(8 * 4).alias("b")),
        sketch.select(F.lit("distinct").alias("kind"), F.lit(8 + 4).alias("b")),
        hitters.select(F.lit("heavy_hitters").alias("kind"), (F.octet_length(F.col("value").cast("string")) + 4).alias("b")),
    ]
    every = kinds[0]
    for k in kinds[1:]:
        every = every.unionByName(k)
    return every.groupBy("kind").agg(F.sum("b").alias("total")).crossJoin(F.broadcast(parts)).select("kind", (F.col("total") / F.col("parts")).alias("bytes_per_part"))
