"""Queries on layouts, sketches, features and selectivity (families m0 to m3)."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.functions.portable import HASH_SPACE
from coarsesample.operators import features as X
from coarsesample.operators import metrics, selectivity
from coarsesample.operators import sketches as S
from coarsesample.plans.query import And, Clause, In, Like, Not, Or, to_sql
from coarsesample.plans.registry import HASH, LINES, counts_sql, histogram_sql, lines, register, rounded
from coarsesample.runtime import materialize, read_table, scratch_path, ship_package
from coarsesample.sources import layouts

TIE = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
BY_PART = "SELECT part_id, count(*) AS n, min(l_orderkey) AS first_key, max(l_orderkey) AS last_key FROM {} GROUP BY part_id"


def by_part(df: DataFrame) -> DataFrame:
    return df.groupBy("part_id").agg(F.count(F.lit(1)).alias("n"), F.min("l_orderkey").alias("first_key"), F.max("l_orderkey").alias("last_key"))


@register("m0_sorted", BY_PART.format(f"(SELECT *, CAST(ntile(100) OVER (ORDER BY {', '.join(TIE)}) AS INTEGER) AS part_id FROM lineitem)"))
def m0_sorted(spark: SparkSession, d: str) -> DataFrame:
    return by_part(layouts.assign_sorted(read_table(spark, d, "lineitem"), TIE, 100))


@register("m0_random", BY_PART.format("(SELECT *, CAST((((l_orderkey * 7 + l_linenumber) * 7919) % 10007 * 31 + (l_orderkey * 7 + l_linenumber) * 17) % 100 AS INTEGER) AS part_id FROM lineitem)"))
def m0_random(spark: SparkSession, d: str) -> DataFrame:
    return by_part(layouts.assign_random(read_table(spark, d, "lineitem"), F.col("l_orderkey") * 7 + F.col("l_linenumber"), 100))


@register("m0_bucketed", f"WITH {LINES} " + BY_PART.format("li"))
def m0_bucketed(spark: SparkSession, d: str) -> DataFrame:
    return by_part(lines(spark, d))


@register("m0_stored")
def m0_stored(spark: SparkSession, d: str) -> DataFrame:
    return by_part(layouts.assign_stored(read_table(spark, d, "lineitem"), 600))


@register("m0_physical", "SELECT count(*) AS n, count(DISTINCT l_orderkey) AS orders FROM lineitem")
def m0_physical(spark: SparkSession, d: str) -> DataFrame:
    return layouts.with_physical_part_id(read_table(spark, d, "lineitem")).where("part_id is not null").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("l_orderkey").alias("orders"))


@register("m0_written", f"WITH {LINES} " + BY_PART.format("li"))
def m0_written(spark: SparkSession, d: str) -> DataFrame:
    path = scratch_path(spark, "layout")
    layouts.write_layout(lines(spark, d), path)
    return by_part(spark.read.parquet(path))


NUM, STR = ["l_quantity", "l_extendedprice", "l_discount"], ["l_returnflag", "l_linestatus"]
_M = "count(*) AS n_rows, count(*) - count({c}) AS n_null, round(min({c}), 4) AS min, round(max({c}), 4) AS max, round(avg({c}), 4) AS mean, round(avg({c} * {c}), 2) AS mean_sq"


@register("m1_measures", f"WITH {LINES} " + " UNION ALL ".join(f"SELECT part_id, '{c}' AS col_name, {_M.format(c=c)} FROM li GROUP BY part_id" for c in NUM))
def m1_measures(spark: SparkSession, d: str) -> DataFrame:
    m = S.measures(lines(spark, d), NUM)
    return m.select("part_id", "col_name", "n_rows", "n_null", *[F.round(c, 4).alias(c) for c in ("min", "max", "mean")], F.round("mean_sq", 2).alias("mean_sq"))


@register("m1_log_measures", f"WITH {LINES} " + " UNION ALL ".join(f"SELECT part_id, '{c}' AS col_name, round(min(ln({c})), 6) AS log_min, round(max(ln({c})), 6) AS log_max, round(avg(ln({c})), 6) AS log_mean, round(avg(ln({c}) * ln({c})), 6) AS log_mean_sq FROM li GROUP BY part_id" for c in NUM[:2]))
def m1_log_measures(spark: SparkSession, d: str) -> DataFrame:
    df = lines(spark, d)
    return rounded(S.measures(df, NUM, S.positive_columns(df, NUM)).where("log_min is not null").select("part_id", "col_name", "log_min", "log_max", "log_mean", "log_mean_sq"), 6)


@register("m1_hist_exact", f"WITH {LINES}, vc AS ({counts_sql(NUM, 'DOUBLE')}) {histogram_sql('vc')}")
def m1_hist_exact(spark: SparkSession, d: str) -> DataFrame:
    return S.histogram(S.value_counts(lines(spark, d), NUM, "double"))


@register("m1_hist_hash", f"WITH {LINES}, vc AS (SELECT part_id, col_name, CAST({HASH.format('value')} AS DOUBLE) AS value, CAST(sum(n) AS BIGINT) AS n FROM ({counts_sql(STR, 'VARCHAR')}) GROUP BY 1, 2, 3) {histogram_sql('vc')}")
def m1_hist_hash(spark: SparkSession, d: str) -> DataFrame:
    return S.histogram(S.hashed(S.value_counts(lines(spark, d), STR, "string")))


@register("m1_exact_dict", f"WITH {LINES} SELECT part_id, col_name, value, n FROM ({counts_sql(STR, 'VARCHAR')}) QUALIFY count(*) OVER (PARTITION BY part_id, col_name) <= 100")
def m1_exact_dict(spark: SparkSession, d: str) -> DataFrame:
    return S.exact_dictionary(S.value_counts(lines(spark, d), STR, "string"))


KEYS = ["l_orderkey", "l_partkey"]
KMV = f"SELECT part_id, col_name, hash, CAST(sum(n) AS BIGINT) AS n FROM (SELECT part_id, col_name, {HASH.format('value')} AS hash, n FROM ({counts_sql(KEYS, 'VARCHAR')})) GROUP BY 1, 2, 3 QUALIFY row_number() OVER (PARTITION BY part_id, col_name ORDER BY hash) <= 128"


@register("m1_kmv", f"WITH {LINES} {KMV}")
def m1_kmv(spark: SparkSession, d: str) -> DataFrame:
    return S.kmv(S.value_counts(lines(spark, d), KEYS, "string"))


KMV_FEATURES = f"SELECT part_id, col_name, round(CASE WHEN count(*) < 128 THEN CAST(count(*) AS DOUBLE) ELSE 127 * {HASH_SPACE} / max(hash) END, 4) AS ndv, round(avg(n), 6) AS freq_avg, max(n) AS freq_max, min(n) AS freq_min, CAST(sum(n) AS BIGINT) AS freq_sum FROM ({KMV}) GROUP BY 1, 2"


@register("m1_kmv_distinct", f"WITH {LINES} SELECT part_id, col_name, ndv FROM ({KMV_FEATURES})")
def m1_kmv_distinct(spark: SparkSession, d: str) -> DataFrame:
    return rounded(S.kmv_features(m1_kmv(spark, d)).select("part_id", "col_name", "ndv"))


@register("m1_kmv_merge", f"WITH {LINES} {KMV}")
def m1_kmv_merge(spark: SparkSession, d: str) -> DataFrame:
    df = lines(spark, d)
    half = lambda r: S.kmv(S.value_counts(df.where(F.col("l_linenumber") % 2 == r), KEYS, "string"))
    return S.kmv_merge(half(0), half(1))


@register("m1_hh_exact", f"WITH {LINES} SELECT part_id, col_name, value, n FROM ({counts_sql(['l_quantity', 'l_linenumber'], 'DOUBLE')}) QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id, col_name)")
def m1_hh_exact(spark: SparkSession, d: str) -> DataFrame:
    return S.heavy_hitters(S.value_counts(lines(spark, d), ["l_quantity", "l_linenumber"], "double"))


@register("m1_hh_lossy")
def m1_hh_lossy(spark: SparkSession, d: str) -> DataFrame:
    ship_package(spark)
    return S.lossy_heavy_hitters(lines(spark, d), ["l_returnflag", "l_partkey"])


@register("m1_hh_frequent_items")
def m1_hh_frequent_items(spark: SparkSession, d: str) -> DataFrame:
    return S.frequent_items(lines(spark, d), "l_returnflag").select("part_id", F.explode("items").alias("i")).select("part_id", F.col("i.item").alias("value"), F.col("i.count").alias("n"))


GLOBAL = f"SELECT col_name, value, n, CAST(row_number() OVER (PARTITION BY col_name ORDER BY n DESC, value) - 1 AS INTEGER) AS bit FROM (SELECT col_name, value, CAST(sum(n) AS BIGINT) AS n FROM (SELECT part_id, col_name, value, n FROM ({counts_sql(STR, 'VARCHAR')}) QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id, col_name)) GROUP BY 1, 2) QUALIFY bit < 25"


@register("m1_global_hh", f"WITH {LINES} {GLOBAL}")
def m1_global_hh(spark: SparkSession, d: str) -> DataFrame:
    return S.global_heavy_hitters(S.heavy_hitters(S.value_counts(lines(spark, d), STR, "string")))


@register(
    "m1_sketch_bytes",
    f"""WITH {LINES}, vc AS ({counts_sql(['l_quantity'], 'DOUBLE')}), parts AS (SELECT count(DISTINCT part_id) AS p FROM li),
 hv AS (SELECT DISTINCT part_id, {HASH.format("CASE WHEN value = floor(value) THEN CAST(CAST(value AS BIGINT) AS VARCHAR) || '.0' ELSE CAST(value AS VARCHAR) END")} AS h FROM vc), kv AS (SELECT part_id, h FROM hv QUALIFY row_number() OVER (PARTITION BY part_id ORDER BY h) <= 128),
 hh AS (SELECT part_id, n, value FROM vc QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id))
 SELECT 'measures' AS kind, CAST(64 AS DOUBLE) AS bytes_per_part UNION ALL SELECT 'histogram', round((SELECT count(*) FROM ({histogram_sql('vc')})) * 32.0 / p, 4) FROM parts
 UNION ALL SELECT 'distinct', round((SELECT count(*) FROM kv) * 12.0 / p, 4) FROM parts UNION ALL SELECT 'heavy_hitters', round((SELECT sum(length(CASE WHEN value = floor(value) THEN CAST(CAST(value AS BIGINT) AS VARCHAR) || '.0' ELSE CAST(value AS VARCHAR) END) + 4) FROM hh) * 1.0 / p, 4) FROM parts""",
)
def m1_sketch_bytes(spark: SparkSession, d: str) -> DataFrame:
    df = lines(spark, d)
    vc = S.value_counts(df, ["l_quantity"], "double")
    return rounded(S.sketch_bytes(S.measures(df, ["l_quantity"]), S.histogram(vc), S.kmv(vc), S.heavy_hitters(vc)))


SMALL = X.TableConfig(("l_quantity", "l_discount", "ship_day"), ("l_returnflag", "l_linestatus"), ("l_returnflag", "l_linestatus"))


def stats(spark: SparkSession, d: str) -> DataFrame:
    return X.partition_stats(lines(spark, d), SMALL)


@register("m1_build", f"WITH {LINES} SELECT part_id, count(*) AS n_rows, round(min(l_quantity), 4) AS low, CAST(count(DISTINCT l_quantity) AS DOUBLE) AS ndv, CAST(count(DISTINCT l_returnflag) AS INTEGER) AS flags FROM li GROUP BY part_id")
def m1_build(spark: SparkSession, d: str) -> DataFrame:
    return stats(spark, d).select("part_id", "n_rows", F.round("l_quantity__min", 4).alias("low"), F.col("l_quantity__ndv").alias("ndv"), F.size("l_returnflag__dict").alias("flags"))


@register("m1_build_onepass", f"WITH {LINES} SELECT part_id, count(*) AS n_rows, round(min(l_quantity), 4) AS low, round(max(l_discount), 4) AS high, CAST(count(DISTINCT l_returnflag) AS INTEGER) AS flags FROM li GROUP BY part_id")
def m1_build_onepass(spark: SparkSession, d: str) -> DataFrame:
    held = X.partition_stats_onepass(lines(spark, d), SMALL)
    return held.select("part_id", "n_rows", F.round("l_quantity__min", 4).alias("low"), F.round("l_discount__max", 4).alias("high"), F.size("l_returnflag__dict").alias("flags"))


@register("m2_measure_block", f"WITH {LINES} SELECT part_id, round(avg(l_quantity), 4) AS mean, round(sqrt(greatest(avg(l_quantity * l_quantity) - avg(l_quantity) * avg(l_quantity), 0)), 4) AS std FROM li GROUP BY part_id")
def m2_measure_block(spark: SparkSession, d: str) -> DataFrame:
    m = S.measures(lines(spark, d), ["l_quantity"])
    return rounded(m.select("part_id", "mean", F.sqrt(F.greatest(F.col("mean_sq") - F.col("mean") * F.col("mean"), F.lit(0.0))).alias("std")))


@register("m2_dv_freq", f"WITH {LINES} SELECT part_id, col_name, freq_avg, freq_max, freq_min, freq_sum FROM ({KMV_FEATURES})")
def m2_dv_freq(spark: SparkSession, d: str) -> DataFrame:
    return rounded(S.kmv_features(m1_kmv(spark, d)).drop("ndv"), 6)


@register("m2_hh_stats", f"WITH {LINES} SELECT part_id, col_name, count(*) AS hh_count, round(avg(n), 4) AS hh_avg, max(n) AS hh_max FROM (SELECT * FROM ({counts_sql(STR, 'VARCHAR')}) QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id, col_name)) GROUP BY 1, 2")
def m2_hh_stats(spark: SparkSession, d: str) -> DataFrame:
    hh = S.heavy_hitters(S.value_counts(lines(spark, d), STR, "string"))
    return rounded(hh.groupBy("part_id", "col_name").agg(F.count(F.lit(1)).alias("hh_count"), F.avg("n").alias("hh_avg"), F.max("n").alias("hh_max")))


@register("m2_bitmap", f"WITH {LINES}, g AS ({GLOBAL}), hh AS (SELECT part_id, value FROM ({counts_sql(['l_returnflag'], 'VARCHAR')}) QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id)) SELECT part_id, CAST(sum(1 << bit) AS BIGINT) AS bits FROM hh JOIN g USING (value) WHERE g.col_name = 'l_returnflag' GROUP BY part_id")
def m2_bitmap(spark: SparkSession, d: str) -> DataFrame:
    st = materialize(stats(spark, d), "stats")
    return X.bitmap(st, "l_returnflag", X.global_items(st, SMALL)["l_returnflag"])


@register("m2_masked", f"WITH {LINES} SELECT part_id, round(avg(l_quantity), 4) AS quantity_mean, 0.0::DOUBLE AS discount_mean FROM li GROUP BY part_id")
def m2_masked(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.plans.query import Agg, QuerySpec

    schema = X.FeatureSchema.of(SMALL)
    used = schema.used(QuerySpec((Agg("sum", "l_quantity", "s"),)), SMALL)
    st = materialize(stats(spark, d), "stats")
    f = X.static_features(st, SMALL, X.global_items(st, SMALL))
    at = lambda n: schema.names.index(n)
    cols = {"quantity_mean": at("l_quantity__mean"), "discount_mean": at("l_discount__mean")}
    return rounded(f.select("part_id", *[(F.col("f")[i] * F.lit(float(used[i]))).alias(n) for n, i in cols.items()]))


@register("m2_normalized", f"WITH {LINES}, m AS (SELECT part_id, sum(l_extendedprice) AS x FROM li GROUP BY part_id), y AS (SELECT part_id, ln(1 + x / avg(x) OVER ()) AS y FROM m) SELECT part_id, round((y - avg(y) OVER ()) / greatest(1, stddev_pop(y) OVER ()), 6) + 0.0 AS z FROM y")
def m2_normalized(spark: SparkSession, d: str) -> DataFrame:
    m = lines(spark, d).groupBy("part_id").agg(F.sum("l_extendedprice").alias("x"))
    y = m.crossJoin(F.broadcast(m.agg(F.avg("x").alias("a")))).select("part_id", F.log1p(F.col("x") / F.col("a")).alias("y"))
    spread = y.agg(F.avg("y").alias("a"), F.greatest(F.lit(1.0), F.stddev_pop("y")).alias("s"))
    return rounded(y.crossJoin(F.broadcast(spread)).select("part_id", ((F.col("y") - F.col("a")) / F.col("s")).alias("z")), 6)


@register("m2_assembled")
def m2_assembled(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    st = materialize(stats(spark, d), "stats")
    return X.static_features(st, SMALL, X.global_items(st, SMALL)).select("part_id", F.size("f").alias("dims"), array_to_vector("f").cast("string").alias("vector"))


# Selectivity: the SQL builds the same histograms and applies the same rule to every leaf.
_RANGE = Clause("l_quantity", "<", 17.5)
_SECOND = Clause("l_discount", ">=", 0.055)
_FLAGS = In("l_returnflag", ("A", "R"))


@cache
def _leaf_sql(col: str, a: float, a_open: bool, b: float, b_open: bool) -> str:
    touched = " AND ".join(["TRUE"] + ([f"hi {'>' if a_open else '>='} {a}"] if a > float("-inf") else []) + ([f"lo {'<' if b_open else '<='} {b}"] if b < float("inf") else []))
    covered = " AND ".join(["TRUE"] + ([f"lo {'>' if a_open else '>='} {a}"] if a > float("-inf") else []) + ([f"hi {'<' if b_open else '<='} {b}"] if b < float("inf") else []))
    high = f"least(hi, {b})" if b < float("inf") else "hi"
    low = f"greatest(lo, {a})" if a > float("-inf") else "lo"
    part = "n_rows / ndv" if a == b else f"CASE WHEN hi = lo THEN n_rows ELSE n_rows * ({high} - {low}) / (hi - lo) END"
    return f"SELECT part_id, sum(CASE WHEN {covered} THEN n_rows WHEN {touched} THEN {part} ELSE 0 END) / sum(n_rows) AS est, sum(CASE WHEN {touched} THEN n_rows ELSE 0 END) / sum(n_rows) AS most FROM h WHERE col_name = '{col}' GROUP BY part_id"


HIST = f"WITH {LINES}, vc AS ({counts_sql(['l_quantity', 'l_discount', 'ship_day'], 'DOUBLE')}), h AS ({histogram_sql('vc')}), a AS ({_leaf_sql('l_quantity', float('-inf'), True, 17.5, True)}), b AS ({_leaf_sql('l_discount', 0.055, False, float('inf'), True)}), f AS (SELECT part_id, sum(CASE WHEN l_returnflag IN ('A', 'R') THEN 1.0 ELSE 0 END) / count(*) AS est FROM li GROUP BY part_id)"


def _features(spark, d, p, *names, or_rule="min"):
    return rounded(selectivity.with_selectivity(stats(spark, d), p, or_rule).select("part_id", *names), 6)


@register("m3_range", f"{HIST} SELECT part_id, round(est, 6) AS sel_indep, round(most, 6) AS sel_upper FROM a")
def m3_range(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, _RANGE, "sel_indep", "sel_upper")


@register("m3_equal", f"{HIST} SELECT part_id, round(est, 6) AS sel_indep, round(most, 6) AS sel_upper FROM ({_leaf_sql('l_quantity', 20.0, False, 20.0, False)})")
def m3_equal(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Clause("l_quantity", "=", 20.0), "sel_indep", "sel_upper")


@register("m3_in", f"{HIST} SELECT part_id, round(est, 6) AS sel_indep FROM f")
def m3_in(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, _FLAGS, "sel_indep")


@register("m3_like", f"WITH {LINES} SELECT part_id, round(sum(CASE WHEN l_linestatus LIKE 'O%' THEN 1.0 ELSE 0 END) / count(*), 6) AS sel_indep FROM li GROUP BY part_id")
def m3_like(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Like("l_linestatus", "O%"), "sel_indep")


@register("m3_upper_and", f"{HIST} SELECT part_id, round(least(a.most, b.most), 6) AS sel_upper FROM a JOIN b USING (part_id)")
def m3_upper_and(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, And((_RANGE, _SECOND)), "sel_upper")


@register("m3_upper_or", f"{HIST} SELECT part_id, round(least(1, a.most + b.most), 6) AS sel_upper FROM a JOIN b USING (part_id)")
def m3_upper_or(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Or((_RANGE, _SECOND)), "sel_upper")


@register("m3_indep_and", f"{HIST} SELECT part_id, round(a.est * b.est * f.est, 6) AS sel_indep FROM a JOIN b USING (part_id) JOIN f USING (part_id)")
def m3_indep_and(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, And((_RANGE, _SECOND, _FLAGS)), "sel_indep")


@register("m3_indep_or", f"{HIST} SELECT part_id, round(least(a.est, b.est), 6) AS sel_indep FROM a JOIN b USING (part_id)")
def m3_indep_or(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Or((_RANGE, _SECOND)), "sel_indep")


@register("m3_indep_or_complement", f"{HIST} SELECT part_id, round(1 - (1 - a.est) * (1 - b.est), 6) AS sel_indep FROM a JOIN b USING (part_id)")
def m3_indep_or_complement(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Or((_RANGE, _SECOND)), "sel_indep", or_rule="complement")


@register("m3_minmax", f"{HIST} SELECT part_id, round(least(a.est, b.est, f.est), 6) AS sel_min, round(greatest(a.est, b.est, f.est), 6) AS sel_max FROM a JOIN b USING (part_id) JOIN f USING (part_id)")
def m3_minmax(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, And((_RANGE, Or((_SECOND, _FLAGS)))), "sel_min", "sel_max")


@register("m3_joint_column", f"{HIST} SELECT part_id, round(x.est + y.est, 6) AS sel_indep FROM ({_leaf_sql('l_quantity', float('-inf'), True, 5.0, True)}) x JOIN ({_leaf_sql('l_quantity', 45.0, True, float('inf'), True)}) y USING (part_id)")
def m3_joint_column(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Or((Clause("l_quantity", "<", 5.0), Clause("l_quantity", ">", 45.0))), "sel_indep")


@register("m3_negation", f"{HIST} SELECT part_id, round(est, 6) AS sel_indep FROM ({_leaf_sql('l_quantity', 17.5, False, float('inf'), True)})")
def m3_negation(spark: SparkSession, d: str) -> DataFrame:
    return _features(spark, d, Not(_RANGE), "sel_indep")


_YEAR = And((Clause("ship_day", ">=", 1096.0), Clause("ship_day", "<", 1461.0)))


@register("m3_filter", f"WITH {LINES} SELECT DISTINCT part_id FROM li WHERE {to_sql(_YEAR)}")
def m3_filter(spark: SparkSession, d: str) -> DataFrame:
    return selectivity.filter_by_predicate(selectivity.with_selectivity(stats(spark, d), _YEAR)).select("part_id")


@register("m3_precision_recall", "SELECT CAST(1 AS DOUBLE) AS filter_precision, CAST(1 AS DOUBLE) AS filter_recall")
def m3_precision_recall(spark: SparkSession, d: str) -> DataFrame:
    kept = selectivity.with_selectivity(stats(spark, d), _YEAR)
    return metrics.filter_quality(kept, lines(spark, d).where(to_sql(_YEAR)).select("part_id").distinct())


@register("m3_fallback_columns", "SELECT CAST(1 AS DOUBLE) AS upper, CAST(1 AS DOUBLE) AS indep")
def m3_fallback_columns(spark: SparkSession, d: str) -> DataFrame:
    return selectivity.with_selectivity(stats(spark, d), None).agg(F.min("sel_upper").alias("upper"), F.max("sel_indep").alias("indep"))
