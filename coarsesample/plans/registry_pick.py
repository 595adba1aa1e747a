"""Queries on picking, execution, baselines and measures (families m4, m5, b, c)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from coarsesample.functions.portable import draw_order
from coarsesample.operators import baselines, clustering, metrics, picker
from coarsesample.operators import sketches as S
from coarsesample.operators.execute import weighted_aggregate, weighted_scan
from coarsesample.plans import experiments
from coarsesample.plans.query import Agg, And, Clause, In, Like, QuerySpec, estimate, exact, parse_sql, partials, validate
from coarsesample.plans.registry import LINES, WIDE, answer_sql, lines, register, rounded
from coarsesample.plans.training import select_features
from coarsesample.runtime import bytes_under, read_table, ship_package
from coarsesample.sources import tables

# A fixed stand-in for occurrence patterns: most partitions share one, some are rare.
PATTERN = "CAST(CASE WHEN part_id % 37 = 0 THEN part_id % 4 WHEN part_id % 50 = 7 THEN 20 ELSE 9 END AS BIGINT)"
PARTS = f"parts AS (SELECT DISTINCT part_id, {PATTERN} AS bits FROM li)"
RARE = "rare AS (SELECT bits, count(*) AS size FROM parts GROUP BY bits QUALIFY count(*) < 10 AND count(*) < 0.1 * max(count(*)) OVER ())"


def patterns(spark: SparkSession, d: str) -> DataFrame:
    return lines(spark, d).select("part_id").distinct().withColumn("bits", F.expr(PATTERN))


@register("m4_outliers", f"WITH {LINES}, {PARTS}, {RARE} SELECT part_id, bits, size FROM parts JOIN rare USING (bits)")
def m4_outliers(spark: SparkSession, d: str) -> DataFrame:
    return picker.outlier_groups(patterns(spark, d))


@register("m4_outliers_capped", f"WITH {LINES}, {PARTS}, {RARE}, run AS (SELECT bits, sum(size) OVER (ORDER BY size, bits ROWS UNBOUNDED PRECEDING) AS s FROM rare) SELECT part_id FROM parts JOIN run USING (bits) WHERE s <= 3")
def m4_outliers_capped(spark: SparkSession, d: str) -> DataFrame:
    return picker.cap_outliers(picker.outlier_groups(patterns(spark, d)), 3).select("part_id")


Q_YEAR = QuerySpec((Agg("sum", "l_extendedprice", "s"), Agg("count", "*", "n")), And((Clause("ship_day", ">=", 1096.0), Clause("ship_day", "<", 1461.0))), ("l_returnflag", "l_linestatus"))
P_SQL = "p AS (SELECT part_id, l_returnflag, l_linestatus, sum(l_extendedprice) AS s__s, CAST(count(*) AS DOUBLE) AS n__s FROM li WHERE ship_day >= 1096.0 AND ship_day < 1461.0 GROUP BY 1, 2, 3)"


def year_parts(spark: SparkSession, d: str) -> DataFrame:
    return partials(lines(spark, d), Q_YEAR)


def _contribution_sql(variant: str) -> str:
    how, kind = variant.split("_")
    rel = [f"{a} / sum({a}) OVER (PARTITION BY l_returnflag, l_linestatus)" for a in ("s__s", "n__s")]
    x, y = rel if kind == "rel" else ["abs(s__s)", "abs(n__s)"]
    e = f"max(greatest(x, y))" if how == "max" else "avg((x + y) / 2)"
    return f"SELECT part_id, greatest({e}, 0) AS contribution FROM (SELECT part_id, {x} AS x, {y} AS y FROM p) GROUP BY part_id"


def _contribution(variant: str):
    @register(f"m4_contribution_{variant}", f"WITH {LINES}, {P_SQL} SELECT part_id, round(contribution, 6) AS contribution FROM ({_contribution_sql(variant)})")
    def run(spark: SparkSession, d: str) -> DataFrame:
        return rounded(metrics.contribution(year_parts(spark, d), ["l_returnflag", "l_linestatus"], ["s__s", "n__s"], variant), 6)

    return run


for _v in ("max_rel", "mean_rel", "max_abs", "mean_abs"):
    _contribution(_v)


RARE = "l_shipdate >= DATE '1998-01-01' AND l_shipdate < DATE '1999-01-01' AND l_quantity > 49.5"


@register("m4_cutoffs", f"WITH {LINES}, s AS (SELECT count(DISTINCT CASE WHEN {RARE} THEN part_id END) / count(DISTINCT part_id)::DOUBLE AS first FROM li) SELECT model, round(CASE WHEN first <= 0.01 THEN first ELSE first * power(0.01 / first, model / 3.0::DOUBLE) END, 6) AS fraction FROM s, (VALUES (0), (1), (2), (3)) t(model)")
def m4_cutoffs(spark: SparkSession, d: str) -> DataFrame:
    """Cut-offs from the share of partitions that contribute to a query."""
    parts = lines(spark, d).groupBy("part_id").agg(F.max(F.expr(f"CASE WHEN {RARE} THEN 1.0D ELSE 0.0D END")).alias("hit"))
    first = parts.agg(F.avg("hit").alias("first")).first()["first"]
    return rounded(spark.createDataFrame(list(enumerate(metrics.cutoff_fractions(first))), "model int, fraction double"), 6)


SCORES = "scores AS (SELECT part_id, avg(l_quantity) - 25.4 AS a, avg(l_discount) - 0.05 AS b FROM li GROUP BY part_id)"


@register("m4_levels_fixed_scores", f"WITH {LINES}, {SCORES} SELECT part_id, CASE WHEN a <= 0 THEN 0 WHEN b <= 0 THEN 1 ELSE 2 END AS level FROM scores")
def m4_levels_fixed_scores(spark: SparkSession, d: str) -> DataFrame:
    rows = lines(spark, d).groupBy("part_id").agg((F.avg("l_quantity") - 25.4).alias("a"), (F.avg("l_discount") - 0.05).alias("b")).toPandas()
    level = picker.importance_levels([rows["a"].to_numpy(), rows["b"].to_numpy()])
    return spark.createDataFrame([(int(p), int(x)) for p, x in zip(rows["part_id"], level, strict=True)], "part_id int, level int")


PRIORITY = "CAST(5 - CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS INTEGER)"
ALLOCATE = f"""WITH s AS (SELECT {PRIORITY} AS level, count(*) AS size FROM orders GROUP BY 1), n AS (SELECT case_id, CAST(floor((SELECT sum(size) FROM s) * share) AS BIGINT) AS n FROM (VALUES ('a', 0.1::DOUBLE), ('b', 0.6::DOUBLE)) t(case_id, share)),
 b AS (SELECT case_id, n, j, (n - coalesce(sum(size) FILTER (level >= j), 0)) / sum(size * power(2.0::DOUBLE, level)) FILTER (level < j) AS base FROM n, s, range(1, 6) t(j) GROUP BY case_id, n, j), o AS (SELECT * FROM b WHERE base * power(2.0::DOUBLE, j - 1) <= 1 + 1e-12 QUALIFY row_number() OVER (PARTITION BY case_id ORDER BY j DESC) = 1),
 w AS (SELECT case_id, n, level, CASE WHEN level >= j THEN size::DOUBLE ELSE base * power(2.0::DOUBLE, level) * size END AS want FROM o, s), f AS (SELECT *, floor(want + 1e-9) AS whole FROM w)
 SELECT case_id, level, CAST(whole + CASE WHEN row_number() OVER (PARTITION BY case_id ORDER BY round(want - whole, 9) DESC, level DESC) <= n - sum(whole) OVER (PARTITION BY case_id) THEN 1 ELSE 0 END AS INTEGER) AS reads FROM f"""


@register("m4_allocate", ALLOCATE)
def m4_allocate(spark: SparkSession, d: str) -> DataFrame:
    """Reads of levels by order priority, the urgent ones most important, at a tenth and at six tenths of all."""
    found = read_table(spark, d, "orders").groupBy(F.expr(PRIORITY).alias("level")).count().orderBy("level").collect()
    sizes = [r["count"] for r in found]
    cases = {c: picker.allocate(sizes, int(sum(sizes) * share)) for c, share in (("a", 0.1), ("b", 0.6))}
    return spark.createDataFrame([(c, r["level"], int(n)) for c, reads in cases.items() for r, n in zip(found, reads, strict=True)], "case_id string, level int, reads int")


FEATS = "f AS (SELECT part_id, part_id % 5 AS cluster, avg(l_quantity) AS x, avg(l_discount) * 100 AS y FROM li GROUP BY part_id)"


def fixed_clusters(spark: SparkSession, d: str) -> DataFrame:
    return lines(spark, d).groupBy("part_id").agg(F.avg("l_quantity").alias("x"), (F.avg("l_discount") * 100).alias("y")).withColumn("cluster", F.col("part_id") % 5)


@register("m4_exemplar_median", f"WITH {LINES}, {FEATS}, m AS (SELECT cluster, quantile_cont(x, 0.5) AS mx, quantile_cont(y, 0.5) AS my, count(*) AS size FROM f GROUP BY 1) SELECT cluster, part_id, size AS weight FROM f JOIN m USING (cluster) QUALIFY row_number() OVER (PARTITION BY cluster ORDER BY round((x - mx) * (x - mx) + (y - my) * (y - my), 9), part_id) = 1")
def m4_exemplar_median(spark: SparkSession, d: str) -> DataFrame:
    f = fixed_clusters(spark, d)
    m = f.groupBy("cluster").agg(F.percentile("x", 0.5).alias("mx"), F.percentile("y", 0.5).alias("my"), F.count(F.lit(1)).alias("weight"))
    far = F.round((F.col("x") - F.col("mx")) ** 2 + (F.col("y") - F.col("my")) ** 2, 9)
    return f.join(F.broadcast(m), "cluster").withColumn("r", F.row_number().over(Window.partitionBy("cluster").orderBy(far, "part_id"))).where("r = 1").select("cluster", "part_id", "weight")


@register("m4_exemplar_random", f"WITH {LINES}, {FEATS} SELECT cluster, part_id FROM f QUALIFY row_number() OVER (PARTITION BY cluster ORDER BY (part_id * 7919 + 3 * 104729) % 10007, part_id) = 1")
def m4_exemplar_random(spark: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("cluster").orderBy(draw_order(F.col("part_id"), 3), "part_id")
    return fixed_clusters(spark, d).withColumn("r", F.row_number().over(order)).where("r = 1").select("cluster", "part_id")


@register("m4_lloyd_step", f"WITH {LINES}, {FEATS}, c AS (SELECT cluster, avg(x) AS cx, avg(y) AS cy FROM f GROUP BY 1), a AS (SELECT f.part_id, c.cluster FROM f, c QUALIFY row_number() OVER (PARTITION BY f.part_id ORDER BY round((x - cx) * (x - cx) + (y - cy) * (y - cy), 9), c.cluster) = 1) SELECT a.cluster, count(*) AS n, round(avg(x), 6) AS x, round(avg(y), 6) AS y FROM a JOIN f USING (part_id) GROUP BY a.cluster")
def m4_lloyd_step(spark: SparkSession, d: str) -> DataFrame:
    f = fixed_clusters(spark, d)
    c = f.groupBy(F.col("cluster").alias("c")).agg(F.avg("x").alias("cx"), F.avg("y").alias("cy"))
    far = F.round((F.col("x") - F.col("cx")) ** 2 + (F.col("y") - F.col("cy")) ** 2, 9)
    near = f.crossJoin(F.broadcast(c)).withColumn("r", F.row_number().over(Window.partitionBy("part_id").orderBy(far, "c"))).where("r = 1")
    return rounded(near.groupBy(F.col("c").alias("cluster")).agg(F.count(F.lit(1)).alias("n"), F.avg("x").alias("x"), F.avg("y").alias("y")), 6)


def _clustered(algo: str):
    @register(f"m4_{algo}")
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = fixed_clusters(spark, d).toPandas()
        found = clustering.cluster_sample(rows["part_id"].to_numpy(), rows[["x", "y"]].to_numpy(float), max(1, len(rows) // 10), algo)
        return spark.createDataFrame(found, "part_id int, weight double, cluster int")

    return run


for _a in ("kmeans", "hac_ward", "hac_single"):
    _clustered(_a)


@register("m4_cell_sample")
def m4_cell_sample(spark: SparkSession, d: str) -> DataFrame:
    ship_package(spark)
    f = fixed_clusters(spark, d).select("part_id", F.array("x", "y").alias("f"))
    return clustering.cell_sample(f, 10, 4)


def _picked(spark: SparkSession, d: str, **flags):
    p, queries, answers, sels, _ = experiments.trained(spark, d, "events", "user")
    n = max(1, len(p.parts) // 10)
    found = experiments.in_tasks(spark, (p.light(), queries, sels), len(queries), lambda x, i: picker.select_full(x[0].candidates(x[1][i], x[2][i]), n, x[0].models, **flags))
    return p, [(i, q, rows) for i, (q, rows) in enumerate(zip(queries, found, strict=True))], answers


@register("m4_select_full")
def m4_select_full(spark: SparkSession, d: str) -> DataFrame:
    """The proposed picker's weighted partitions for held-out queries."""
    _, picks, _ = _picked(spark, d)
    return spark.createDataFrame([(i, *r) for i, _, rows in picks for r in rows], "query int, " + picker.SELECTION)


@register("m4_answer_full")
def m4_answer_full(spark: SparkSession, d: str) -> DataFrame:
    """Weighted answer of one held-out query, executed on the chosen partitions only."""
    p, picks, _ = _picked(spark, d)
    _, q, rows = picks[0]
    return rounded(weighted_aggregate(p.scan(rows), q), 2)


@register("m4_train")
def m4_train(spark: SparkSession, d: str) -> DataFrame:
    p = experiments.trained(spark, d, "events", "user")[0]
    return spark.createDataFrame([(i, len(m.model), float(m.gain.sum())) for i, m in enumerate(p.models)], "model int, trees int, gain double")


@register("m4_feature_selection")
def m4_feature_selection(spark: SparkSession, d: str) -> DataFrame:
    p, *_, (queries, _, sels, answers) = experiments.trained(spark, d, "events", "user")
    kept, trace = select_features(p, queries[: len(answers)], answers, sels[: len(answers)])
    return spark.createDataFrame([(i, float(e), int(kept.sum())) for i, e in enumerate(trace)], "step int, error double, kept int")


@register("m4_fallback")
def m4_fallback(spark: SparkSession, d: str) -> DataFrame:
    """The rule itself: queries whose typical estimated selectivity is under a percent are sampled at random."""
    p, queries, _, sels, _ = experiments.trained(spark, d, "events", "user")
    _, picks, _ = _picked(spark, d)
    rare = [float(np.median(s[s[:, 0] > 0, 1])) if (s[:, 0] > 0).any() else 0.0 for s in sels]
    return spark.createDataFrame([(i, rare[i], role, sum(r[2] == role for r in rows)) for i, _, rows in picks for role in sorted({r[2] for r in rows})], "query int, typical_selectivity double, role string, reads int")


# Execution on a fixed selection: every tenth partition, weight ten.
def tenth(spark: SparkSession, d: str) -> DataFrame:
    return lines(spark, d).select("part_id").distinct().where("part_id % 10 = 3").withColumn("weight", F.lit(10.0))


Q_PLAIN = QuerySpec((Agg("sum", "l_quantity", "s"),), None, ("l_returnflag",))
WEIGHTED = {
    "m5_weighted_sum": Q_PLAIN,
    "m5_weighted_count": QuerySpec((Agg("count", "*", "n"),), Clause("l_quantity", ">", 30.0), ("l_linestatus",)),
    "m5_weighted_avg": QuerySpec((Agg("avg", "l_discount", "a"), Agg("avg", "l_tax", "b")), None, ("l_returnflag", "l_linestatus")),
    "m5_weighted_case": QuerySpec((Agg("sum", "l_extendedprice", "s", In("l_returnflag", ("A",))), Agg("count", "*", "n", Like("l_linestatus", "O%"))), Clause("l_discount", ">=", 0.02), ("l_linenumber",)),
    "m5_linear_projection": QuerySpec((Agg("sum", "l_quantity + 2 * l_linenumber", "s"), Agg("sum", "l_extendedprice * (1 - l_discount)", "r"))),
    "m5_derived_group": QuerySpec((Agg("sum", "l_quantity", "s"),), None, ("l_linenumber", "l_returnflag", "l_linestatus")),
}


def _weighted(name: str, q: QuerySpec):
    @register(name, f"WITH {LINES}, w AS (SELECT *, 10.0::DOUBLE AS weight FROM li WHERE part_id % 10 = 3) {answer_sql(q, 'w', 'weight')}")
    def run(spark: SparkSession, d: str) -> DataFrame:
        return rounded(weighted_aggregate(weighted_scan(lines(spark, d), tenth(spark, d)), q), 4)

    return run


for _n, _q in WEIGHTED.items():
    _weighted(_n, _q)


@register("m5_partials", f"WITH {LINES}, {P_SQL} SELECT part_id, l_returnflag, l_linestatus, round(s__s, 2) AS s__s, n__s FROM p")
def m5_partials(spark: SparkSession, d: str) -> DataFrame:
    return rounded(year_parts(spark, d), 2)


@register("m5_estimate", f"WITH {LINES}, w AS (SELECT *, 10.0::DOUBLE AS weight FROM li WHERE part_id % 10 = 3) {answer_sql(Q_YEAR, 'w', 'weight')}")
def m5_estimate(spark: SparkSession, d: str) -> DataFrame:
    return rounded(estimate(year_parts(spark, d), Q_YEAR, tenth(spark, d)), 4)


@register("m5_exact", f"WITH {LINES} {answer_sql(Q_YEAR, 'li')}")
def m5_exact(spark: SparkSession, d: str) -> DataFrame:
    return rounded(exact(lines(spark, d), Q_YEAR), 4)


@register("m5_star", f"WITH {LINES} SELECT p_type, round(sum(l_extendedprice * 10.0), 2) AS s FROM li JOIN part ON l_partkey = p_partkey WHERE part_id % 10 = 3 GROUP BY p_type")
def m5_star(spark: SparkSession, d: str) -> DataFrame:
    fact = weighted_scan(lines(spark, d), tenth(spark, d))
    joined = fact.join(read_table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return rounded(weighted_aggregate(joined, QuerySpec((Agg("sum", "l_extendedprice", "s"),), None, ("p_type",))), 2)


@register("m5_nested", f"WITH {LINES}, i AS (SELECT l_returnflag, part_id, sum(l_quantity) AS q FROM li GROUP BY 1, 2) SELECT l_returnflag, round(sum(q), 2) AS s FROM i WHERE q > 100 GROUP BY 1")
def m5_nested(spark: SparkSession, d: str) -> DataFrame:
    inner = lines(spark, d).groupBy("l_returnflag", "part_id").agg(F.sum("l_quantity").alias("q"))
    return rounded(exact(inner, QuerySpec((Agg("sum", "q", "s"),), Clause("q", ">", 100.0), ("l_returnflag",))), 2)


@register("m5_sql_front", f"WITH {LINES} SELECT l_returnflag, round(sum(l_quantity), 2) AS s, CAST(count(*) AS DOUBLE) AS n FROM li WHERE (l_discount BETWEEN 0.02 AND 0.06 OR l_linestatus IN ('O')) AND NOT l_quantity > 40 GROUP BY l_returnflag")
def m5_sql_front(spark: SparkSession, d: str) -> DataFrame:
    _, q = parse_sql("SELECT l_returnflag, sum(l_quantity) AS s, count(*) AS n FROM li WHERE (l_discount BETWEEN 0.02 AND 0.06 OR l_linestatus IN ('O')) AND NOT l_quantity > 40 GROUP BY l_returnflag")
    return rounded(exact(lines(spark, d), q), 2)


@register("m5_validate", "SELECT unnest(['max', 'many groups', 'many pairs', 'fine']) AS case_name, unnest([1, CAST(least(o, n) > 10000 AS INTEGER), CAST(least(o * p, n) > 10000 AS INTEGER), 0]) AS problems FROM (SELECT count(DISTINCT l_orderkey) AS o, count(DISTINCT l_partkey) AS p, count(*) AS n FROM lineitem)")
def m5_validate(spark: SparkSession, d: str) -> DataFrame:
    """Queries outside the scope, by the table's own distinct values and rows."""
    cols = ("l_orderkey", "l_partkey", "l_returnflag")
    held = read_table(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("rows"), *[F.countDistinct(c).alias(c) for c in cols]).first().asDict()
    total = Agg("sum", "l_tax", "s")
    cases = {"max": QuerySpec((Agg("max", "l_tax", "m"),)), "many groups": QuerySpec((total,), None, ("l_orderkey",)), "many pairs": QuerySpec((total,), None, ("l_orderkey", "l_partkey")), "fine": Q_PLAIN}
    return spark.createDataFrame([(k, len(validate(q, {c: held[c] for c in cols}, held["rows"]))) for k, q in cases.items()], "case_name string, problems int")


# Baselines
B_N = "(SELECT count(DISTINCT part_id) FROM li)"


def parts_frame(spark: SparkSession, d: str) -> DataFrame:
    return lines(spark, d).select("part_id").distinct()


@register("b1_uniform", f"WITH {LINES} SELECT part_id, round({B_N} / 10.0::DOUBLE, 6) AS weight FROM (SELECT DISTINCT part_id FROM li) ORDER BY (part_id * 7919 + 104729) % 10007, part_id LIMIT 10")
def b1_uniform(spark: SparkSession, d: str) -> DataFrame:
    return rounded(baselines.select_uniform(parts_frame(spark, d), 10, 1), 6)


@register("b2_filtered", f"WITH {LINES}, k AS (SELECT DISTINCT part_id FROM li WHERE ship_day >= 1096 AND ship_day < 1461) SELECT part_id, round((SELECT count(*) FROM k) / 5.0::DOUBLE, 6) AS weight FROM k ORDER BY (part_id * 7919 + 104729) % 10007, part_id LIMIT 5")
def b2_filtered(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.plans.registry_stats import _YEAR, stats
    from coarsesample.operators.selectivity import filter_by_predicate, with_selectivity

    return rounded(baselines.select_uniform(filter_by_predicate(with_selectivity(stats(spark, d), _YEAR)).select("part_id"), 5, 1), 6)


@register("b3_strata_fixed_scores", f"WITH {LINES}, {SCORES}, s AS (SELECT part_id, ntile(5) OVER (ORDER BY round(a, 9), part_id) AS stratum FROM scores), z AS (SELECT *, count(*) OVER (PARTITION BY stratum) AS size, count(*) OVER () AS everything, row_number() OVER (PARTITION BY stratum ORDER BY (part_id * 7919 + 2 * 104729) % 10007, part_id) AS pos FROM s), r AS (SELECT *, least(size, greatest(1, CAST(floor(size * 12 / everything) AS INTEGER))) AS reads FROM z) SELECT part_id, round(size / reads, 6) AS weight, CAST(stratum AS INTEGER) AS stratum FROM r WHERE pos <= reads")
def b3_strata_fixed_scores(spark: SparkSession, d: str) -> DataFrame:
    scored = lines(spark, d).groupBy("part_id").agg(F.round(F.avg("l_quantity") - 25.4, 9).alias("score"))
    return rounded(baselines.select_strata(scored, 12, 5, 2), 6)


@register("b3_strata_model")
def b3_strata_model(spark: SparkSession, d: str) -> DataFrame:
    p, queries, _, sels, _ = experiments.trained(spark, d, "events", "user")
    return spark.createDataFrame([(i, *r) for i, (q, s) in enumerate(zip(queries, sels, strict=True)) for r in experiments.pick(p, "strata", q, s, max(1, len(p.parts) // 10), 0)], "query int, part_id int, weight double")


ROWS = "(l_orderkey * 8 + l_linenumber)"


@register("b4_row_sample", f"SELECT l_returnflag, count(*) AS n FROM lineitem WHERE ({ROWS} * 7919 + 13) % 1000 < 10 GROUP BY 1")
def b4_row_sample(spark: SparkSession, d: str) -> DataFrame:
    return baselines.sample_rows(read_table(spark, d, "lineitem"), F.col("l_orderkey") * 8 + F.col("l_linenumber"), 10).groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@register("b4_blocks_touched", f"WITH {LINES} SELECT round(count(DISTINCT CASE WHEN ({ROWS} * 7919 + 13) % 1000 < 10 THEN part_id END) / count(DISTINCT part_id)::DOUBLE, 6) AS touched FROM li")
def b4_blocks_touched(spark: SparkSession, d: str) -> DataFrame:
    df = lines(spark, d)
    hit = baselines.sample_rows(df, F.col("l_orderkey") * 8 + F.col("l_linenumber"), 10)
    return rounded(hit.agg(F.countDistinct("part_id").alias("a")).crossJoin(df.agg(F.countDistinct("part_id").alias("b"))).select((F.col("a") / F.col("b")).alias("touched")), 6)


@register("b5_full_scan", f"WITH {LINES} {answer_sql(Q_PLAIN, 'li')}")
def b5_full_scan(spark: SparkSession, d: str) -> DataFrame:
    return rounded(exact(lines(spark, d), Q_PLAIN), 4)


@register("b6_ten_runs", f"WITH {LINES}, p AS (SELECT part_id, sum(l_quantity) AS x FROM li GROUP BY 1), r AS (SELECT seed, part_id, x, row_number() OVER (PARTITION BY seed ORDER BY (part_id * 7919 + seed * 104729) % 10007, part_id) AS pos, count(*) OVER (PARTITION BY seed) AS n FROM p, range(10) t(seed)) SELECT seed, round(sum(x) * max(n) / 10.0::DOUBLE, 2) AS estimate FROM r WHERE pos <= 10 GROUP BY seed")
def b6_ten_runs(spark: SparkSession, d: str) -> DataFrame:
    p = lines(spark, d).groupBy("part_id").agg(F.sum("l_quantity").alias("x"))
    seeds = spark.range(10).select(F.col("id").alias("seed"))
    own = Window.partitionBy("seed")
    order = own.orderBy(F.pmod(F.col("part_id") * 7919 + F.col("seed") * 104729, F.lit(10007)), "part_id")
    r = p.crossJoin(F.broadcast(seeds)).withColumn("at", F.row_number().over(order)).withColumn("n", F.count(F.lit(1)).over(own))
    return rounded(r.where("at <= 10").groupBy("seed").agg((F.sum("x") * F.max("n") / 10).alias("estimate")), 2)


# Measures
T_SQL = "t AS (SELECT z, sum(x) AS s, CAST(count(*) AS DOUBLE) AS n FROM v GROUP BY z), e AS (SELECT z, sum(x) * 10 AS s, CAST(count(*) AS DOUBLE) * 10 AS n FROM v WHERE k % 10 = 3 AND z % 7 <> 5 GROUP BY z)"
V_SQL = "v AS (SELECT CAST(floor(exp(ln(26.0::DOUBLE) * ((l_partkey) % 997) / 997.0::DOUBLE)) AS INTEGER) AS z, l_orderkey AS k, l_quantity AS x FROM lineitem)"
REL = "SELECT t.z, t.s, t.n, e.s AS es, e.n AS en FROM t LEFT JOIN e USING (z)"


def true_and_guess(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    from coarsesample.functions.portable import zipf_like

    v = read_table(spark, d, "lineitem").select(zipf_like(F.col("l_partkey")).alias("z"), F.col("l_orderkey").alias("k"), F.col("l_quantity").alias("x"))
    agg = lambda df, w: df.groupBy("z").agg((F.sum("x") * w).alias("s"), (F.count(F.lit(1)).cast("double") * w).alias("n"))
    return agg(v, 1), agg(v.where("k % 10 = 3 and z % 7 <> 5"), 10)


@register("c1_missed_groups", f"WITH {V_SQL}, {T_SQL} SELECT round(avg(CASE WHEN es IS NULL THEN 1.0 ELSE 0 END), 6) AS missed FROM ({REL})")
def c1_missed_groups(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.missed_groups(*true_and_guess(spark, d), ["z"]), 6)


@register("c2_avg_rel_error", f"WITH {V_SQL}, {T_SQL} SELECT round(avg((coalesce(abs(es - s) / s, 1) + coalesce(abs(en - n) / n, 1)) / 2), 6) AS rel_error FROM ({REL})")
def c2_avg_rel_error(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.avg_rel_error(*true_and_guess(spark, d), ["z"], ["s", "n"]), 6)


@register("c3_abs_over_true", f"WITH {V_SQL}, {T_SQL} SELECT round((avg(abs(coalesce(es, 0) - s)) / avg(s) + avg(abs(coalesce(en, 0) - n)) / avg(n)) / 2, 6) AS abs_over_true FROM ({REL})")
def c3_abs_over_true(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.abs_error_over_true(*true_and_guess(spark, d), ["z"], ["s", "n"]), 6)


# Curves with known shapes, one point per order priority and tenth of a key.
CURVE = "curve AS (SELECT o_orderpriority AS method, CAST((o_orderkey % 10 + 1) AS DOUBLE) / 10 AS budget, round(avg(o_totalprice), 4) / (o_orderkey % 10 + 1) AS error FROM orders GROUP BY o_orderpriority, o_orderkey % 10)"


def curve(spark: SparkSession, d: str) -> DataFrame:
    at = F.col("o_orderkey") % 10
    return read_table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("method"), at.alias("t")).agg(F.round(F.avg("o_totalprice"), 4).alias("a")).select("method", ((F.col("t") + 1).cast("double") / 10).alias("budget"), (F.col("a") / (F.col("t") + 1)).alias("error"))


@register("c4_auc", f"WITH {CURVE}, l AS (SELECT *, lag(budget) OVER w AS b0, lag(error) OVER w AS e0 FROM curve WINDOW w AS (PARTITION BY method ORDER BY budget)) SELECT method, round(sum((budget - b0) * (error + e0) / 2), 4) AS auc FROM l GROUP BY method")
def c4_auc(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.auc(curve(spark, d), ["method"]))


BUDGET = "l AS (SELECT *, lag(budget) OVER w AS b0, lag(error) OVER w AS e0 FROM curve WINDOW w AS (PARTITION BY method ORDER BY budget)), need AS (SELECT method, min(CASE WHEN e0 IS NULL OR e0 <= 50000 THEN budget ELSE b0 + (e0 - 50000) / (e0 - error) * (budget - b0) END) AS budget FROM l WHERE error <= 50000 GROUP BY method)"


@register("c5_budget_for_error", f"WITH {CURVE}, {BUDGET} SELECT method, round(budget, 6) AS budget FROM need")
def c5_budget_for_error(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.budget_for_error(curve(spark, d), ["method"], 50000.0), 6)


@register("c5_reduction", f"WITH {CURVE}, {BUDGET} SELECT round((SELECT budget FROM need WHERE method = '5-LOW') / (SELECT budget FROM need WHERE method = '1-URGENT'), 6) AS reduction")
def c5_reduction(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.reduction(curve(spark, d), "1-URGENT", "5-LOW", 50000.0), 6)


@register("c6_error_ratio", f"WITH {CURVE} SELECT method, round(error / (SELECT error FROM curve WHERE method = '1-URGENT' AND abs(budget - 0.3) < 1e-9), 6) AS ratio FROM curve WHERE abs(budget - 0.3) < 1e-9")
def c6_error_ratio(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.error_ratio(curve(spark, d), "1-URGENT", 0.3), 6)


@register("c7_read_fraction", f"WITH {LINES} SELECT round(count(DISTINCT CASE WHEN part_id % 10 = 3 THEN part_id END) / count(DISTINCT part_id)::DOUBLE, 6) AS parts_read, round(sum(CASE WHEN part_id % 10 = 3 THEN 1.0 ELSE 0 END) / count(*), 6) AS rows_read FROM li")
def c7_read_fraction(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.read_fraction(lines(spark, d).groupBy("part_id").agg(F.count(F.lit(1)).alias("n_rows")), tenth(spark, d)), 6)


@register("c8_storage")
def c8_storage(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for name, layout in experiments.VIEWS:
        p = experiments.trained(spark, d, name, layout)[0]
        num, text = list(p.w.cfg.numeric), list(p.w.cfg.strings)
        vn, vs = S.value_counts(p.df, num, "double"), S.value_counts(p.df, text, "string")
        kv = S.kmv(vn).unionByName(S.kmv(vs))
        hist = S.histogram(vn).drop("lo", "hi").unionByName(S.histogram(S.hashed(vs)).drop("lo", "hi"))
        hh = S.heavy_hitters(vn).select("part_id", F.col("value").cast("string").alias("value")).unionByName(S.heavy_hitters(vs).select("part_id", "value"))
        per_part = bytes_under(spark, p.path) / max(1, len(p.parts))
        rows.append(S.sketch_bytes(S.measures(p.df, num), hist, kv, hh).withColumn("view", F.lit(name)).withColumn("share_of_part", F.col("bytes_per_part") / per_part))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return rounded(out)


@register("c9_picker_times")
def c9_picker_times(spark: SparkSession, d: str) -> DataFrame:
    return experiments.picker_times(spark, d)


@register("c10_speedup")
def c10_speedup(spark: SparkSession, d: str) -> DataFrame:
    return experiments.speedups(spark, d)


@register("c11_filter_quality", f"WITH {LINES}, k AS (SELECT DISTINCT part_id FROM li WHERE ship_day >= 1096 AND ship_day < 1461 AND l_quantity > 49.5), s AS (SELECT part_id FROM li GROUP BY part_id HAVING max(ship_day) >= 1096 AND min(ship_day) < 1461 AND max(l_quantity) > 49.5) SELECT round((SELECT count(*) FROM k) / (SELECT count(*) FROM s)::DOUBLE, 6) AS filter_precision, CAST(1 AS DOUBLE) AS filter_recall")
def c11_filter_quality(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.operators.selectivity import with_selectivity
    from coarsesample.plans.registry_stats import stats

    p = And((Clause("ship_day", ">=", 1096.0), Clause("ship_day", "<", 1461.0), Clause("l_quantity", ">", 49.5)))
    hits = lines(spark, d).where("ship_day >= 1096 and ship_day < 1461 and l_quantity > 49.5").select("part_id").distinct()
    return rounded(metrics.filter_quality(with_selectivity(stats(spark, d), p), hits), 6)


@register("c12_importance")
def c12_importance(spark: SparkSession, d: str) -> DataFrame:
    return experiments.feature_kinds(spark, d)


@register("c13_spread", "SELECT o_orderpriority AS template, round(avg(o_totalprice), 4) AS mean_error, round(min(o_totalprice), 4) AS best, round(max(o_totalprice), 4) AS worst FROM orders GROUP BY 1")
def c13_spread(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.spread(read_table(spark, d, "orders").select(F.col("o_orderpriority").alias("template"), F.col("o_totalprice").alias("error"))))


@register("c14_error_by_band", "SELECT CASE WHEN s < 0.2 THEN 'low' WHEN s <= 0.8 THEN 'mid' ELSE 'high' END AS band, round(avg(o_totalprice), 4) AS error, count(*) AS queries FROM (SELECT (o_orderkey % 100) / 100.0::DOUBLE AS s, o_totalprice FROM orders) GROUP BY 1")
def c14_error_by_band(spark: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.error_by_band(read_table(spark, d, "orders").select(((F.col("o_orderkey") % 100) / 100).alias("selectivity"), F.col("o_totalprice").alias("error"))))


@register("c15_blocks_closed_form", "SELECT round(avg(1 - power(0.99::DOUBLE, n)), 6) AS touched FROM (SELECT l_orderkey // 25 AS block, count(*) AS n FROM lineitem GROUP BY 1)")
def c15_blocks_closed_form(spark: SparkSession, d: str) -> DataFrame:
    """Expected share of blocks of 25 orders' lines, about 100 rows, that a one percent row sample reads."""
    blocks = read_table(spark, d, "lineitem").groupBy(F.floor(F.col("l_orderkey") / 25)).agg(F.count(F.lit(1)).alias("n"))
    return rounded(blocks.agg(F.avg(baselines.blocks_touched(0.01, F.col("n"))).alias("touched")), 6)


@register("c16_bias_variance", f"WITH {LINES}, f AS (SELECT part_id, part_id % 5 AS cluster, avg(l_quantity) AS x FROM li GROUP BY 1, 2), c AS (SELECT cluster, count(*) AS s, avg(x) AS m, sum(x * x) AS q FROM f GROUP BY 1) SELECT round(sum(s * m), 4) AS expected, round(sum(s * (q - s * m * m)), 2) AS variance FROM c")
def c16_bias_variance(spark: SparkSession, d: str) -> DataFrame:
    return metrics.bias_variance(fixed_clusters(spark, d)).select(F.round("expected", 4).alias("expected"), F.round("variance", 2).alias("variance"))


@register("c16_drawn", f"WITH {LINES}, f AS (SELECT part_id, part_id % 5 AS cluster, avg(l_quantity) AS x FROM li GROUP BY 1, 2), s AS (SELECT cluster, count(*) AS size FROM f GROUP BY 1), r AS (SELECT seed, size * x AS e, row_number() OVER (PARTITION BY seed, cluster ORDER BY (part_id * 7919 + seed * 104729) % 10007, part_id) AS pos FROM f JOIN s USING (cluster), range(200) t(seed)), e AS (SELECT seed, sum(e) AS e FROM r WHERE pos = 1 GROUP BY seed) SELECT round(avg(e), 4) AS mean, round(stddev_pop(e), 4) AS deviation, count(*) AS draws FROM e")
def c16_drawn(spark: SparkSession, d: str) -> DataFrame:
    """Mean and deviation of the total over 200 drawings of random exemplars, beside the closed forms of c16_bias_variance."""
    f = fixed_clusters(spark, d).select("part_id", "cluster", "x")
    sized = f.join(F.broadcast(f.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))), "cluster")
    seeds = spark.range(200).select(F.col("id").alias("seed"))
    order = Window.partitionBy("seed", "cluster").orderBy(F.pmod(F.col("part_id") * 7919 + F.col("seed") * 104729, F.lit(10007)), "part_id")
    drawn = sized.crossJoin(F.broadcast(seeds)).withColumn("at", F.row_number().over(order)).where("at = 1")
    each = drawn.groupBy("seed").agg(F.sum(F.col("size") * F.col("x")).alias("e"))
    return rounded(each.agg(F.avg("e").alias("mean"), F.stddev_pop("e").alias("deviation"), F.count(F.lit(1)).alias("draws")))


# Row-level answers on the wide view serve W5's exact side.
def wide_exact(name: str, q: QuerySpec):
    @register(f"w5_{name}", f"WITH {WIDE} {answer_sql(q, 'wide')}")
    def run(spark: SparkSession, d: str) -> DataFrame:
        return rounded(exact(tables.lineitem_wide(spark, d), q), 4)

    return run


