"""Queries on workloads, experiments and ablations (families w and v)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.plans import experiments, workload
from coarsesample.plans.query import Agg, Clause, QuerySpec, estimate, exact, partials, to_sql
from coarsesample.plans.registry import LINES, WIDE, answer_sql, lines, register, rounded
from coarsesample.plans.registry_pick import wide_exact
from coarsesample.plans.training import constants_of
from coarsesample.runtime import read_table
from coarsesample.sources import tables

for _name, _q in workload.templates().items():
    wide_exact(_name, _q)


@register("w1_lineitem_wide", f"WITH {WIDE} SELECT z_part, z_supp, z_cust, count(*) AS n, round(sum(revenue), 4) AS revenue, min(ship_day) AS first_day, max(order_year) AS last_year FROM wide GROUP BY 1, 2, 3")
def w1_lineitem_wide(spark: SparkSession, d: str) -> DataFrame:
    return tables.lineitem_wide(spark, d).groupBy("z_part", "z_supp", "z_cust").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("revenue"), 4).alias("revenue"), F.min("ship_day").alias("first_day"), F.max("order_year").alias("last_year"))


@register("w2_orders_wide", "SELECT r_name, CAST(year(o_orderdate) AS INTEGER) AS o_year, CAST(month(o_orderdate) AS INTEGER) AS o_month, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2, 3")
def w2_orders_wide(spark: SparkSession, d: str) -> DataFrame:
    return tables.orders_wide(spark, d).groupBy("r_name", "o_year", "o_month").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@register("w3_events_flat", "SELECT CAST(floor(exp(ln(26.0::DOUBLE) * ((user_id * 7) % 997) / 997.0::DOUBLE)) AS INTEGER) AS z_user, CAST(hour(ts) AS INTEGER) AS hour, count(*) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS INTEGER)) AS BIGINT) AS k FROM events GROUP BY 1, 2")
def w3_events_flat(spark: SparkSession, d: str) -> DataFrame:
    return tables.events_flat(spark, d).groupBy("z_user", "hour").agg(F.count(F.lit(1)).alias("n"), F.sum("k").alias("k"))


@register("w4_documents_flat", "SELECT lang, quality, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, CAST(sum(len(string_split(text, chr(10)))) AS BIGINT) AS lines, CAST(sum(len(regexp_extract_all(text, '[0-9]'))) AS BIGINT) AS digits, CAST(sum(len(regexp_extract_all(text, '[A-Z]'))) AS BIGINT) AS upper FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2")
def w4_documents_flat(spark: SparkSession, d: str) -> DataFrame:
    return tables.documents_flat(spark, d).groupBy("lang", "quality").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.sum("n_lines").alias("lines"), F.sum("n_digits").alias("digits"), F.sum("n_upper").alias("upper"))


@register("w4_embeddings_wide", "SELECT CAST(label AS VARCHAR) AS label, count(*) AS n, round(avg(embedding[1]::DOUBLE), 6) AS e0, round(avg(embedding[64]::DOUBLE), 6) AS e63 FROM embeddings GROUP BY 1")
def w4_embeddings_wide(spark: SparkSession, d: str) -> DataFrame:
    return rounded(tables.embeddings_wide(spark, d).groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.avg("e0").alias("e0"), F.avg("e63").alias("e63")), 6)


@register("w5_unseen_templates")
def w5_unseen_templates(spark: SparkSession, d: str) -> DataFrame:
    return experiments.unseen(spark, d)


@register("w5_weighted_q01", f"WITH {WIDE}, w AS (SELECT *, 5.0::DOUBLE AS weight FROM wide WHERE floor((ship_day - 9131) / 25.0) % 5 = 2) {answer_sql(workload.templates()['q01'], 'w', 'weight')}")
def w5_weighted_q01(spark: SparkSession, d: str) -> DataFrame:
    q = workload.templates()["q01"]
    df = tables.lineitem_wide(spark, d).withColumn("part_id", F.floor((F.col("ship_day") - 9131) / 25).cast("int"))
    chosen = df.select("part_id").distinct().where("part_id % 5 = 2").withColumn("weight", F.lit(5.0))
    return rounded(estimate(partials(df, q), q, chosen), 4)


@register("w6_generator")
def w6_generator(spark: SparkSession, d: str) -> DataFrame:
    p, test, *_, train = experiments.trained(spark, d, "events", "user")
    fresh = workload.generate(p.w, constants_of(p), 20, seed=5)
    rows = [(kind, i, to_sql(q.where), ",".join(q.group_by), ",".join(a.alias for a in q.aggs)) for kind, qs in (("train", train[0]), ("test", test), ("fresh", fresh)) for i, q in enumerate(qs)]
    return spark.createDataFrame(rows, "kind string, query int, predicate string, group_by string, aggregates string")


def _sweep(view: str, layout: str, key: str):
    @register(key)
    def run(spark: SparkSession, d: str) -> DataFrame:
        return experiments.sweep(spark, d, view, layout)

    return run


for _key, _view, _layout in (
    ("w7_sweep_lineitem", "lineitem", "shipdate"),
    ("w7_sweep_orders", "orders", "day"),
    ("w7_sweep_events", "events", "user"),
    ("w7_sweep_documents", "documents", "n_chars"),
    ("w7_sweep_embeddings", "embeddings", "e0"),
    ("w8_layout_lineitem_price", "lineitem", "price"),
    ("w8_layout_lineitem_z_part", "lineitem", "z_part"),
    ("w8_layout_orders_priority", "orders", "priority"),
    ("w8_layout_orders_totalprice", "orders", "totalprice"),
    ("w8_layout_events_ts", "events", "ts"),
    ("w8_layout_events_value", "events", "value"),
    ("w8_layout_documents_lang", "documents", "lang"),
    ("w8_layout_embeddings_label", "embeddings", "label"),
    ("w9_random_layout", "lineitem", "random"),
):
    _sweep(_view, _layout, _key)


def _curve(spark: SparkSession, d: str) -> DataFrame:
    """The main sweeps of the two views whose columns are skewed or selective, as a curve per view and method."""
    both = experiments.sweep(spark, d, "events", "user").unionByName(experiments.sweep(spark, d, "orders", "day"))
    return both.select("view", "method", "budget", F.col("rel_error").alias("error"))


@register("w7_auc")
def w7_auc(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.operators.metrics import auc

    return auc(_curve(spark, d), ["view", "method"])


@register("w7_error_ratio")
def w7_error_ratio(spark: SparkSession, d: str) -> DataFrame:
    """Every method's error over the full method's at 1, 5 and 10 percent read."""
    from coarsesample.operators.metrics import error_ratio

    out = None
    for view in ("events", "orders"):
        for b in (0.01, 0.05, 0.1):
            part = error_ratio(_curve(spark, d).where(F.col("view") == view), "full", b).select(F.lit(view).alias("view"), F.lit(b).alias("budget"), "method", "ratio")
            out = part if out is None else out.unionByName(part)
    return out


@register("w7_reduction")
def w7_reduction(spark: SparkSession, d: str) -> DataFrame:
    """How many times less the full method reads than another for the error it has at a tenth."""
    from coarsesample.operators.metrics import reduction

    out = None
    for view in ("events", "orders"):
        curve = _curve(spark, d).where(F.col("view") == view)
        target = curve.where("method = 'full' and abs(budget - 0.1) < 1e-9").first()["error"]
        for against in ("uniform", "filtered", "strata"):
            part = reduction(curve, "full", against, target).select(F.lit(view).alias("view"), F.lit(against).alias("against"), F.lit(target).alias("error"), "reduction")
            out = part if out is None else out.unionByName(part)
    return out


@register("w10_partition_count")
def w10_partition_count(spark: SparkSession, d: str) -> DataFrame:
    few = experiments.n_parts_of(spark, d, "lineitem") // 10
    both = [experiments.sweep(spark, d, "lineitem", "shipdate", ("uniform", "filtered", "full"), n) for n in (few, 10 * few)]
    return both[0].unionByName(both[1])


@register("w11_selectivity_bands")
def w11_selectivity_bands(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.operators.metrics import error_by_band

    rows = experiments.bands(spark, d)
    out = None
    for m in ("uniform", "filtered", "full"):
        part = error_by_band(rows.where(F.col("method") == m)).withColumn("method", F.lit(m))
        out = part if out is None else out.unionByName(part)
    return out


@register("w12_lesion_and_factor")
def w12_lesion_and_factor(spark: SparkSession, d: str) -> DataFrame:
    return experiments.lesion(spark, d)


@register("w13_clusterers")
def w13_clusterers(spark: SparkSession, d: str) -> DataFrame:
    return experiments.clusterers(spark, d)


Q_EVENTS = QuerySpec((Agg("sum", "value", "s"),), Clause("k", ">", 50.0), ("event_type",))
EVENTS = "ev AS (SELECT *, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events)"


@register("w16_illustration", f"WITH {EVENTS} {answer_sql(Q_EVENTS, 'ev')}")
def w16_illustration(spark: SparkSession, d: str) -> DataFrame:
    return rounded(exact(tables.events_flat(spark, d), Q_EVENTS), 4)


@register("w16_dominant_share", "SELECT round(max(n) / sum(n)::DOUBLE, 6) AS share, count(*) AS kinds FROM (SELECT CAST(floor(exp(ln(26.0::DOUBLE) * ((l_partkey) % 997) / 997.0::DOUBLE)) AS INTEGER) AS z, count(*) AS n FROM lineitem GROUP BY 1)")
def w16_dominant_share(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.functions.portable import zipf_like

    by = read_table(spark, d, "lineitem").groupBy(zipf_like(F.col("l_partkey")).alias("z")).agg(F.count(F.lit(1)).alias("n"))
    return rounded(by.agg((F.max("n") / F.sum("n")).alias("share"), F.count(F.lit(1)).alias("kinds")), 6)


@register("w17_pages", "SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*) AS n, CAST(sum(length(html)) AS BIGINT) AS chars FROM pages GROUP BY 1")
def w17_pages(spark: SparkSession, d: str) -> DataFrame:
    return tables.pages_flat(spark, d).groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@register("w17_conversations", "SELECT role, count(*) AS n, CAST(sum(length(text)) AS BIGINT) AS chars, max(turn) AS last_turn FROM conversations GROUP BY 1")
def w17_conversations(spark: SparkSession, d: str) -> DataFrame:
    return tables.conversations_flat(spark, d).groupBy("role").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.max("turn").alias("last_turn"))


@register("w17_benchmark", "SELECT count(*) AS n, CAST(sum(length(text)) AS BIGINT) AS chars FROM benchmark")
def w17_benchmark(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "benchmark").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).cast("long").alias("chars"))


def _lesion_of(key: str, method: str):
    @register(key)
    def run(spark: SparkSession, d: str) -> DataFrame:
        return experiments.lesion(spark, d, ("full", method))

    return run


for _key, _method in (("v1_no_clusters", "no_clusters"), ("v2_no_outliers", "no_outliers"), ("v3_no_models", "no_models"), ("v4_filter_only", "filter"), ("v4_filter_outliers", "filter_outliers"), ("v4_filter_clusters", "filter_clusters"), ("v4_filter_models", "filter_models"), ("v4_random", "random")):
    _lesion_of(_key, _method)


@register("v5_knobs")
def v5_knobs(spark: SparkSession, d: str) -> DataFrame:
    return experiments.knobs(spark, d).where("knob <> 'exemplar'")


@register("v5_model_counts")
def v5_model_counts(spark: SparkSession, d: str) -> DataFrame:
    return experiments.model_counts(spark, d)


@register("v6_feature_ablation")
def v6_feature_ablation(spark: SparkSession, d: str) -> DataFrame:
    return experiments.feature_ablation(spark, d)


@register("v7_clusterer_swap")
def v7_clusterer_swap(spark: SparkSession, d: str) -> DataFrame:
    return experiments.clusterers(spark, d, (("events", "user"),))


@register("v8_exemplar")
def v8_exemplar(spark: SparkSession, d: str) -> DataFrame:
    return experiments.knobs(spark, d).where("knob = 'exemplar'")


V9 = " UNION ALL ".join(f"SELECT {b} AS buckets, round(avg(abs(est - truth)), 6) AS error FROM (SELECT part_id, sum(CASE WHEN hi < 17.5 THEN n_rows WHEN lo < 17.5 THEN CASE WHEN hi = lo THEN n_rows ELSE n_rows * (least(hi, 17.5) - lo) / (hi - lo) END ELSE 0 END) / sum(n_rows) AS est FROM h{b} GROUP BY 1) JOIN t USING (part_id)" for b in (5, 10, 20))


def _v9_sql() -> str:
    from coarsesample.plans.registry import counts_sql, histogram_sql

    hists = ", ".join(f"h{b} AS ({histogram_sql('vc', b)})" for b in (5, 10, 20))
    return f"WITH {LINES}, vc AS ({counts_sql(['l_quantity'], 'DOUBLE')}), {hists}, t AS (SELECT part_id, sum(CASE WHEN l_quantity < 17.5 THEN 1.0 ELSE 0 END) / count(*) AS truth FROM li GROUP BY 1) {V9}"


@register("v9_bucket_counts", _v9_sql())
def v9_bucket_counts(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.operators import sketches as S
    from coarsesample.operators.selectivity import bounds
    from coarsesample.plans.query import normalize

    df = lines(spark, d)
    truth = df.groupBy("part_id").agg(F.avg(F.when(F.col("l_quantity") < 17.5, 1.0).otherwise(0.0)).alias("truth"), F.count(F.lit(1)).alias("n_rows"), F.min("l_quantity").alias("l_quantity__min"), F.max("l_quantity").alias("l_quantity__max"))
    vc, out = S.value_counts(df, ["l_quantity"], "double"), None
    guess = bounds(normalize(Clause("l_quantity", "<", 17.5)))[1]
    for b in (5, 10, 20):
        hist = S.histogram(vc, b).groupBy("part_id").agg(F.sort_array(F.collect_list(F.struct("lo", "hi", "n_rows", "ndv"))).alias("l_quantity__hist"))
        one = truth.join(hist, "part_id").select(F.lit(b).alias("buckets"), F.abs(guess - F.col("truth")).alias("e")).groupBy("buckets").agg(F.avg("e").alias("error"))
        out = one if out is None else out.unionByName(one)
    return rounded(out, 6)


def _kmv_sizes_sql() -> str:
    from coarsesample.functions.portable import HASH_SPACE
    from coarsesample.plans.registry import HASH, counts_sql
    from coarsesample.plans.registry_stats import KEYS

    truth = " UNION ALL ".join(f"SELECT part_id, '{c}' AS col_name, count(DISTINCT {c}) AS truth FROM li GROUP BY part_id" for c in KEYS)
    return f"""WITH {LINES}, h AS (SELECT DISTINCT part_id, col_name, {HASH.format('value')} AS hash FROM ({counts_sql(KEYS, 'VARCHAR')})), r AS (SELECT *, row_number() OVER (PARTITION BY part_id, col_name ORDER BY hash) AS place FROM h), t AS ({truth}),
 e AS (SELECT k, part_id, col_name, count(*) AS kept, CASE WHEN count(*) < k THEN CAST(count(*) AS DOUBLE) ELSE (k - 1) * {HASH_SPACE} / max(hash) END AS ndv FROM r, (VALUES (32), (64), (128), (256)) s(k) WHERE place <= k GROUP BY 1, 2, 3)
 SELECT k, round(avg(abs(ndv - truth) / truth), 6) AS error, round(avg(kept), 6) AS kept FROM e JOIN t USING (part_id, col_name) GROUP BY k"""


@register("v9_kmv_sizes", _kmv_sizes_sql())
def v9_kmv_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Error of the distinct estimates by the sketch's size."""
    from coarsesample.operators import sketches as S
    from coarsesample.plans.registry_stats import KEYS
    from coarsesample.runtime import materialize

    df, out = lines(spark, d), None
    each = F.inline(F.array(*[F.struct(F.lit(c).alias("col_name"), F.col(c).alias("truth")) for c in KEYS]))
    truth = df.groupBy("part_id").agg(*[F.countDistinct(c).alias(c) for c in KEYS]).select("part_id", each)
    largest = materialize(S.kmv(S.value_counts(df, KEYS, "string"), 256), "kmv")
    for k in (32, 64, 128, 256):
        sketch = S.kmv_shrink(largest, k)
        kept = sketch.groupBy("part_id", "col_name").agg(F.count(F.lit(1)).alias("kept"))
        each = S.kmv_features(sketch, k).join(kept, ["part_id", "col_name"]).join(truth, ["part_id", "col_name"])
        one = each.agg(F.lit(k).alias("k"), F.avg(F.abs(F.col("ndv") - F.col("truth")) / F.col("truth")).alias("error"), F.avg("kept").alias("kept"))
        out = one if out is None else out.unionByName(one)
    return rounded(out, 6)


SUPPORTS = (0.005, 0.01, 0.02, 0.05)


def _supports_sql() -> str:
    from coarsesample.plans.registry import counts_sql

    return f"""WITH {LINES}, vc AS (SELECT *, CAST(sum(n) OVER (PARTITION BY part_id, col_name) AS DOUBLE) AS whole FROM ({counts_sql(['l_quantity', 'l_linenumber'], 'DOUBLE')})), a AS (SELECT col_name, count(DISTINCT part_id) AS parts, sum(n) AS whole FROM vc GROUP BY 1)
 SELECT support, col_name, round(count(*) / any_value(a.parts)::DOUBLE, 6) AS items, round(sum(n) / any_value(a.whole)::DOUBLE, 6) AS covered FROM vc JOIN a USING (col_name), (VALUES {', '.join(f'({s}::DOUBLE)' for s in SUPPORTS)}) t(support) WHERE n >= vc.whole * support GROUP BY 1, 2"""


@register("v9_supports", _supports_sql())
def v9_supports(spark: SparkSession, d: str) -> DataFrame:
    """Heavy hitters of a partition and the rows they cover, by support; a support that no value reaches has no row."""
    from coarsesample.operators import sketches as S

    vc, out = S.value_counts(lines(spark, d), ["l_quantity", "l_linenumber"], "double"), None
    whole = vc.groupBy("col_name").agg(F.countDistinct("part_id").alias("parts"), F.sum("n").alias("whole"))
    for s in SUPPORTS:
        one = S.heavy_hitters(vc, s).groupBy("col_name").agg(F.count(F.lit(1)).alias("items"), F.sum("n").alias("n")).select(F.lit(s).alias("support"), "*")
        out = one if out is None else out.unionByName(one)
    shares = out.join(F.broadcast(whole), "col_name").select("support", "col_name", (F.col("items") / F.col("parts")).alias("items"), (F.col("n") / F.col("whole")).alias("covered"))
    return rounded(shares, 6)


def _bitmap_caps_sql() -> str:
    from coarsesample.plans.registry import counts_sql

    return f"""WITH {LINES}, hh AS (SELECT part_id, value, n FROM ({counts_sql(['l_quantity'], 'DOUBLE')}) QUALIFY n >= 0.01 * sum(n) OVER (PARTITION BY part_id)), g AS (SELECT value, sum(n) AS n, row_number() OVER (ORDER BY sum(n) DESC, value) AS place FROM hh GROUP BY value)
 SELECT cap, count(*) AS bits, round(sum(n) / (SELECT sum(n) FROM g)::DOUBLE, 6) AS covered FROM g, (VALUES (5), (10), (25), (50)) t(cap) WHERE place <= cap GROUP BY cap"""


@register("v9_bitmap_caps", _bitmap_caps_sql())
def v9_bitmap_caps(spark: SparkSession, d: str) -> DataFrame:
    """Share of the heavy hitters' rows that the occurrence bitmap can name, by its cap."""
    from coarsesample.operators import sketches as S
    from coarsesample.runtime import materialize

    hh, out = materialize(S.heavy_hitters(S.value_counts(lines(spark, d), ["l_quantity"], "double")), "hitters"), None
    for cap in (5, 10, 25, 50):
        one = S.global_heavy_hitters(hh, cap).agg(F.lit(cap).alias("cap"), F.count(F.lit(1)).alias("bits"), F.sum("n").alias("n"))
        out = one if out is None else out.unionByName(one)
    whole = hh.agg(F.sum("n").alias("whole"))
    return rounded(out.crossJoin(F.broadcast(whole)).select("cap", "bits", (F.col("n") / F.col("whole")).alias("covered")), 6)
