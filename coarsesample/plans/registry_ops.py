"""Queries on the operators around the methods (family o), streams (s) and functions (u)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.functions import udfs
from coarsesample.functions.portable import zipf_like
from coarsesample.operators import relational as R
from coarsesample.operators import sketches as S
from coarsesample.plans.query import And, Clause, In, Like, Not, Or, to_sql
from coarsesample.plans.registry import LINES, lines, register, rounded
from coarsesample.runtime import materialize, read_table, scratch_path, ship_package
from coarsesample.sources.io import scan, scan_any, write_table
from coarsesample.streaming import streams


def plain(name: str, sql: str, spark_sql: str | None = None, tables: str = "lineitem", digits: int = 4, doubles: str = "") -> None:
    """A query whose Spark form is SQL too, over temporary views of the tables; ``doubles`` are rounded in both."""
    wrapped = f"SELECT * REPLACE ({', '.join(f'round({c}, {digits}) + 0.0 AS {c}' for c in doubles.split())}) FROM ({sql})" if doubles else sql

    @register(name, wrapped)
    def run(spark: SparkSession, d: str) -> DataFrame:
        for t in tables.split():
            read_table(spark, d, t).createOrReplaceTempView(t)
        return rounded(spark.sql(spark_sql or sql), digits)


@register("o01_scan", "SELECT l_orderkey, round(l_quantity, 2) AS l_quantity FROM lineitem WHERE l_quantity > 49.5 AND l_returnflag = 'A'")
def o01_scan(spark: SparkSession, d: str) -> DataFrame:
    return rounded(scan(spark, d, "lineitem", ["l_orderkey", "l_quantity"], "l_quantity > 49.5 AND l_returnflag = 'A'"), 2)


@register("o02_sources", "SELECT f.fmt, n.n_nationkey, n.n_name FROM nation n, (VALUES ('csv'), ('json'), ('orc'), ('memory')) f(fmt)")
def o02_sources(spark: SparkSession, d: str) -> DataFrame:
    nation = read_table(spark, d, "nation").select("n_nationkey", "n_name")
    out = None
    for fmt in ("csv", "json", "orc", "memory"):
        if fmt == "memory":
            back = spark.createDataFrame(nation.collect(), nation.schema)
        else:
            path = scratch_path(spark, fmt)
            write_table(nation, path, fmt)
            back = scan_any(spark, fmt, path, nation.schema)
        back = back.select(F.lit(fmt).alias("fmt"), "*")
        out = back if out is None else out.unionByName(back)
    return out


@register("o03_sinks", "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def o03_sinks(spark: SparkSession, d: str) -> DataFrame:
    path = scratch_path(spark, "sink")
    write_table(read_table(spark, d, "lineitem").select("l_returnflag", "l_quantity"), path, "parquet", by=["l_returnflag"])
    write_table(read_table(spark, d, "lineitem").select("l_returnflag", "l_quantity").limit(0), path, "parquet", mode="append", by=["l_returnflag"])
    return spark.read.parquet(path).groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@register("o04_data_source", f"WITH {LINES} SELECT part_id, count(*) AS n, 10.0::DOUBLE AS weight FROM li WHERE part_id IN (3, 13) GROUP BY 1")
def o04_data_source(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.sources.io import read_weighted
    from coarsesample.sources.layouts import write_layout

    path = scratch_path(spark, "weighted")
    write_layout(lines(spark, d), path)
    return read_weighted(spark, path, {3: 10.0, 13: 10.0}).groupBy("part_id", "weight").agg(F.count(F.lit(1)).alias("n"))


@register("o05_sample_by_key", "SELECT l_returnflag, count(*) AS n FROM lineitem WHERE (l_orderkey * 7919) % 100 < CASE l_returnflag WHEN 'A' THEN 10 ELSE 2 END GROUP BY 1")
def o05_sample_by_key(spark: SparkSession, d: str) -> DataFrame:
    rate = F.when(F.col("l_returnflag") == "A", 10).otherwise(2)
    return read_table(spark, d, "lineitem").where(F.pmod(F.col("l_orderkey") * 7919, F.lit(100)) < rate).groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


plain("o06_project", "SELECT l_orderkey, l_linenumber, l_quantity * l_extendedprice AS gross, CAST(l_quantity AS INTEGER) AS whole, 'x' AS tag FROM lineitem", doubles="gross")

PRED = Or((And((Clause("l_quantity", ">=", 10.0), Clause("l_quantity", "<=", 12.0), Not(In("l_returnflag", ("A",))))), And((Like("l_linestatus", "F%"), Clause("l_discount", "<", 0.01), Clause("l_tax", "<>", 0.02)))))


@register("o07_filter", f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem WHERE {to_sql(PRED)} GROUP BY 1, 2")
def o07_filter(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").where(to_sql(PRED)).groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


plain("o08_case", "SELECT CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'mid' ELSE 'big' END AS size, count(*) AS n, sum(coalesce(nullif(l_discount, 0), 1)) AS s FROM lineitem GROUP BY 1", doubles="s")
plain("o09_inner_join", "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1", tables="lineitem orders", doubles="q")
plain("o09_left_join", "SELECT quality, count(*) AS n FROM documents LEFT JOIN labels ON documents.doc_id = labels.doc_id GROUP BY 1", tables="documents labels")
plain("o09_full_join", "SELECT count(*) AS n, count(d.doc_id) AS docs, count(l.doc_id) AS labelled FROM documents d FULL JOIN (SELECT doc_id + 5 AS doc_id FROM labels) l ON d.doc_id = l.doc_id", tables="documents labels")


@register("o09_join_hints", "SELECT 'merge' AS hint, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT 'shuffle_hash', count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT 'broadcast', count(*) FROM lineitem JOIN nation ON l_linenumber = n_nationkey")
def o09_join_hints(spark: SparkSession, d: str) -> DataFrame:
    li, orders, nation = (read_table(spark, d, t) for t in ("lineitem", "orders", "nation"))
    one = lambda h, other, on: li.join(other.hint(h), on).agg(F.lit(h).alias("hint"), F.count(F.lit(1)).alias("n"))
    key = F.col("l_orderkey") == F.col("o_orderkey")
    return one("merge", orders, key).unionByName(one("shuffle_hash", orders, key)).unionByName(one("broadcast", nation, F.col("l_linenumber") == F.col("n_nationkey")))


plain("o10_semi", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49) GROUP BY 1", tables="lineitem orders")
plain("o10_anti", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey) GROUP BY 1", tables="lineitem orders")


@register("o11_band_join", "SELECT b.low, count(*) AS n FROM lineitem JOIN (VALUES (0, 10), (10, 25), (25, 60)) b(low, high) ON l_quantity >= low AND l_quantity < high GROUP BY 1")
def o11_band_join(spark: SparkSession, d: str) -> DataFrame:
    bands = spark.createDataFrame([(0, 10), (10, 25), (25, 60)], "low int, high int")
    return R.band_join(read_table(spark, d, "lineitem"), "l_quantity", bands, "low", "high").groupBy("low").agg(F.count(F.lit(1)).alias("n"))



@register("o12_as_of_join", "SELECT e.event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.ts < e.ts AND p.event_type = 'click' AND p.ts = (SELECT max(q.ts) FROM events q WHERE q.user_id = e.user_id AND q.ts < e.ts AND q.event_type = 'click')) IS NOT NULL AS found FROM events e")
def o12_as_of_join(spark: SparkSession, d: str) -> DataFrame:
    events = read_table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = events.where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click"))
    return R.as_of_join(events, clicks, "user_id", "ts", ["click"]).select("event_id", F.col("prev_click").isNotNull().alias("found"))


@register("o13_interval_join", "SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view' AND abs(epoch(a.ts) - epoch(b.ts)) <= 3600")
def o13_interval_join(spark: SparkSession, d: str) -> DataFrame:
    seconds = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)") / 1e6
    e = read_table(spark, d, "events").select("user_id", "event_type", seconds.alias("s"))
    a, b = e.where("event_type = 'click'").select("user_id", F.col("s").alias("t")), e.where("event_type = 'view'").select("user_id", F.col("s").alias("u"))
    return R.interval_join(a, b, "user_id", "t", "u", 3600.0).agg(F.count(F.lit(1)).alias("pairs"))


plain("o14_cross_join", "SELECT r_name, n_name FROM region CROSS JOIN nation", tables="region nation")
plain("o15_aggregate", "SELECT l_returnflag, sum(l_quantity) AS s, count(*) AS n, avg(l_discount) AS a, min(l_tax) AS low, max(l_tax) AS high, stddev_samp(l_quantity) AS sd, var_samp(l_quantity) AS v, corr(l_quantity, l_extendedprice) AS c FROM lineitem GROUP BY 1", doubles="s a low high sd v c")
plain("o16_count_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, CAST(sum(DISTINCT l_linenumber) AS BIGINT) AS s FROM lineitem GROUP BY 1")
plain("o17_conditional", "SELECT l_linestatus, sum(l_quantity) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_quantity > 40) AS big FROM lineitem GROUP BY 1", doubles="a")
plain("o18_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
plain("o18_cube", "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) AS INTEGER) AS g, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
plain("o18_rollup", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)", doubles="q")
plain("o19_collect", "SELECT l_linestatus, array_to_string(list_sort(list(DISTINCT l_linenumber)), ',') AS numbers FROM lineitem GROUP BY 1", "SELECT l_linestatus, array_join(sort_array(collect_set(l_linenumber)), ',') AS numbers FROM lineitem GROUP BY 1")


@register("o20_approx_distinct")
def o20_approx_distinct(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").agg(F.approx_count_distinct("l_orderkey").alias("hll_pp"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("hll"), F.expr("theta_sketch_estimate(theta_sketch_agg(l_orderkey))").alias("theta"), F.countDistinct("l_orderkey").alias("exact"))


plain("o21_percentile", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS p50, quantile_cont(l_extendedprice, 0.9) AS p90 FROM lineitem GROUP BY 1", "SELECT l_returnflag, percentile(l_quantity, 0.5) AS p50, percentile(l_extendedprice, 0.9) AS p90 FROM lineitem GROUP BY 1", doubles="p50 p90")


@register("o21_percentile_sketches")
def o21_percentile_sketches(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", 0.5).alias("approx"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D)").alias("kll"))


@register("o22_frequency_sketches")
def o22_frequency_sketches(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").agg(F.length(F.count_min_sketch("l_partkey", F.lit(0.01), F.lit(0.95), F.lit(7))).alias("cms_bytes"), F.size(F.expr("approx_top_k(l_returnflag, 3)")).alias("top"), F.size(F.histogram_numeric("l_quantity", F.lit(5))).alias("bins"))


@register("o23_pivot", "SELECT l_returnflag, round(sum(l_quantity) FILTER (WHERE l_linestatus = 'F'), 4) AS F, round(sum(l_quantity) FILTER (WHERE l_linestatus = 'O'), 4) AS O FROM lineitem GROUP BY 1")
def o23_pivot(spark: SparkSession, d: str) -> DataFrame:
    return rounded(read_table(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.sum("l_quantity")))


@register("o23_unpivot", "SELECT name, round(sum(x), 4) AS total FROM (SELECT 'l_quantity' AS name, l_quantity AS x FROM lineitem UNION ALL SELECT 'l_tax', l_tax FROM lineitem) GROUP BY 1")
def o23_unpivot(spark: SparkSession, d: str) -> DataFrame:
    long = read_table(spark, d, "lineitem").unpivot(["l_orderkey"], ["l_quantity", "l_tax"], "name", "x")
    return rounded(long.groupBy("name").agg(F.sum("x").alias("total")))


W6 = "WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate)"
plain("o24_ranking", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(2) OVER w AS INTEGER) AS nt, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM lineitem {W6}", doubles="pr cd")
plain("o25_analytic", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, lag(l_quantity) OVER w AS prev, lead(l_quantity) OVER w AS next, first_value(l_quantity) OVER w AS f, sum(l_quantity) OVER (w ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS moving, avg(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber RANGE BETWEEN 1 PRECEDING AND CURRENT ROW) AS near FROM lineitem {W6}", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, lag(l_quantity) OVER w AS prev, lead(l_quantity) OVER w AS next, first_value(l_quantity) OVER w AS f, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS moving, avg(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber RANGE BETWEEN 1 PRECEDING AND CURRENT ROW) AS near FROM lineitem {W6}", doubles="prev next f moving near")
plain("o26_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", tables="orders", doubles="o_totalprice")
plain("o26_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5", tables="orders")


@register("o26_top_k_per_group", "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def o26_top_k_per_group(spark: SparkSession, d: str) -> DataFrame:
    return R.top_k_per_group(read_table(spark, d, "orders"), ["o_orderpriority"], [F.desc("o_totalprice"), "o_orderkey"], 3).select("o_orderpriority", "o_orderkey")


plain("o27_union", "SELECT kind, count(*) AS n FROM (SELECT 'a' AS kind, n_name AS x FROM nation UNION ALL SELECT 'b', r_name FROM region UNION SELECT 'a', n_name FROM nation) GROUP BY 1", tables="nation region")
plain("o27_intersect_except", "SELECT * FROM (SELECT l_linenumber AS x FROM lineitem INTERSECT SELECT n_nationkey FROM nation) EXCEPT SELECT r_regionkey FROM region", tables="lineitem nation region")
plain("o27_bag_operations", "SELECT x, count(*) AS n FROM (SELECT l_linenumber % 3 AS x FROM lineitem EXCEPT ALL SELECT n_nationkey % 3 FROM nation) GROUP BY 1", tables="lineitem nation")


@register("o27_dedupe", "SELECT count(*) AS n FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)")
def o27_dedupe(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").dropDuplicates(["l_orderkey", "l_linenumber"]).agg(F.count(F.lit(1)).alias("n"))


plain("o28_strings", "SELECT p_partkey, upper(p_name) AS u, substr(p_name, 1, 3) AS s, CAST(length(p_name) AS INTEGER) AS n, replace(p_name, ' ', '_') AS r, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, md5(p_name) AS h, trim(concat(' ', p_type, ' ')) AS t FROM part", tables="part")
plain("o29_dates", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(day(o_orderdate) AS INTEGER) AS dd, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS first_day, CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS later FROM orders", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS dd, datediff(o_orderdate, DATE '1995-01-01') AS days, CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS first_day, add_months(CAST(o_orderdate AS DATE), 2) AS later FROM orders", tables="orders")
plain("o30_math", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, ln(l_extendedprice) AS a, exp(l_tax) AS b, sqrt(l_quantity) AS c, power(l_quantity, 2) AS d, abs(l_discount - 0.05) AS e, floor(l_quantity / 7) AS f, least(l_tax, l_discount) AS g, greatest(l_tax, l_discount) AS h, l_partkey % 7 AS i FROM lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, ln(l_extendedprice) AS a, exp(l_tax) AS b, sqrt(l_quantity) AS c, power(l_quantity, 2) AS d, abs(l_discount - 0.05) AS e, CAST(floor(l_quantity / 7) AS DOUBLE) AS f, least(l_tax, l_discount) AS g, greatest(l_tax, l_discount) AS h, l_partkey % 7 AS i FROM lineitem", doubles="a b c d e f g h")


@register("o30_skew_column", "SELECT CAST(floor(exp(ln(26.0::DOUBLE) * ((l_partkey) % 997) / 997.0::DOUBLE)) AS INTEGER) AS z, count(*) AS n FROM lineitem GROUP BY 1")
def o30_skew_column(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "lineitem").groupBy(zipf_like(F.col("l_partkey")).alias("z")).agg(F.count(F.lit(1)).alias("n"))


@register("o30_salted_sum", "SELECT l_returnflag, round(sum(l_quantity), 2) AS total, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY 1")
def o30_salted_sum(spark: SparkSession, d: str) -> DataFrame:
    return rounded(R.salted_sum(read_table(spark, d, "lineitem"), "l_returnflag", "l_quantity"), 2)


plain("o31_arrays", "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS sq, round(CAST(list_max(embedding) AS DOUBLE), 4) AS top, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings", "SELECT vec_id, CAST(size(embedding) AS BIGINT) AS n, aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * x), 0D, (a, x) -> a + x) AS sq, CAST(array_max(embedding) AS DOUBLE) AS top, CAST(size(filter(embedding, x -> x > 0)) AS BIGINT) AS pos FROM embeddings", tables="embeddings", doubles="sq top")
plain("o31_explode", "SELECT w, count(*) AS n FROM (SELECT unnest(string_split(p_name, ' ')) AS w FROM part) GROUP BY 1", "SELECT w, count(*) AS n FROM part LATERAL VIEW explode(split(p_name, ' ')) AS w GROUP BY 1", tables="part")
plain("o32_maps", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM lineitem GROUP BY 1", "SELECT l_returnflag, element_at(map_from_entries(collect_list(struct(l_linestatus, n))), 'O') AS o FROM (SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY 1, 2) GROUP BY 1")
plain("o33_json", "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1", "SELECT from_json(props, 'k INT').k AS k, count(*) AS n FROM events GROUP BY 1", tables="events")


@register("o34_vectors", "SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: CAST(z[1] AS DOUBLE) * z[2])), 3) + 0.0 AS d FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id = 0) b")
def o34_vectors(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return rounded(e.crossJoin(F.broadcast(e.where("vec_id = 0").select(F.col("v").alias("u")))).select("vec_id", R.dot("v", "u").alias("d")), 3)


@register("o34_median_vector", "SELECT label, CAST(i AS INTEGER) AS at, round(quantile_cont(CAST(embedding[i + 1] AS DOUBLE), 0.5), 4) AS median FROM embeddings, range(64) t(i) GROUP BY 1, 2")
def o34_median_vector(spark: SparkSession, d: str) -> DataFrame:
    return rounded(R.median_vector(read_table(spark, d, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v")), ["label"], "v"))


plain("o35_bits", "SELECT l_returnflag, CAST(bit_or(1 << l_linenumber) AS BIGINT) AS seen, CAST(bit_count(CAST(bit_or(1 << l_linenumber) AS BIGINT)) AS INTEGER) AS n FROM lineitem GROUP BY 1", "SELECT l_returnflag, bit_or(shiftleft(1L, l_linenumber)) AS seen, bit_count(bit_or(shiftleft(1L, l_linenumber))) AS n FROM lineitem GROUP BY 1")
plain("o36_subqueries", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS s FROM orders GROUP BY 1) SELECT c_mktsegment, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM big WHERE s > (SELECT avg(s) FROM big)) GROUP BY 1", tables="orders customer")
plain("o36_correlated", "SELECT o_orderpriority, count(*) AS n FROM orders o WHERE o_totalprice > (SELECT avg(i.o_totalprice) FROM orders i WHERE i.o_orderpriority = o.o_orderpriority) GROUP BY 1", tables="orders")


@register("o37_checkpoint", "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def o37_checkpoint(spark: SparkSession, d: str) -> DataFrame:
    return materialize(read_table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")), "flags")


@register("o38_pruned_scan", f"WITH {LINES} SELECT count(DISTINCT part_id) AS files FROM li WHERE part_id IN (3, 13)")
def o38_pruned_scan(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.sources.layouts import write_layout

    path = scratch_path(spark, "pruned")
    write_layout(lines(spark, d), path)
    df = spark.read.parquet(path).where(F.col("part_id").isin([3, 13]))
    return df.select(F.input_file_name().alias("f")).distinct().agg(F.count(F.lit(1)).alias("files"))


# Streams
DAY = "CAST(epoch(date_trunc('day', ts)) AS BIGINT)"


@register("s1_ingest", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def s1_ingest(spark: SparkSession, d: str) -> DataFrame:
    return streams.drain(streams.events_stream(spark, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "complete", "s1")


@register("s2_tumbling", f"SELECT {DAY} AS start, event_type, count(*) AS n, round(min(value), 4) AS low, round(max(value), 4) AS high, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def s2_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return rounded(streams.drain(streams.windowed(streams.events_stream(spark, d), "1 day"), "complete", "s2"))


@register("s3_sliding", "SELECT CAST(s AS BIGINT) AS start, event_type, count(*) AS n, round(min(value), 4) AS low, round(max(value), 4) AS high, round(sum(value), 4) AS total FROM (SELECT *, unnest([floor(epoch(ts) / 43200) * 43200, floor(epoch(ts) / 43200) * 43200 - 43200]) AS s FROM events) GROUP BY 1, 2")
def s3_sliding(spark: SparkSession, d: str) -> DataFrame:
    return rounded(streams.drain(streams.windowed(streams.events_stream(spark, d), "1 day", "12 hours"), "complete", "s3"))


@register("s4_sessions", "WITH g AS (SELECT user_id, floor(epoch(ts)) AS s, value FROM events), f AS (SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY user_id ORDER BY s) < 7200 THEN 0 ELSE 1 END AS new FROM g), i AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY s ROWS UNBOUNDED PRECEDING) AS run FROM f) SELECT user_id, CAST(min(s) AS BIGINT) AS start, count(*) AS n, round(sum(value), 4) AS total FROM i GROUP BY user_id, run")
def s4_sessions(spark: SparkSession, d: str) -> DataFrame:
    return rounded(streams.drain(streams.sessions(streams.events_stream(spark, d), "2 hours"), "complete", "s4"))


@register("s5_seal", f"SELECT {DAY} // 86400 AS part_id, count(*) AS n_rows, round(avg(value), 4) AS mean, round(max(value), 4) AS max FROM events GROUP BY 1 HAVING ({DAY} // 86400 + 1) * 86400 <= (SELECT max(CAST(floor(epoch(ts)) AS BIGINT)) FROM events) - 3600")
def s5_seal(spark: SparkSession, d: str) -> DataFrame:
    return rounded(streams.drain(streams.sealed(streams.events_stream(spark, d, 1000)), "append", "s5"))


@register("s6_stateful", "SELECT CAST(user_id % 10 AS INTEGER) AS key, count(*) AS n, round(min(value), 4) AS low, round(max(value), 4) AS high, round(sum(value), 2) AS total FROM events GROUP BY 1")
def s6_stateful(spark: SparkSession, d: str) -> DataFrame:
    ship_package(spark)
    out = streams.drain(streams.stateful(streams.events_stream(spark, d, 1000)), "update", "s6")
    last = R.top_k_per_group(out, ["key"], [F.desc("n")], 1)
    return last.select("key", "n", F.round("low", 4).alias("low"), F.round("high", 4).alias("high"), F.round("total", 2).alias("total"))


LATE = "event_id % 97 = 5"
MARK = f"(SELECT max(CAST(floor(epoch(ts)) AS BIGINT)) FROM events WHERE NOT ({LATE})) - 3600"


@register("s7_late_rows", f"SELECT CAST({DAY} // 86400 AS VARCHAR) || CASE WHEN {LATE} AND ({DAY} // 86400 + 1) * 86400 <= {MARK} THEN '-delta' ELSE '' END AS part_key, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def s7_late_rows(spark: SparkSession, d: str) -> DataFrame:
    out = streams.deltas(spark, d, LATE)
    return rounded(out.groupBy("part_key").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")))


@register("s8_dedupe", "SELECT count(DISTINCT event_id) AS n FROM events")
def s8_dedupe(spark: SparkSession, d: str) -> DataFrame:
    events = streams.events_stream(spark, d)
    twice = events.select("event_id", "at").union(events.select("event_id", "at")).withWatermark("at", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return streams.drain(twice, "append", "s8").agg(F.count(F.lit(1)).alias("n"))


@register("s8_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def s8_static_join(spark: SparkSession, d: str) -> DataFrame:
    joined = streams.events_stream(spark, d).join(read_table(spark, d, "customer").select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    return streams.drain(joined.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete", "s8s")


@register("s8_stream_join", "SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view' AND floor(epoch(b.ts)) >= floor(epoch(a.ts)) AND floor(epoch(b.ts)) <= floor(epoch(a.ts)) + 3600")
def s8_stream_join(spark: SparkSession, d: str) -> DataFrame:
    e = streams.events_stream(spark, d)
    a = e.where("event_type = 'click'").select(F.col("user_id").alias("u1"), F.col("at").alias("t1")).withWatermark("t1", "1 hour")
    b = e.where("event_type = 'view'").select(F.col("user_id").alias("u2"), F.col("at").alias("t2")).withWatermark("t2", "1 hour")
    joined = a.join(b, F.expr("u1 = u2 and t2 >= t1 and t2 <= t1 + interval 1 hour"))
    return streams.drain(joined, "append", "s8j").agg(F.count(F.lit(1)).alias("pairs"))


# Functions on stored sketches
@register("u1_sketch_expressions", f"WITH {LINES} SELECT part_id, count(DISTINCT l_returnflag) AS ndv, max(n) AS top FROM (SELECT part_id, l_returnflag, count(*) AS n FROM li GROUP BY 1, 2) GROUP BY 1")
def u1_sketch_expressions(spark: SparkSession, d: str) -> DataFrame:
    vc = S.value_counts(lines(spark, d), ["l_returnflag"], "string")
    arrays = vc.groupBy("part_id").agg(F.sort_array(F.collect_list(F.struct("n", "value"))).alias("hh"))
    return arrays.select("part_id", F.size("hh").cast("long").alias("ndv"), udfs.top_frequency("hh").alias("top"))


@register("u2_grouped_sketch", f"WITH {LINES} SELECT part_id, CAST(count(DISTINCT l_linenumber) AS DOUBLE) AS ndv FROM li GROUP BY 1")
def u2_grouped_sketch(spark: SparkSession, d: str) -> DataFrame:
    ship_package(spark)
    return lines(spark, d).groupBy("part_id").agg(udfs.kmv_distinct(F.xxhash64("l_linenumber")).alias("ndv"))


@register("u3_table_function", f"WITH {LINES} SELECT part_id, l_returnflag AS value, count(*) AS n FROM li GROUP BY 1, 2")
def u3_table_function(spark: SparkSession, d: str) -> DataFrame:
    ship_package(spark)
    vc = S.value_counts(lines(spark, d), ["l_returnflag"], "string")
    held = vc.groupBy("part_id").agg(F.sort_array(F.collect_list(F.struct("value", "n"))).alias("sketch"))
    spark.udtf.register("sketch_explode", udfs.SketchExplode)
    materialize(held, "sketches").createOrReplaceTempView("held_sketches")
    return spark.sql("SELECT s.part_id, t.value, t.n FROM held_sketches s, LATERAL sketch_explode(s.sketch) t")




@register("u4_weighted_sql")
def u4_weighted_sql(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.plans.experiments import trained
    from coarsesample.plans.front import weighted_sql

    p = trained(spark, d, "events", "user")[0]
    return rounded(weighted_sql(p, "SELECT event_type, sum(value) AS s, count(*) AS n FROM events WHERE k > 50 GROUP BY event_type", 0.2), 2)


@register("u4_weighted_sql_full", "SELECT event_type, round(sum(value), 2) AS s, CAST(count(*) AS DOUBLE) AS n FROM events WHERE CAST(json_extract_string(props, '$.k') AS INTEGER) > 50 GROUP BY event_type")
def u4_weighted_sql_full(spark: SparkSession, d: str) -> DataFrame:
    from coarsesample.plans.experiments import trained
    from coarsesample.plans.front import weighted_sql

    p = trained(spark, d, "events", "user")[0]
    return rounded(weighted_sql(p, "SELECT event_type, sum(value) AS s, count(*) AS n FROM events WHERE k > 50 GROUP BY event_type", 1.0), 2)
