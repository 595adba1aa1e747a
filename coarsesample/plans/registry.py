"""Registration of queries with their SQL, and SQL texts shared by several."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.plans.query import QuerySpec, to_sql
from coarsesample.runtime import read_table
from coarsesample.sources.layouts import assign_bucketed

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    """Decorator: the function is query ``name``; ``sql`` is its DuckDB text."""

    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return put


def rounded(df: DataFrame, digits: int = 4) -> DataFrame:
    """All doubles rounded, for comparison between engines; negative zero becomes zero."""
    return df.select(*[(F.round(F.col(c), digits) + F.lit(0.0)).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem in value buckets of 25 shipping days."""
    table = read_table(spark, sf_dir, "lineitem")
    return assign_bucketed(table.withColumn("ship_day", F.datediff("l_shipdate", F.lit("1995-01-01"))), F.col("ship_day"), 25)


SHIP_DAY = "CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS INTEGER)"
LINES = f"li AS (SELECT *, {SHIP_DAY} AS ship_day, CAST(floor({SHIP_DAY} / 25.0) AS INTEGER) AS part_id FROM lineitem)"
EPOCH = "CAST(date_diff('day', DATE '1970-01-01', CAST({} AS DATE)) AS INTEGER)"


def zipf_sql(key: str) -> str:
    return f"CAST(floor(exp(ln(26.0::DOUBLE) * (({key}) % 997) / 997.0::DOUBLE)) AS INTEGER)"


WIDE = f"""wide AS (SELECT l.*, o.o_custkey, o.o_orderstatus, o.o_totalprice, o.o_orderdate, o.o_orderpriority, c.c_acctbal, c.c_mktsegment,
 p.p_name, p.p_brand, p.p_type, p.p_size, p.p_retailprice, s.s_acctbal, cn.n_name AS cust_nation, cr.r_name AS cust_region, sn.n_name AS supp_nation, sr.r_name AS supp_region,
 {EPOCH.format('l_shipdate')} AS ship_day, {EPOCH.format('o_orderdate')} AS order_day, CAST(year(l_shipdate) AS INTEGER) AS ship_year, CAST(year(o_orderdate) AS INTEGER) AS order_year,
 l_extendedprice * (1 - l_discount) AS revenue, CASE WHEN cn.n_name = sn.n_name THEN 'yes' ELSE 'no' END AS same_nation,
 {zipf_sql('l_partkey')} AS z_part, {zipf_sql('l_suppkey * 13')} AS z_supp, {zipf_sql('o_custkey * 5')} AS z_cust
 FROM lineitem l JOIN orders o ON l_orderkey = o_orderkey JOIN customer c ON o_custkey = c_custkey JOIN part p ON l_partkey = p_partkey JOIN supplier s ON l_suppkey = s_suppkey
 JOIN nation cn ON c_nationkey = cn.n_nationkey JOIN region cr ON cn.n_regionkey = cr.r_regionkey JOIN nation sn ON s_nationkey = sn.n_nationkey JOIN region sr ON sn.n_regionkey = sr.r_regionkey)"""


def answer_sql(q: QuerySpec, table: str, weight: str | None = None, digits: int = 4) -> str:
    """SELECT text of a query's exact answer, or of its weighted one where ``weight`` is a column.

    Products of the tables' prices and rates have four decimals; fewer digits would round at ties.
    """
    w = weight or "1"
    out = list(q.group_by)
    for a in q.aggs:
        x = "1" if a.expr == "*" else f"({a.expr})"
        x = x if a.where is None else f"CASE WHEN {to_sql(a.where)} THEN {x} END"
        total = f"coalesce(sum(CAST({x} AS DOUBLE) * {w}), 0)"
        count = f"coalesce(sum(CASE WHEN {x} IS NOT NULL THEN CAST({w} AS DOUBLE) END), 0)"
        e = {"sum": total, "count": count, "avg": f"{total} / nullif({count}, 0)"}[a.fn]
        out.append(f"round(CAST({e} AS DOUBLE), {digits}) + 0.0 AS {a.alias}")
    group = f" GROUP BY {', '.join(q.group_by)}" if q.group_by else ""
    return f"SELECT {', '.join(out)} FROM {table} WHERE {to_sql(q.where)}{group}"


def counts_sql(cols: list[str], kind: str) -> str:
    """CTE body: part_id, col_name, value, n of the bucketed lines."""
    return " UNION ALL ".join(f"SELECT part_id, '{c}' AS col_name, CAST({c} AS {kind}) AS value, count(*) AS n FROM li WHERE {c} IS NOT NULL GROUP BY ALL" for c in cols)


HASH = "CAST('0x' || substr(md5({}), 1, 8) AS BIGINT)"


def histogram_sql(source: str, buckets: int = 10) -> str:
    """Equal-depth histogram of value counts."""
    placed = f"SELECT *, CAST(floor(coalesce(sum(n) OVER (PARTITION BY part_id, col_name ORDER BY value ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * {buckets} / sum(n) OVER (PARTITION BY part_id, col_name)) AS INTEGER) AS bucket FROM {source}"
    return f"SELECT part_id, col_name, bucket, min(value) AS lo, max(value) AS hi, CAST(sum(n) AS BIGINT) AS n_rows, count(*) AS ndv FROM ({placed}) GROUP BY 1, 2, 3"
