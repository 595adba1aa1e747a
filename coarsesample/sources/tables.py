"""The wide views of the experiments, derived from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.functions.portable import zipf_like
from coarsesample.runtime import broadcast_if_small, read_table


def days(column: str) -> F.Column:
    """A timestamp as days since the epoch, the numeric form that sketches use."""
    return F.datediff(F.col(column), F.lit("1970-01-01")).cast("int")


def lineitem_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star, joined once; joins keep every line."""
    read = lambda t: read_table(spark, sf_dir, t)
    nation = read("nation").join(read("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    side = lambda p: nation.select(F.col("n_nationkey").alias(f"{p}_nk"), F.col("n_name").alias(f"{p}_nation"), F.col("r_name").alias(f"{p}_region"))
    customer = read("customer").join(side("cust"), F.col("c_nationkey") == F.col("cust_nk")).drop("cust_nk", "c_name", "c_nationkey")
    supplier = read("supplier").join(side("supp"), F.col("s_nationkey") == F.col("supp_nk")).drop("supp_nk", "s_name", "s_nationkey")
    supplier = broadcast_if_small(supplier, 100_000)  # else all lines would be dealt by it
    orders = read("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).drop("c_custkey")
    wide = (
        read("lineitem")
        .join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(read("part"), F.col("l_partkey") == F.col("p_partkey"))
        .join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        .drop("o_orderkey", "p_partkey", "s_suppkey")
    )
    return wide.withColumns(
        {
            "ship_day": days("l_shipdate"),
            "order_day": days("o_orderdate"),
            "ship_year": F.year("l_shipdate"),
            "order_year": F.year("o_orderdate"),
            "revenue": F.col("l_extendedprice") * (1 - F.col("l_discount")),
            "same_nation": F.when(F.col("cust_nation") == F.col("supp_nation"), "yes").otherwise("no"),
            "z_part": zipf_like(F.col("l_partkey")),
            "z_supp": zipf_like(F.col("l_suppkey") * 13),
            "z_cust": zipf_like(F.col("o_custkey") * 5),
        }
    )


def orders_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with customer and place; days count from the epoch."""
    read = lambda t: read_table(spark, sf_dir, t)
    place = read("nation").join(read("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    customer = read("customer").join(place, F.col("c_nationkey") == F.col("n_nationkey"))
    wide = read("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).drop("c_custkey")
    return wide.withColumns({"o_day": days("o_orderdate"), "o_year": F.year("o_orderdate"), "o_month": F.month("o_orderdate")})


def events_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the JSON field, clock columns and a skewed tenant."""
    return read_table(spark, sf_dir, "events").withColumns(
        {"k": F.get_json_object("props", "$.k").cast("int"), "hour": F.hour("ts"), "dow": F.dayofweek("ts"), "z_user": zipf_like(F.col("user_id") * 7)}
    )


def documents_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with numbers drawn from the text, and labels where there are any."""
    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    text = F.col("text")
    flat = docs.withColumns(
        {
            "n_words": F.size(F.split(F.trim(text), r"\s+")).cast("long"),
            "n_lines": F.size(F.split(text, "\n")).cast("long"),
            "n_digits": F.regexp_count(text, F.lit("[0-9]")).cast("long"),
            "n_upper": F.regexp_count(text, F.lit("[A-Z]")).cast("long"),
            "n_punct": F.regexp_count(text, F.lit("[!-/:-@]")).cast("long"),
            "mean_word_len": F.char_length(F.regexp_replace(text, r"\s+", "")) / F.greatest(F.size(F.split(F.trim(text), r"\s+")), F.lit(1)),
        }
    ).drop("text")
    return flat.join(labels, "doc_id", "left")


def embeddings_wide(spark: SparkSession, sf_dir: str, dims: int = 64) -> DataFrame:
    """One numeric column per component."""
    table = read_table(spark, sf_dir, "embeddings")
    return table.select("vec_id", F.col("label").cast("string").alias("label"), *[F.col("embedding")[i].cast("double").alias(f"e{i}") for i in range(dims)])


def pages_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages by host and size."""
    return read_table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.length("html").cast("long").alias("n_chars"))


def conversations_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns by role and length."""
    return read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").cast("long").alias("n_chars"))
