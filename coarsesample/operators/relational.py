"""Helpers around Spark's relational operators that have no single built-in form."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str]) -> DataFrame:
    """Each left row with the last right row of its key strictly before it: a union and one sorted window, no nested loop.

    The right row travels as one struct, so its null values stay null and rows never mix. Of right rows
    at the same time the greatest struct counts.
    """
    row = F.struct(*[F.col(v).alias(v) for v in values])
    rest = [c for c in left.columns if c not in (key, at)]
    b = right.select(key, at, F.lit(1).alias("__side"), row.alias("__row"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in rest])
    a = left.select("*", F.lit(0).alias("__side"), F.lit(None).cast(b.schema["__row"].dataType).alias("__row"))
    w = Window.partitionBy(key).orderBy(at, "__side", "__row").rowsBetween(Window.unboundedPreceding, -1)
    joined = a.unionByName(b).withColumn("__last", F.last("__row", ignorenulls=True).over(w))
    return joined.where("__side = 0").select(*left.columns, *[F.col("__last")[v].alias(f"prev_{v}") for v in values])


def band_join(values: DataFrame, x: str, bands: DataFrame, low: str, high: str) -> DataFrame:
    """Rows with the bands [low, high) that hold them; bands are few and broadcast."""
    return values.join(F.broadcast(bands), (F.col(x) >= F.col(low)) & (F.col(x) < F.col(high)))


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, other: str, span: float) -> DataFrame:
    """Pairs of a key whose times differ by ``span`` at most, as an equi join on time buckets and their neighbours."""
    a = left.withColumn("__b", F.floor(F.col(at) / span))
    b = right.withColumn("__b", F.explode(F.array(*[F.floor(F.col(other) / span) + i for i in (-1, 0, 1)])))
    return a.join(b, [key, "__b"]).where(F.abs(F.col(at) - F.col(other)) <= span).drop("__b")


def top_k_per_group(df: DataFrame, by: list[str], order: list[Column | str], k: int) -> DataFrame:
    """The first k rows of each group; Spark prunes with a partial group limit before the shuffle."""
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("__r") <= k).drop("__r")


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """Sum by a skewed key in two steps."""
    part = df.groupBy(key, F.pmod(F.xxhash64(value), F.lit(salts)).alias("__s")).agg(F.sum(value).alias("__p"), F.count(F.lit(1)).alias("__n"))
    return part.groupBy(key).agg(F.sum("__p").alias("total"), F.sum("__n").alias("n"))


def squared_distance(a: str | Column, b: str | Column) -> Column:
    """Squared Euclidean distance of two arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)


def dot(a: str | Column, b: str | Column) -> Column:
    """Dot product of two arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def median_vector(df: DataFrame, by: list[str], vector: str) -> DataFrame:
    """Elementwise median per group, in long form (position, median)."""
    return df.select(*by, F.posexplode(vector).alias("at", "x")).groupBy(*by, "at").agg(F.percentile("x", 0.5).alias("median"))
