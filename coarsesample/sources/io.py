"""Reading and writing tables of any format, and reading weighted partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from coarsesample.runtime import read_table


def scan(spark: SparkSession, sf_dir: str, name: str, cols: list[str], where: str = "true") -> DataFrame:
    """Column-pruned, filter-pushed read of a given table."""
    return read_table(spark, sf_dir, name).where(where).select(*cols)


def scan_any(spark: SparkSession, fmt: str, path: str, schema: StructType) -> DataFrame:
    """csv, json, orc, parquet or text with a declared schema; ``table`` reads a catalog table."""
    if fmt == "table":
        return spark.table(path)
    return spark.read.format(fmt).schema(schema).load(path)


def write_table(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", by: list[str] | None = None) -> None:
    """One set of files per value of ``by``, dealt beforehand so that a value isn't spread over all tasks."""
    if by:
        df.repartition(*by).write.format(fmt).mode(mode).partitionBy(*by).save(path)
    else:
        df.write.format(fmt).mode(mode).save(path)


def read_weighted(spark: SparkSession, path: str, weights: dict[int, float]) -> DataFrame:
    """Chosen partition directories only, by explicit paths, with their weights; the listing of others is never read."""
    paths = [f"{path}/part_id={p}" for p in sorted(weights)]
    table = spark.createDataFrame(sorted(weights.items()), "part_id int, weight double")
    return spark.read.option("basePath", path).parquet(*paths).join(F.broadcast(table), "part_id")
