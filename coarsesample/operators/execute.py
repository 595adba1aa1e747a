"""Running a query on weighted partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.plans.query import QuerySpec, finish, to_sql


def weighted_scan(df: DataFrame, selection: DataFrame, path: str | None = None) -> DataFrame:
    """The chosen partitions' rows with column ``weight``.

    Where the table lies in one directory per part_id at ``path``, only the chosen directories are
    listed and read, however many they are. Otherwise the choice is a literal list of any length,
    which prunes partition directories at planning and else filters rows; a broadcast join alone would
    read everything. A selection is a plan's result: some bytes for every partition that is read.
    """
    weights = {r["part_id"]: r["weight"] for r in selection.select("part_id", "weight").collect()}
    if not weights:
        return df.where("false").withColumn("weight", F.lit(0.0))
    if path:
        chosen = df.sparkSession.read.schema(df.schema).option("basePath", path).parquet(*[f"{path}/part_id={p}" for p in sorted(weights)])
        chosen = chosen.select(*df.columns)
    else:
        chosen = df.where(f"part_id IN ({', '.join(map(str, sorted(weights)))})")
    return chosen.join(F.broadcast(selection.select("part_id", "weight")), "part_id")


def weighted_aggregate(df: DataFrame, q: QuerySpec) -> DataFrame:
    """Weighted answers: SUM of w*x, COUNT of w, AVG their quotient over non-null x."""
    given = df if q.where is None else df.where(to_sql(q.where))
    out = []
    for a in q.aggs:
        x = F.lit(1) if a.expr == "*" else F.expr(a.expr)
        x = x if a.where is None else F.when(F.expr(to_sql(a.where)), x)
        some = F.when(x.isNotNull(), F.col("weight"))
        total, count = F.coalesce(F.sum(x.cast("double") * F.col("weight")), F.lit(0.0)), F.coalesce(F.sum(some), F.lit(0.0))
        out += [(count if a.fn == "count" else total).alias(f"{a.alias}__s")] + ([count.alias(f"{a.alias}__c")] if a.fn == "avg" else [])
    return finish(q, given.groupBy(*q.group_by).agg(*out))
