"""Error, cost and quality measures over answers, curves and selections."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _met(true: DataFrame, est: DataFrame, keys: list[str], aggs: list[str]) -> DataFrame:
    """One row per true group: values, estimates and whether the group was found. Null keys meet."""
    right = est.select(*[F.col(k).alias(f"__{k}") for k in keys], *[F.col(a).cast("double").alias(f"__{a}") for a in aggs], F.lit(1).alias("__found"))
    on = F.lit(True)
    for k in keys:
        on = on & F.col(k).eqNullSafe(F.col(f"__{k}"))
    return true.join(right, on, "left") if keys else true.crossJoin(right)


def missed_groups(true: DataFrame, est: DataFrame, keys: list[str]) -> DataFrame:
    """Share of true groups that the estimate lacks."""
    return _met(true, est, keys, []).agg(F.avg(F.when(F.col("__found").isNull(), 1.0).otherwise(0.0)).alias("missed"))


def avg_rel_error(true: DataFrame, est: DataFrame, keys: list[str], aggs: list[str]) -> DataFrame:
    """Mean over groups and aggregates of |estimate - truth| / |truth|; a missed group counts 1, as does a wrong zero."""
    met, errors = _met(true, est, keys, aggs), []
    for a in aggs:
        t, e = F.col(a).cast("double"), F.col(f"__{a}")
        errors.append(F.when(F.col("__found").isNull(), 1.0).when(t == 0, F.when(e == 0, 0.0).otherwise(1.0)).otherwise(F.abs(e - t) / F.abs(t)))
    total = errors[0]
    for x in errors[1:]:
        total = total + x
    return met.agg(F.avg(total / len(aggs)).alias("rel_error"))


def abs_error_over_true(true: DataFrame, est: DataFrame, keys: list[str], aggs: list[str]) -> DataFrame:
    """Per aggregate the mean absolute error over the mean truth, then their mean; a missed estimate is 0."""
    met = _met(true, est, keys, aggs)
    each = [F.avg(F.abs(F.coalesce(F.col(f"__{a}"), F.lit(0.0)) - F.col(a))) / F.abs(F.avg(F.col(a).cast("double"))) for a in aggs]
    total = each[0]
    for x in each[1:]:
        total = total + x
    return met.agg((total / len(aggs)).alias("abs_over_true"))


def auc(curve: DataFrame, by: list[str], x: str = "budget", y: str = "error") -> DataFrame:
    """Area under a curve by trapezoids."""
    w = Window.partitionBy(*by).orderBy(x)
    piece = (F.col(x) - F.lag(x).over(w)) * (F.col(y) + F.lag(y).over(w)) / 2
    return curve.withColumn("__p", piece).groupBy(*by).agg(F.sum("__p").alias("auc"))


def budget_for_error(curve: DataFrame, by: list[str], target: float, x: str = "budget", y: str = "error") -> DataFrame:
    """Least budget at which the curve, linear between points, comes down to a target."""
    w = Window.partitionBy(*by).orderBy(x)
    held = curve.withColumn("__x", F.lag(x).over(w)).withColumn("__y", F.lag(y).over(w))
    at = F.when(F.col("__y").isNull() | (F.col("__y") <= target), F.col(x)).otherwise(F.col("__x") + (F.col("__y") - target) / (F.col("__y") - F.col(y)) * (F.col(x) - F.col("__x")))
    return held.where(F.col(y) <= target).groupBy(*by).agg(F.min(at).alias("budget"))


def reduction(curve: DataFrame, method: str, against: str, target: float) -> DataFrame:
    """How many times less a method reads than another for the same error."""
    need = budget_for_error(curve, ["method"], target)
    return need.agg((F.max(F.when(F.col("method") == against, F.col("budget"))) / F.max(F.when(F.col("method") == method, F.col("budget")))).alias("reduction"))


def error_ratio(curve: DataFrame, method: str, budget: float) -> DataFrame:
    """Every method's error over one method's, at a budget."""
    at = curve.where(F.abs(F.col("budget") - budget) < 1e-9)
    base = at.where(F.col("method") == method).select(F.col("error").alias("__b"))
    return at.crossJoin(F.broadcast(base)).select("method", (F.col("error") / F.col("__b")).alias("ratio"))


def read_fraction(sizes: DataFrame, selection: DataFrame) -> DataFrame:
    """Shares of partitions and rows read. ``sizes`` has part_id and n_rows."""
    held = sizes.join(F.broadcast(selection.select("part_id", F.lit(1).alias("__in"))), "part_id", "left")
    return held.agg((F.count("__in") / F.count(F.lit(1))).alias("parts_read"), (F.sum(F.when(F.col("__in") == 1, F.col("n_rows")).otherwise(0)) / F.sum("n_rows")).alias("rows_read"))


def filter_quality(stats: DataFrame, matches: DataFrame) -> DataFrame:
    """Precision and recall of ``sel_upper > 0`` against partitions with matching rows."""
    held = stats.select("part_id", (F.col("sel_upper") > 0).alias("kept")).join(matches.select("part_id", F.lit(True).alias("has")), "part_id", "left").fillna(False, ["has"])
    both = F.sum((F.col("kept") & F.col("has")).cast("int"))
    return held.agg((both / F.sum(F.col("kept").cast("int"))).alias("filter_precision"), (both / F.sum(F.col("has").cast("int"))).alias("filter_recall"))


def error_by_band(errors: DataFrame) -> DataFrame:
    """Mean error by true selectivity: below 0.2, up to 0.8, above."""
    band = F.when(F.col("selectivity") < 0.2, "low").when(F.col("selectivity") <= 0.8, "mid").otherwise("high")
    return errors.groupBy(band.alias("band")).agg(F.avg("error").alias("error"), F.count(F.lit(1)).alias("queries"))


def spread(errors: DataFrame) -> DataFrame:
    """Mean, best and worst error over a template's instances."""
    return errors.groupBy("template").agg(F.avg("error").alias("mean_error"), F.min("error").alias("best"), F.max("error").alias("worst"))


def contribution(parts: DataFrame, keys: list[str], aggs: list[str], variant: str = "max_rel") -> DataFrame:
    """A partition's weight in the answer, from per-partition partial answers.

    Relative variants use the share of each group's total; absolute ones the value itself. The
    largest or the mean over groups and aggregates is taken; a zero total gives zero.
    """
    how, kind = variant.split("_")
    totals = parts.groupBy(*keys).agg(*[F.sum(a).alias(f"__{a}") for a in aggs])
    if keys:
        right = totals.select(*[F.col(k).alias(f"__{k}") for k in keys], *[f"__{a}" for a in aggs])
        on = F.lit(True)
        for k in keys:
            on = on & F.col(k).eqNullSafe(F.col(f"__{k}"))
        held = parts.join(right, on)
    else:
        held = parts.crossJoin(F.broadcast(totals))
    each = [F.when(F.col(f"__{a}") != 0, F.col(a) / F.col(f"__{a}")).otherwise(0.0) if kind == "rel" else F.abs(F.col(a)) for a in aggs]
    if how == "max":
        best = F.greatest(*each) if len(each) > 1 else each[0]
        return held.groupBy("part_id").agg(F.greatest(F.max(best), F.lit(0.0)).alias("contribution"))
    total = each[0]
    for x in each[1:]:
        total = total + x
    return held.groupBy("part_id").agg(F.greatest(F.avg(total / len(aggs)), F.lit(0.0)).alias("contribution"))


def cutoff_fractions(first: float, k: int = 4, top: float = 0.01) -> list[float]:
    """Shares of partitions that the k models look for, falling geometrically from the contributing ones to the top."""
    if first <= top or k == 1:
        return [first] * k
    return [first * (top / first) ** (i / (k - 1)) for i in range(k)]


def bias_variance(values: DataFrame) -> DataFrame:
    """Closed forms for a random exemplar with fixed clusters: expectation and variance of the estimated total."""
    by = values.groupBy("cluster").agg(F.count(F.lit(1)).alias("s"), F.avg("x").alias("m"), F.sum(F.col("x") * F.col("x")).alias("q"))
    return by.agg(F.sum(F.col("s") * F.col("m")).alias("expected"), F.sum(F.col("s") * (F.col("q") - F.col("s") * F.col("m") * F.col("m"))).alias("variance"))
