"""SQL in, weighted answer out: the whole query-time path behind one call."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.operators.execute import weighted_aggregate
from coarsesample.operators.picker import select_full
from coarsesample.plans.query import exact, parse_sql, validate
from coarsesample.plans.training import Prepared


def distinct_estimates(p: Prepared) -> dict[str, float]:
    """Distinct values of each sketched column in a typical partition."""
    cols = [*p.w.cfg.numeric, *p.w.cfg.strings]
    row = p.stats.agg(*[F.percentile_approx(f"{c}__ndv", 0.5).alias(c) for c in cols]).first()
    return {c: float(row[c] or 1) for c in cols}


def weighted_sql(p: Prepared, text: str, budget: float) -> DataFrame:
    """Answer a restricted SELECT over a prepared view by reading a share ``budget`` of its partitions.

    Planning reads statistics only. A full budget runs the exact query; queries out of scope raise
    ValueError; a predicate that no partition can match gives the empty (or zero) answer.
    """
    _, q = parse_sql(text)
    distinct = distinct_estimates(p)
    why = validate(q, distinct)
    if why:
        raise ValueError("; ".join(why))
    if budget >= 1:
        return exact(p.df, q)
    rows_per_part = max(1.0, float(p.stats.agg(F.sum("n_rows")).first()[0] or 0) / max(1, len(p.parts)))
    groups = 1.0
    for c in q.group_by:
        groups *= distinct.get(c, 1.0)
    sel = p.selectivities([q])[0]
    n = max(1, round(budget * len(p.parts)))
    chosen = select_full(p.candidates(q, sel), n, p.models, near_unique=min(groups, rows_per_part) > rows_per_part / 2)
    return weighted_aggregate(p.scan(chosen), q)
