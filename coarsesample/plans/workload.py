"""Workloads: configurations of the views, a random query generator, and benchmark-like templates."""

from __future__ import annotations

import random
import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.operators.features import TableConfig
from coarsesample.plans.query import Agg, And, Clause, In, Like, Not, Or, QuerySpec
from coarsesample.sources import layouts, tables


@dataclass(frozen=True)
class Workload:
    """A view, its layouts (sort columns by name) and its columns."""

    name: str
    view: object
    layouts: dict
    cfg: TableConfig
    sums: tuple[str, ...]
    numeric_filters: tuple[str, ...]


_TIE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"]
WORKLOADS = {
    "lineitem": Workload(
        "lineitem",
        tables.lineitem_wide,
        {"shipdate": ["l_shipdate", *_TIE], "price": ["l_extendedprice", *_TIE], "z_part": ["z_part", *_TIE], "random": None},
        TableConfig(
            ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "revenue", "ship_day", "order_day", "ship_year", "order_year", "o_totalprice", "c_acctbal", "s_acctbal", "p_size", "p_retailprice", "z_part", "z_supp", "z_cust"),
            ("l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority", "c_mktsegment", "p_brand", "p_type", "p_name", "cust_nation", "cust_region", "supp_nation", "supp_region", "same_nation"),
            ("l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority", "c_mktsegment", "p_type", "cust_region", "supp_nation", "supp_region", "same_nation", "ship_year", "order_year"),
        ),
        ("l_quantity", "l_extendedprice", "revenue", "o_totalprice"),
        ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "ship_day", "order_day", "order_year", "p_size", "p_retailprice", "z_part", "z_supp", "z_cust"),
    ),
    "orders": Workload(
        "orders",
        tables.orders_wide,
        {"day": ["o_day", "o_orderkey"], "priority": ["o_orderpriority", "o_orderkey"], "totalprice": ["o_totalprice", "o_orderkey"]},
        TableConfig(("o_totalprice", "o_day", "c_acctbal"), ("o_orderstatus", "o_orderpriority", "c_mktsegment", "n_name", "r_name"), ("o_orderstatus", "o_orderpriority", "c_mktsegment", "r_name")),
        ("o_totalprice", "c_acctbal"),
        ("o_totalprice", "o_day", "c_acctbal"),
    ),
    "events": Workload(
        "events",
        tables.events_flat,
        {"user": ["user_id", "event_id"], "ts": ["ts", "event_id"], "value": ["value", "event_id"]},
        TableConfig(("value", "k", "hour", "dow", "user_id", "z_user"), ("event_type",), ("event_type", "z_user")),
        ("value", "k"),
        ("value", "k", "hour", "user_id"),
    ),
    "documents": Workload(
        "documents",
        tables.documents_flat,
        {"n_chars": ["n_chars", "doc_id"], "lang": ["lang", "source", "doc_id"]},
        TableConfig(("n_chars", "n_words", "n_lines", "n_digits", "n_upper", "n_punct", "mean_word_len", "quality", "toxic"), ("lang", "source"), ("lang", "source", "quality")),
        ("n_chars", "n_words", "n_lines"),
        ("n_chars", "n_words", "n_lines", "n_digits", "n_punct", "mean_word_len"),
    ),
    "embeddings": Workload(
        "embeddings",
        lambda s, d: tables.embeddings_wide(s, d),
        {"e0": ["e0", "vec_id"], "label": ["label", "vec_id"]},
        TableConfig(tuple(f"e{i}" for i in range(64)), ("label",), ("label",)),
        ("e0", "e1", "e2"),
        tuple(f"e{i}" for i in range(64)),
    ),
}


def laid_out(spark: SparkSession, sf_dir: str, name: str, layout: str, n_parts: int) -> DataFrame:
    """A workload's view with part_id under one of its layouts."""
    w = WORKLOADS[name]
    view = w.view(spark, sf_dir)
    order = w.layouts[layout]
    if order is None:
        return layouts.assign_random(view, F.col("l_orderkey") * 7 + F.col("l_linenumber"), n_parts)
    return layouts.assign_sorted(view, list(dict.fromkeys(order)), n_parts)


def _pattern(rng: random.Random, value: str) -> str:
    """A LIKE pattern that the value matches: its begin, its end, or a part of it."""
    plain = re.split(r"[%_\\\\]", value)[0]
    n = rng.randint(1, max(1, len(plain)))
    at = rng.randint(0, max(0, len(plain) - n))
    return rng.choice([f"{plain[:n]}%", f"%{plain[at : at + n]}%"]) if plain else "%"


def _tree(rng: random.Random, clauses: list):
    """Clauses as one predicate."""
    if len(clauses) < 2:
        return clauses[0] if clauses else None
    kind = rng.random()
    if kind < 0.2:
        out = Or(tuple(clauses))
    elif kind < 0.35 and len(clauses) > 2:
        out = And((Or(tuple(clauses[:2])), *clauses[2:]))
    else:
        out = And(tuple(clauses))
    return Not(out) if rng.random() < 0.05 else out


def generate(w: Workload, constants: dict[str, list], n: int, seed: int, columnsets: int = 16, most_groups: int = 1000) -> list[QuerySpec]:
    """n different random queries: up to 8 group columns, 0 to 5 clauses, 1 to 3 aggregates.

    ``constants`` holds candidate values by column, from sketches. Group columns come from a pool of
    ``columnsets`` sets, as a workload's do; a set grows as long as its known distinct values multiply
    to ``most_groups`` at most. Clauses are comparisons, sets, patterns, and negations of these; a tree
    is a conjunction, a disjunction, or a disjunction inside a conjunction, now and then negated.
    """
    rng, out, seen = random.Random(seed), [], set()
    strings = [c for c in w.cfg.strings if constants.get(c)]
    pool = [()]
    for _ in range(columnsets - 1):
        cols, groups = [], 1
        for c in rng.sample(w.cfg.groupable, min(len(w.cfg.groupable), rng.randint(1, 8))):
            if groups * max(1, len(constants.get(c, ()))) <= most_groups:
                cols.append(c)
                groups *= max(1, len(constants.get(c, ())))
        pool.append(tuple(sorted(cols)))
    pool = list(dict.fromkeys(pool))
    for _ in range(200 * n):
        if len(out) == n:
            break
        groups = rng.choice(pool)
        clauses = []
        for _ in range(rng.choice([0, 1, 1, 2, 2, 3, 4, 5])):
            if strings and rng.random() < 0.4:
                c = rng.choice(strings)
                values = constants[c]
                kind = rng.random()
                if kind < 0.4:
                    clauses.append(Clause(c, rng.choice(["=", "<>"]), rng.choice(values)))
                elif kind < 0.8:
                    clauses.append(In(c, tuple(sorted(rng.sample(values, min(len(values), rng.randint(1, 3)))))))
                else:
                    clauses.append(Like(c, _pattern(rng, rng.choice(values))))
            else:
                c = rng.choice([x for x in w.numeric_filters if constants.get(x)])
                clauses.append(Clause(c, rng.choice(["<", "<=", ">", ">="]), rng.choice(constants[c])))
            if rng.random() < 0.1:
                clauses[-1] = Not(clauses[-1])
        where = _tree(rng, clauses)
        aggs = [Agg("sum", c, f"sum_{c}") for c in rng.sample(w.sums, rng.randint(1, min(2, len(w.sums))))]
        if rng.random() < 0.6:
            aggs.append(Agg("count", "*", "n"))
        if rng.random() < 0.2:
            aggs.append(Agg("avg", w.sums[0], "mean"))
        q = QuerySpec(tuple(aggs[:3]), where, groups)
        if q not in seen:
            seen.add(q)
            out.append(q)
    return out


def day(text: str) -> int:
    """Days since the epoch of an ISO date."""
    import datetime

    return (datetime.date.fromisoformat(text) - datetime.date(1970, 1, 1)).days


def templates(rng: random.Random | None = None) -> dict[str, QuerySpec]:
    """Benchmark-like queries on the wide line view, one instance each; constants vary with ``rng``."""
    rng = rng or random.Random(0)
    year = rng.choice([1996, 1997, 1998, 1999])
    y0, y1 = float(day(f"{year}-01-01")), float(day(f"{year + 1}-01-01"))
    nations = ["FRANCE", "GERMANY"]
    in_year = And((Clause("ship_day", ">=", y0), Clause("ship_day", "<", y1)))
    rev = Agg("sum", "revenue", "sum_rev")
    return {
        "q01": QuerySpec((Agg("sum", "l_quantity", "sum_qty"), Agg("sum", "l_extendedprice", "sum_price"), rev, Agg("avg", "l_quantity", "avg_qty"), Agg("avg", "l_discount", "avg_disc"), Agg("count", "*", "n")), Clause("ship_day", "<=", float(day("2001-08-01") - rng.randint(0, 90))), ("l_returnflag", "l_linestatus")),
        "q05": QuerySpec((rev,), And((In("cust_region", ("ASIA",)), Clause("order_year", "=", float(year)), Clause("same_nation", "=", "yes"))), ("supp_nation",)),
        "q06": QuerySpec((Agg("sum", "l_extendedprice * l_discount", "sum_disc"),), And((in_year, Clause("l_discount", ">=", 0.05), Clause("l_discount", "<=", 0.07), Clause("l_quantity", "<", 24.0)))),
        "q07": QuerySpec((rev,), And((In("supp_nation", tuple(nations)), In("cust_nation", tuple(nations)), in_year)), ("supp_nation", "cust_nation", "ship_year")),
        "q08": QuerySpec((Agg("sum", "revenue", "nation_rev", Clause("supp_nation", "=", nations[0])), rev), And((In("cust_region", ("EUROPE",)), In("order_year", (1996.0, 1997.0)))), ("order_year",)),
        "q09": QuerySpec((Agg("sum", "revenue - 0.6 * p_retailprice * l_quantity", "profit"),), Like("p_name", "%e%"), ("supp_nation", "order_year")),
        "q12": QuerySpec((Agg("count", "*", "high", In("o_orderpriority", ("1-URGENT", "2-HIGH"))), Agg("count", "*", "low", In("o_orderpriority", ("1-URGENT", "2-HIGH"), True))), And((In("l_returnflag", ("A", "R")), in_year)), ("l_linestatus",)),
        "q14": QuerySpec((Agg("sum", "revenue", "promo", Like("p_type", "PROMO%")), rev), And((Clause("ship_day", ">=", y0), Clause("ship_day", "<", y0 + 30)))),
        "q17": QuerySpec((Agg("sum", "l_extendedprice", "sum_price"), Agg("avg", "l_quantity", "avg_qty")), And((In("p_size", (10.0, 11.0, 12.0)), Clause("l_quantity", "<", 10.0)))),
        "q19": QuerySpec((rev,), Or((And((Clause("p_size", "<=", 5.0), Clause("l_quantity", "<=", 11.0))), And((Clause("p_size", "<=", 10.0), Clause("l_quantity", ">=", 10.0), Clause("l_quantity", "<=", 20.0))), And((Clause("p_size", "<=", 15.0), Clause("l_quantity", ">=", 20.0), Clause("l_quantity", "<=", 30.0)))))),
    }
