"""Predicates: rewriting, parsing, scope."""

import random

import pytest

from coarsesample.plans.query import And, Clause, In, Intervals, Like, Not, Or, QuerySpec, Agg, columns_of, normalize, parse_predicate, parse_sql, to_sql, validate


def holds(p, row) -> bool:
    match p:
        case Clause(c, op, v):
            x = row[c]
            return {"=": x == v, "<>": x != v, "<": x < v, "<=": x <= v, ">": x > v, ">=": x >= v}[op]
        case In(c, vs, neg):
            return (row[c] in vs) != neg
        case Intervals(c, spans):
            return any((row[c] > a if ao else row[c] >= a) and (row[c] < b if bo else row[c] <= b) for a, ao, b, bo in spans)
        case And(of):
            return all(holds(x, row) for x in of)
        case Or(of):
            return any(holds(x, row) for x in of)
        case Not(of):
            return not holds(of, row)


def random_predicate(rng, depth=3):
    if depth == 0 or rng.random() < 0.4:
        if rng.random() < 0.3:
            return In("s", tuple(rng.sample("abcd", 2)), rng.random() < 0.5)
        if rng.random() < 0.2:
            return In("x", tuple(float(v) for v in rng.sample(range(6), 2)), rng.random() < 0.5)
        return Clause(rng.choice("xy"), rng.choice(["=", "<>", "<", "<=", ">", ">="]), float(rng.randint(0, 5)))
    kind = rng.choice(["and", "or", "not"])
    if kind == "not":
        return Not(random_predicate(rng, depth - 1))
    return (And if kind == "and" else Or)(tuple(random_predicate(rng, depth - 1) for _ in range(rng.randint(1, 3))))


def test_normalize_keeps_meaning():
    rng = random.Random(1)
    rows = [{"x": float(x), "y": float(y), "s": s} for x in range(-1, 7) for y in range(0, 6, 2) for s in "abe"]
    for _ in range(400):
        p = random_predicate(rng)
        n = normalize(p)
        assert [holds(p, r) for r in rows] == [holds(n, r) for r in rows], to_sql(p)


def test_same_column_is_one_clause():
    p = normalize(Or((Clause("x", "<", 1.0), Clause("x", ">", 10.0))))
    assert isinstance(p, Intervals) and len(p.spans) == 2
    assert normalize(And((Clause("x", "<", 1.0), Clause("x", ">", 10.0)))).spans == ()


def test_parser_round_trip():
    table, q = parse_sql("select g, sum(x) as s, count(*) as n from t where not (a between 1 and 3 or b in ('u','v')) and c like 'z%' group by g")
    assert table == "t" and q.group_by == ("g",) and [a.fn for a in q.aggs] == ["sum", "count"]
    assert columns_of(q.where) == {"a", "b", "c"}
    assert parse_predicate(to_sql(q.where)) == q.where


@pytest.mark.parametrize("text", ["select max(x) from t", "select x from t", "select sum(x) from t where a < b", "select sum(x) from a, b"])
def test_out_of_scope(text):
    with pytest.raises(ValueError):
        parse_sql(text)


def test_validate():
    assert validate(QuerySpec((Agg("max", "x", "m"),)))
    assert validate(QuerySpec((Agg("sum", "x", "s"),), None, ("k",)), {"k": 1e9})
    assert not validate(QuerySpec((Agg("sum", "x", "s"),), Like("a", "b%"), ("k",)), {"k": 10})
