"""The query description: aggregates, a predicate tree and group-by columns; its forms as Spark and SQL.

Predicates are immutable trees, so a query can be hashed, compared between workloads and rewritten.
normalize() pushes negations to the leaves and gathers a node's leaves on one column into one leaf: an
interval set for numbers, a value set or excluded set for strings.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

INF = float("inf")


@dataclass(frozen=True)
class Clause:
    """column op constant, with op one of = <> < <= > >=."""

    col: str
    op: str
    value: float | str


@dataclass(frozen=True)
class In:
    col: str
    values: tuple
    negated: bool = False


@dataclass(frozen=True)
class Like:
    col: str
    pattern: str
    negated: bool = False


@dataclass(frozen=True)
class And:
    of: tuple


@dataclass(frozen=True)
class Or:
    of: tuple


@dataclass(frozen=True)
class Not:
    of: object


@dataclass(frozen=True)
class Intervals:
    """Numbers in a union of disjoint intervals (low, low is open, high, high is open)."""

    col: str
    spans: tuple


@dataclass(frozen=True)
class Agg:
    """sum, count or avg of an SQL expression, of the rows where ``where`` holds."""

    fn: str
    expr: str
    alias: str
    where: object = None


@dataclass(frozen=True)
class QuerySpec:
    aggs: tuple
    where: object = None
    group_by: tuple = ()


def literal(value) -> str:
    return "'" + str(value).replace("'", "''") + "'" if isinstance(value, str) else repr(value)


def to_sql(p) -> str:
    """Predicate text that Spark and DuckDB both read."""
    match p:
        case None:
            return "TRUE"
        case Clause(c, op, v):
            return f"{c} {op} {literal(v)}"
        case In(c, vs, neg):
            return f"{c} {'NOT ' if neg else ''}IN ({', '.join(map(literal, vs))})"
        case Like(c, pat, neg):
            return f"{c} {'NOT ' if neg else ''}LIKE {literal(pat)}"
        case And(of):
            return "(" + " AND ".join(map(to_sql, of)) + ")" if of else "TRUE"
        case Or(of):
            return "(" + " OR ".join(map(to_sql, of)) + ")" if of else "FALSE"
        case Not(of):
            return f"NOT ({to_sql(of)})"
        case Intervals(c, spans):
            one = lambda s: " AND ".join([f"{c} {'>' if s[1] else '>='} {s[0]!r}"] * (s[0] > -INF) + [f"{c} {'<' if s[3] else '<='} {s[2]!r}"] * (s[2] < INF)) or f"{c} IS NOT NULL"
            return "(" + " OR ".join(f"({one(s)})" for s in spans) + ")" if spans else "FALSE"
    raise TypeError(p)


def columns_of(p) -> set[str]:
    match p:
        case None:
            return set()
        case And(of) | Or(of):
            return set().union(*map(columns_of, of))
        case Not(of):
            return columns_of(of)
    return {p.col}


def query_columns(q: QuerySpec, known: set[str]) -> set[str]:
    """Columns a query uses, out of those known."""
    words = set(re.findall(r"[A-Za-z_]\w*", " ".join(a.expr for a in q.aggs)))
    return ((words | columns_of(q.where) | set().union(*(columns_of(a.where) for a in q.aggs))) & known) | (set(q.group_by) & known)


FLIP = {"=": "<>", "<>": "=", "<": ">=", ">=": "<", ">": "<=", "<=": ">"}


def push_negation(p, negate: bool = False):
    """No Not is left; operators flip."""
    match p:
        case Not(of):
            return push_negation(of, not negate)
        case And(of) | Or(of):
            kind = (Or if isinstance(p, And) else And) if negate else type(p)
            return kind(tuple(push_negation(x, negate) for x in of))
    if not negate:
        return p
    if isinstance(p, Clause):
        return replace(p, op=FLIP[p.op])
    if isinstance(p, In | Like):
        return replace(p, negated=not p.negated)
    return Intervals(p.col, _complement(p.spans))


def _complement(spans: tuple) -> tuple:
    out, low, low_open = [], -INF, True
    for a, ao, b, bo in spans:
        if a > low or (a == low and ao and not low_open):
            out.append((low, low_open, a, not ao))
        low, low_open = b, not bo
    if low < INF:
        out.append((low, low_open, INF, True))
    return tuple(out)


def _united(spans: list[tuple]) -> tuple:
    out: list[tuple] = []
    for s in sorted(spans, key=lambda s: (s[0], s[1])):
        if out and (s[0] < out[-1][2] or (s[0] == out[-1][2] and not (s[1] and out[-1][3]))):
            a, ao, b, bo = out[-1]
            if s[2] > b or (s[2] == b and bo and not s[3]):
                out[-1] = (a, ao, s[2], s[3])
        else:
            out.append(s)
    return tuple(out)


def _as_intervals(p) -> Intervals | None:
    """Numeric leaves as interval sets; None for what is no numeric leaf."""
    if isinstance(p, Intervals):
        return p
    if isinstance(p, Clause) and not isinstance(p.value, str):
        v = float(p.value)
        spans = {"=": ((v, False, v, False),), "<": ((-INF, True, v, True),), "<=": ((-INF, True, v, False),), ">": ((v, True, INF, True),), ">=": ((v, False, INF, True),)}
        return Intervals(p.col, spans[p.op] if p.op != "<>" else _complement(spans["="]))
    if isinstance(p, In) and p.values and not any(isinstance(v, str) for v in p.values):
        spans = _united([(float(v), False, float(v), False) for v in p.values])
        return Intervals(p.col, _complement(spans) if p.negated else spans)
    return None


def _as_set(p) -> In | None:
    if isinstance(p, In):
        return p
    if isinstance(p, Clause) and isinstance(p.value, str) and p.op in ("=", "<>"):
        return In(p.col, (p.value,), p.op == "<>")
    return None


def _merge_sets(a: In, b: In, both: bool) -> In:
    """One leaf for two value sets under AND (both) or OR."""
    x, y = set(a.values), set(b.values)
    if not both:
        m = _merge_sets(replace(a, negated=not a.negated), replace(b, negated=not b.negated), True)
        return replace(m, negated=not m.negated)
    if not a.negated and not b.negated:
        return In(a.col, tuple(sorted(x & y)))
    if a.negated and b.negated:
        return In(a.col, tuple(sorted(x | y)), True)
    keep, out = (x, y) if b.negated else (y, x)
    return In(a.col, tuple(sorted(keep - out)))


def normalize(p):
    """Negations at the leaves, nested equal nodes flattened, one leaf for each column of a node."""
    return _gather(push_negation(p)) if p is not None else None


def _gather(p):
    if not isinstance(p, And | Or):
        return _as_intervals(p) or _as_set(p) or p
    flat: list = []
    for x in map(_gather, p.of):
        flat.extend(x.of if type(x) is type(p) else (x,))
    numbers: dict[str, Intervals] = {}
    sets: dict[str, In] = {}
    rest = []
    for x in flat:
        if isinstance(x, Intervals):
            held = numbers.get(x.col)
            if held is None:
                numbers[x.col] = x
            elif isinstance(p, Or):
                numbers[x.col] = Intervals(x.col, _united([*held.spans, *x.spans]))
            else:
                numbers[x.col] = Intervals(x.col, _complement(_united([*_complement(held.spans), *_complement(x.spans)])))
        elif isinstance(x, In):
            sets[x.col] = _merge_sets(sets[x.col], x, isinstance(p, And)) if x.col in sets else x
        else:
            rest.append(x)
    out = (*numbers.values(), *sets.values(), *rest)
    return out[0] if len(out) == 1 else type(p)(out)


def validate(q: QuerySpec, distinct: dict[str, float] | None = None, rows: float = INF, most_groups: float = 10_000) -> list[str]:
    """Why a query is outside the scope; an empty list if it is inside."""
    why = [f"aggregate {a.fn} is not supported" for a in q.aggs if a.fn not in ("sum", "count", "avg")]
    if not q.aggs:
        why.append("no aggregate")
    if len(q.group_by) > 8:
        why.append("more than eight group-by columns")
    if distinct:
        groups = reduce(lambda x, c: x * distinct.get(c, 1), q.group_by, 1.0)
        if min(groups, rows) > most_groups:
            why.append("group-by columns have too many values")
    return why


def parts_of(q: QuerySpec) -> list[tuple[str, str, str, Column]]:
    """Additive parts: (aggregate's alias, part, fn, column). An average is a sum and a count."""
    out = []
    for a in q.aggs:
        x = F.lit(1) if a.expr == "*" else F.expr(a.expr)
        x = x if a.where is None else F.when(F.expr(to_sql(a.where)), x)
        total = F.coalesce(F.sum(x.cast("double")), F.lit(0.0))
        if a.fn == "sum":
            out.append((a.alias, f"{a.alias}__s", "sum", total))
        elif a.fn == "count":
            out.append((a.alias, f"{a.alias}__s", "count", F.count(x).cast("double")))
        else:
            out += [(a.alias, f"{a.alias}__s", "sum", total), (a.alias, f"{a.alias}__c", "count", F.count(x).cast("double"))]
    return out


def finish(q: QuerySpec, df: DataFrame) -> DataFrame:
    """Answers from summed parts."""
    out = []
    for a in q.aggs:
        s = F.col(f"{a.alias}__s")
        out.append((s / F.when(F.col(f"{a.alias}__c") != 0, F.col(f"{a.alias}__c")) if a.fn == "avg" else s).alias(a.alias))
    return df.select(*q.group_by, *out)


def partials(df: DataFrame, q: QuerySpec) -> DataFrame:
    """Per-partition answers in parts: one scan, one partial aggregation."""
    given = df if q.where is None else df.where(to_sql(q.where))
    return given.groupBy("part_id", *q.group_by).agg(*[c.alias(n) for _, n, _, c in parts_of(q)])


def exact(df: DataFrame, q: QuerySpec) -> DataFrame:
    """The whole table's answer."""
    given = df if q.where is None else df.where(to_sql(q.where))
    return finish(q, given.groupBy(*q.group_by).agg(*[c.alias(n) for _, n, _, c in parts_of(q)]))


def estimate(parts: DataFrame, q: QuerySpec, selection: DataFrame) -> DataFrame:
    """Answers from cached per-partition parts and a selection (part_id, weight); no rescan."""
    held = parts.join(F.broadcast(selection.select("part_id", "weight")), "part_id")
    names = [n for _, n, _, _ in parts_of(q)]
    return finish(q, held.groupBy(*q.group_by).agg(*[F.sum(F.col(n) * F.col("weight")).alias(n) for n in names]))


_SELECT = re.compile(r"^\s*select\s+(?P<out>.+?)\s+from\s+(?P<table>\w+)(?:\s+where\s+(?P<where>.+?))?(?:\s+group\s+by\s+(?P<group>.+?))?\s*;?\s*$", re.I | re.S)
_AGG = re.compile(r"^(sum|count|avg|min|max)\s*\((.+)\)(?:\s+as\s+(\w+))?$", re.I | re.S)
_TOKEN = re.compile(r"\s*(?:(?P<num>-?\d+(?:\.\d+)?)|(?P<str>'(?:[^']|'')*')|(?P<op><=|>=|<>|!=|=|<|>)|(?P<punct>[(),])|(?P<word>[A-Za-z_]\w*))")


def _split(text: str) -> list[str]:
    """Parts at commas outside of parentheses."""
    out, depth, last = [], 0, 0
    for i, ch in enumerate(text):
        depth += (ch == "(") - (ch == ")")
        if ch == "," and not depth:
            out.append(text[last:i])
            last = i + 1
    return [x.strip() for x in [*out, text[last:]]]


def parse_sql(text: str) -> tuple[str, QuerySpec]:
    """A restricted SELECT as table name and query; raises ValueError for what is out of scope."""
    m = _SELECT.match(text)
    if not m:
        raise ValueError("only SELECT aggregates FROM one table [WHERE ...] [GROUP BY ...]")
    groups = tuple(_split(m["group"])) if m["group"] else ()
    aggs = []
    for i, part in enumerate(_split(m["out"])):
        a = _AGG.match(part)
        if a:
            if a[1].lower() in ("min", "max"):
                raise ValueError(f"{a[1]} is not supported")
            aggs.append(Agg(a[1].lower(), a[2].strip(), a[3] or f"a{i}"))
        elif part not in groups:
            raise ValueError(f"{part} is neither an aggregate nor grouped")
    return m["table"], QuerySpec(tuple(aggs), parse_predicate(m["where"]) if m["where"] else None, groups)


def parse_predicate(text: str):
    """A predicate from text, by recursive descent."""
    tokens, at = [], 0
    while at < len(text.rstrip()):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"can't read {text[at:at + 20]!r}")
        tokens.append((m.lastgroup, m[m.lastgroup]))
        at = m.end()
    pos = 0

    def peek() -> str:
        return tokens[pos][1].upper() if pos < len(tokens) else ""

    def take(*wanted: str) -> str:
        nonlocal pos
        if pos >= len(tokens) or (wanted and peek() not in wanted):
            raise ValueError(f"expected {wanted or 'more'}, got {peek()!r}")
        pos += 1
        return tokens[pos - 1][1]

    def constant():
        kind = tokens[pos][0] if pos < len(tokens) else ""
        if kind not in ("num", "str"):
            raise ValueError("a clause compares one column with a constant")
        value = take()
        return value[1:-1].replace("''", "'") if kind == "str" else float(value)

    def leaf():
        if peek() == "NOT":
            take()
            return Not(leaf())
        if peek() == "(":
            take()
            inner = either()
            take(")")
            return inner
        col = take()
        negated = peek() == "NOT"
        if negated:
            take()
        if peek() == "IN":
            take()
            take("(")
            values = [constant()]
            while peek() == ",":
                take()
                values.append(constant())
            take(")")
            return In(col, tuple(values), negated)
        if peek() == "LIKE":
            take()
            return Like(col, constant(), negated)
        if peek() == "BETWEEN":
            take()
            low = constant()
            take("AND")
            span = And((Clause(col, ">=", low), Clause(col, "<=", constant())))
            return Not(span) if negated else span
        op = take("=", "<>", "!=", "<", "<=", ">", ">=")
        return Clause(col, "<>" if op == "!=" else op, constant())

    def chain(word: str, kind, below):
        parts = [below()]
        while peek() == word:
            take()
            parts.append(below())
        return parts[0] if len(parts) == 1 else kind(tuple(parts))

    def both():
        return chain("AND", And, leaf)

    def either():
        return chain("OR", Or, both)

    out = either()
    if pos != len(tokens):
        raise ValueError(f"unexpected {peek()!r}")
    return out
