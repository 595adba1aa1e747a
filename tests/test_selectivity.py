"""The filter's bound never loses a matching partition; the four features by hand."""

import random

import pytest
from pyspark.sql import functions as F

from coarsesample.operators import features as X
from coarsesample.operators.selectivity import filter_by_predicate, four_features, with_selectivity
from coarsesample.plans.query import And, Clause, In, Like, Or, to_sql
from test_query import random_predicate

CFG = X.TableConfig(("x", "y"), ("s",), ("s",))


@pytest.mark.parametrize("build", [X.partition_stats, X.partition_stats_onepass])
def test_recall_is_perfect(spark, build):
    rng = random.Random(5)
    rows = []
    for part in range(25):
        lo = rng.randint(0, 4)
        for _ in range(rng.randint(1, 30)):
            rows.append((part, None if rng.random() < 0.1 else float(rng.randint(lo, min(5, lo + 2))), rng.random() * 5, None if rng.random() < 0.1 else rng.choice("abcd"[: 1 + part % 4])))
    df = spark.createDataFrame(rows, "part_id int, x double, y double, s string").cache()
    stats = build(df, CFG).cache()
    preds = [random_predicate(rng) for _ in range(60)] + [Like("s", "a%"), Like("s", "a%", True)]
    kept = stats.select("part_id", *[four_features(p)["sel_upper"].alias(f"u{i}") for i, p in enumerate(preds)]).collect()
    true = df.groupBy("part_id").agg(*[F.count(F.when(F.expr(to_sql(p)), 1)).alias(f"u{i}") for i, p in enumerate(preds)]).collect()
    have = {r["part_id"]: r for r in true}
    for r in kept:
        for i, p in enumerate(preds):
            if have[r["part_id"]][f"u{i}"] > 0:
                assert r[f"u{i}"] > 0, to_sql(p)


def test_four_features_by_hand(spark):
    rows = [(1, float(i), float(i % 2), "ab"[i % 2]) for i in range(10)]
    stats = X.partition_stats(spark.createDataFrame(rows, "part_id int, x double, y double, s string"), CFG)
    a, b = Clause("x", "<", 2.0), In("s", ("a",))
    both = with_selectivity(stats, And((a, b))).first()
    assert (round(both["sel_upper"], 6), round(both["sel_indep"], 6), both["sel_min"], both["sel_max"]) == (0.2, 0.1, 0.2, 0.5)
    either = with_selectivity(stats, Or((a, b))).first()
    assert (round(either["sel_upper"], 6), round(either["sel_indep"], 6)) == (0.7, 0.2)
    assert round(with_selectivity(stats, Or((a, b)), "complement").first()["sel_indep"], 6) == 0.6
    assert with_selectivity(stats, None).first()["sel_upper"] == 1.0
    assert filter_by_predicate(with_selectivity(stats, Clause("x", ">", 100.0))).count() == 0


def test_schema_is_fixed_and_masked():
    from coarsesample.plans.query import Agg, QuerySpec

    schema = X.FeatureSchema.of(CFG)
    q = QuerySpec((Agg("sum", "x", "s1"),), None, ())
    used = schema.used(q, CFG)
    assert len(used) == len(schema)
    assert all(u == 0 for u, c in zip(used, schema.cols) if c in ("y", "s"))
    assert all(u == 1 for u, k in zip(used, schema.kinds) if k == "selectivity")


def test_driver_folding_equals_expressions(spark):
    import numpy as np

    from coarsesample.plans.experiments import trained
    from conftest import TINY

    p, queries, _, sels, _ = trained(spark, TINY, "events", "user")
    for q, s in list(zip(queries, sels))[:6]:
        rows = with_selectivity(p.stats, q.where).orderBy("part_id").select("sel_upper", "sel_indep", "sel_min", "sel_max").toPandas().to_numpy(float)
        assert np.allclose(np.nan_to_num(rows), s, atol=1e-9)


def test_features_of_both_builders_agree(spark):
    rows = [(p, float(i % (5 + p)), float(i), "abc"[i % 3]) for p in range(3) for i in range(60)]
    df = spark.createDataFrame(rows, "part_id int, x double, y double, s string")
    out = []
    for build in (X.partition_stats, X.partition_stats_onepass):
        st = build(df, CFG).cache()
        out.append({r["part_id"]: r["f"] for r in X.static_features(st, CFG, X.global_items(st, CFG)).collect()})
    names = X.FeatureSchema.of(CFG).names
    for p in range(3):
        for n, a, b in zip(names, out[0][p], out[1][p]):
            if n.split("__")[-1] not in ("freq_min",):
                assert abs(a - b) <= 0.06 * max(1, abs(a)), n


@pytest.mark.parametrize("build", [X.partition_stats, X.partition_stats_onepass])
def test_partitions_without_values_stay(spark, build):
    rows = [(0, 1.0, 2.0, "a"), (1, None, None, None), (1, None, None, None), (2, 3.0, None, None), (3, None, 1.0, "b")]
    df = spark.createDataFrame(rows, "part_id int, x double, y double, s string")
    stats = build(df, CFG)
    assert sorted(r["part_id"] for r in stats.collect()) == [0, 1, 2, 3]
    for p in (Clause("x", ">", 2.0), Clause("y", "<", 5.0), In("s", ("a",)), Like("s", "b%")):
        kept = {r["part_id"] for r in filter_by_predicate(with_selectivity(stats, p)).collect()}
        true = {r["part_id"] for r in df.where(to_sql(p)).collect()}
        assert true <= kept
    assert X.static_features(stats, CFG, X.global_items(stats, CFG)).count() == 4


@pytest.mark.parametrize("build", [X.partition_stats, X.partition_stats_onepass])
def test_arrays_say_what_expressions_say(spark, build):
    import numpy as np

    from coarsesample.operators.selectivity import ColumnArrays, bounds, leaves_of
    from coarsesample.plans.query import normalize

    rng = random.Random(8)
    rows = [(p, None if rng.random() < 0.1 else float(rng.randint(0, 30)), rng.random(), None if p == 4 or rng.random() < 0.1 else rng.choice(["ab", "bc", "c_%"])) for p in range(12) for _ in range(rng.randint(1, 60))]
    df = spark.createDataFrame([*rows, (12, None, None, None)], "part_id int, x double, y double, s string")
    stats = build(df, CFG).cache()
    preds = [Clause("x", o, v) for o in ("<", "<=", ">", ">=", "=", "<>") for v in (0.0, 7.0, 7.5, 30.0, 99.0)] + [In("s", ("ab", "zz")), In("s", ("ab",), True), Like("s", "%b%"), Like("s", "b_"), Like("s", "c%", True), Like("s", "c\\_\\%")]
    leaves = list(dict.fromkeys(x for p in preds for x in leaves_of(normalize(p))))
    parts = np.arange(13)
    want = stats.select("part_id", *[e.cast("double").alias(f"{n}{i}") for i, x in enumerate(leaves) for n, e in zip("gm", bounds(x)[1:])]).toPandas().set_index("part_id").loc[parts]
    arrays = {c: ColumnArrays(stats, c, parts) for c in ("x", "s")}
    for i, x in enumerate(leaves):
        guess, most = arrays[x.col].bounds(x)
        assert np.nan_to_num(guess) == pytest.approx(np.nan_to_num(want[f"g{i}"].to_numpy(float))), x
        assert np.nan_to_num(most) == pytest.approx(np.nan_to_num(want[f"m{i}"].to_numpy(float))), x


@pytest.mark.parametrize("dealt", [False, True])
def test_runs_say_what_exact_counts_say(spark, dealt):
    """Statistics of rows that lie by partition, also where that turns out not to be so, without the sketches' aggregation."""
    rng = random.Random(4)
    rows = [(p, None if p == 3 or rng.random() < 0.1 else float(rng.randint(p == 2, 9) or -0.0), 1.0 + rng.random(), None if p == 4 else rng.choice(["a", "é", ""])) for p in range(6) for _ in range(40)]
    df = spark.createDataFrame(rows, "part_id int, x double, y double, s string").coalesce(1)
    got = X.partition_stats_onepass(df.repartition(3) if dealt else df, CFG, whole=True)
    want = X.partition_stats(df, CFG).cache()
    items = X.global_items(want, CFG)
    each = [{r["part_id"]: dict(zip(X.FeatureSchema.of(CFG).names, r["f"])) for r in X.static_features(t, CFG, items).collect()} for t in (got, want)]
    assert sorted(each[0]) == sorted(each[1]) == list(range(6))
    for p, named in each[1].items():
        for n, v in named.items():
            if not n.endswith("freq_min"):
                assert each[0][p][n] == pytest.approx(v, abs=1e-9), (p, n)
    held = [{r["part_id"]: sorted((e["value"], e["n"]) for e in r["s__dict"] or ()) for r in t.select("part_id", "s__dict").collect()} for t in (got, want)]
    assert held[0] == held[1]
