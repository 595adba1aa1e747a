"""Worked examples of picking, clustering, budgets and errors."""

import numpy as np
import pytest

from coarsesample.operators import baselines, clustering, metrics, picker
from coarsesample.plans.training import BoostedTrees


@pytest.mark.parametrize("sizes,n,want", [([40, 20, 10], 14, [4, 5, 5]), ([100, 10, 4], 60, [47, 9, 4]), ([5, 5], 20, [5, 5]), ([0, 7], 3, [0, 3]), ([10], 0, [0]), ([50, 1, 1], 3, [1, 1, 1])])
def test_allocate(sizes, n, want):
    assert picker.allocate(sizes, n) == want


def test_allocate_always_fits():
    rng = np.random.default_rng(0)
    for _ in range(300):
        sizes = rng.integers(0, 30, rng.integers(1, 6)).tolist()
        n = int(rng.integers(0, 80))
        out = picker.allocate(sizes, n, float(rng.choice([1, 2, 4])))
        assert sum(out) == min(n, sum(sizes)) and all(0 <= o <= s for o, s in zip(out, sizes))


def test_outlier_rule(spark):
    rows = [(i, 1) for i in range(50)] + [(100 + i, 2) for i in range(9)] + [(200 + i, 3) for i in range(4)]
    found = picker.outlier_groups(spark.createDataFrame(rows, "part_id int, bits long"))
    assert {r["bits"] for r in found.collect()} == {3}
    even = spark.createDataFrame([(i, i // 10) for i in range(1000)], "part_id int, bits long")
    assert picker.outlier_groups(even).count() == 0


@pytest.mark.parametrize("algo", ["kmeans", "hac_ward", "hac_single"])
def test_clusters_of_separate_points(algo):
    x = np.array([[0.0, 0], [0.1, 0], [10, 10], [10.1, 10], [20, 0], [20.1, 0.1]])
    label = clustering.ALGORITHMS[algo](x, 3, seed=1)
    assert label[0] == label[1] and label[2] == label[3] and label[4] == label[5] and len(set(label)) == 3
    picks = clustering.cluster_sample(np.arange(6), x, 3, algo)
    assert sum(w for _, w, _ in picks) == 6 and len(picks) == 3


def test_ward_matches_brute_force():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(14, 2))
    groups = [[i] for i in range(14)]
    cost = lambda g: ((x[g] - x[g].mean(0)) ** 2).sum()
    while len(groups) > 4:
        a, b = min(((i, j) for i in range(len(groups)) for j in range(i)), key=lambda p: cost(groups[p[0]] + groups[p[1]]) - cost(groups[p[0]]) - cost(groups[p[1]]))
        groups[b] += groups.pop(a)
    label = clustering.ward(x, 4)
    assert {frozenset(g) for g in groups} == {frozenset(np.flatnonzero(label == k).tolist()) for k in set(label)}


def test_repeated_points_share_weight():
    picks = clustering.cluster_sample(np.arange(10), np.zeros((10, 3)), 4)
    assert len(picks) == 4 and sum(w for _, w, _ in picks) == pytest.approx(10)


def test_identical_partitions_are_exact():
    x = np.repeat(np.eye(3), 5, axis=0)
    value = np.repeat([1.0, 5.0, 9.0], 5)
    picks = clustering.cluster_sample(np.arange(15), x, 3)
    assert sum(w * value[p] for p, w, _ in picks) == pytest.approx(value.sum())


def test_full_budget_reads_everything():
    c = picker.Candidates(np.arange(8), np.random.rand(8, 2), [None] * 8, np.ones(8), np.ones(8), np.random.rand(8, 2))
    rows = picker.select_full(c, 8)
    assert sorted(r[0] for r in rows) == list(range(8)) and all(r[1] == 1 for r in rows)
    assert picker.select_full(c, 0) == []


def test_weights_cover_candidates():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(60, 3))
    c = picker.Candidates(np.arange(60), x, [(1,)] * 57 + [(2,)] * 3, (np.arange(60) % 5 > 0).astype(float), np.ones(60), x)
    rows = picker.select_full(c, 15, [lambda r: r[:, 0], lambda r: r[:, 1]], outlier_share=0.3)
    assert len(rows) == 15 and sum(r[1] for r in rows) == pytest.approx(48)
    assert all(r[0] % 5 for r in rows)


def test_funnel_stops_at_first_failure():
    assert picker.importance_levels([np.array([1, 1, -1.0]), np.array([1, -1, 1.0]), np.array([-1, 1, 1.0])]).tolist() == [2, 1, 0]


def test_error_measures(spark):
    true = spark.createDataFrame([("a", 100.0), ("b", 10.0), ("c", 1.0)], "g string, v double")
    est = spark.createDataFrame([("a", 110.0), ("b", 10.0)], "g string, v double")
    assert metrics.missed_groups(true, est, ["g"]).first()[0] == pytest.approx(1 / 3)
    assert metrics.avg_rel_error(true, est, ["g"], ["v"]).first()[0] == pytest.approx(1.1 / 3)
    assert metrics.abs_error_over_true(true, est, ["g"], ["v"]).first()[0] == pytest.approx(11 / 111)


def test_null_groups_meet(spark):
    t = spark.createDataFrame([(None, 4.0), ("a", 2.0)], "g string, v double")
    assert metrics.avg_rel_error(t, t, ["g"], ["v"]).first()[0] == 0


def test_contribution(spark):
    parts = spark.createDataFrame([(1, "g1", 5.0), (2, "g1", 5.0), (1, "g2", 1.0), (2, "g2", 99.0), (3, "g3", 0.0)], "part_id int, g string, v double")
    got = {r[0]: r[1] for r in metrics.contribution(parts, ["g"], ["v"]).collect()}
    assert got == {1: 0.5, 2: 0.99, 3: 0.0}


def test_fractions_and_blocks():
    assert metrics.cutoff_fractions(0.64) == pytest.approx([0.64, 0.16, 0.04, 0.01])
    assert baselines.blocks_touched(0.01, 100) == pytest.approx(0.634, abs=1e-3)


def test_filtered_count_is_unbiased_over_all_draws(spark):
    from itertools import combinations

    values = [3.0, 8.0, 1.0, 4.0]
    draws = [sum(values[i] for i in c) * 4 / 2 for c in combinations(range(4), 2)]
    assert sum(draws) / len(draws) == sum(values)


def test_strata_weights_sum_to_candidates():
    rows = baselines.strata_rows(np.arange(37), np.random.default_rng(1).normal(size=37), 11, 5, 2)
    assert sum(w for _, w in rows) == pytest.approx(37)


def test_trees_learn():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(600, 6))
    y = np.where((x[:, 2] > 0.3) & (x[:, 4] < 0.5), 1.0, -1.0)
    m = BoostedTrees().fit(x, y, np.ones(600))
    assert ((m(x) > 0) == (y > 0)).mean() > 0.95
    assert set(np.argsort(m.gain)[-2:]) == {2, 4}


def test_cells_cluster_in_parallel(spark):
    rng = np.random.default_rng(0)
    df = spark.createDataFrame([(i, rng.normal(size=3).tolist()) for i in range(200)], "part_id int, f array<double>")
    rows = clustering.cell_sample(df, 40, 4).collect()
    assert sum(r["weight"] for r in rows) == pytest.approx(200)


def test_constants_come_from_all_partitions(spark):
    from types import SimpleNamespace

    from coarsesample.plans.training import constants_of

    rows = [(i, [(float(10 * i + j),) for j in range(1, 11)], [(f"v{i:03d}",)]) for i in range(200)]
    stats = spark.createDataFrame(rows, "part_id int, x__hist array<struct<hi: double>>, s__dict array<struct<value: string>>")
    got = constants_of(SimpleNamespace(stats=stats, w=SimpleNamespace(cfg=SimpleNamespace(numeric=("x",), strings=("s",)))))
    assert len(got["x"]) == 20 and got["x"][0] == 1.0 and got["x"][-1] == 2000.0
    assert max(b - a for a, b in zip(got["x"], got["x"][1:], strict=False)) < 150
    assert got["s"] == [f"v{i:03d}" for i in range(200)]


def test_cells_never_overrun_the_budget(spark):
    rng = np.random.default_rng(1)
    df = spark.createDataFrame([(i, rng.normal(size=4).tolist()) for i in range(500)], "part_id int, f array<double>")
    for n, cells in ((10, 64), (1, 64), (37, 5), (499, 64)):
        rows = clustering.cell_sample(df, n, cells).collect()
        assert len(rows) == n and sum(r["weight"] for r in rows) == pytest.approx(500)


def test_thirty_thousand_partitions():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(30_000, 6))
    c = picker.Candidates(np.arange(30_000), x, [(1,)] * 30_000, np.ones(30_000), np.ones(30_000), x)
    rows = picker.select_full(c, 1500, [lambda r: r[:, 0], lambda r: r[:, 1] - 1])
    assert len(rows) == 1500 == len({r[0] for r in rows}) and sum(r[1] for r in rows) == pytest.approx(30_000)


def test_split_sample_is_cluster_sample_below_its_limit():
    x = np.random.default_rng(3).normal(size=(50, 3))
    assert clustering.split_sample(np.arange(50), x, 7) == clustering.cluster_sample(np.arange(50), x, 7)
    picks = clustering.split_sample(np.arange(50), x, 7, most=10)
    assert len(picks) == 7 and sum(w for _, w, _ in picks) == pytest.approx(50)


@pytest.mark.parametrize("chosen", [5, 2000])
def test_only_chosen_files_are_read(spark, tmp_path, chosen):
    from coarsesample.operators.execute import weighted_scan

    n, path = (40, f"file://{tmp_path}/few") if chosen == 5 else (2500, f"file://{tmp_path}/many")
    spark.range(n * 2).selectExpr("id AS x", f"CAST(id % {n} AS INT) AS part_id").repartition(4, "part_id").write.partitionBy("part_id").parquet(path)
    df = spark.read.parquet(path)
    picks = picker.selection_frame(spark, [(i, 2.0, "r", 0, 0) for i in range(0, n, n // chosen)][:chosen])
    for at in (path, None):
        got = weighted_scan(df, picks, at)
        assert got.count() == 2 * chosen and got.agg({"weight": "sum"}).first()[0] == 4.0 * chosen
        plan = got._jdf.queryExecution().executedPlan()
        if at:
            read = {f.split("part_id=")[1].split("/")[0] for f in got.inputFiles()}
            assert len(read) == chosen
        else:
            assert "PartitionFilters: [" in plan.toString() and "part_id" in plan.toString().split("PartitionFilters: [")[1].split("]")[0]


def test_contributions_on_spark_equal_the_answers(spark):
    from coarsesample.plans.query import Agg, Clause, QuerySpec
    from coarsesample.plans.training import Answers, batch_partials, contributions_of

    rng = np.random.default_rng(5)
    rows = [(int(rng.integers(0, 9)), rng.choice(["a", "b", None]), rng.choice(["u", "v"]), float(rng.normal()), int(rng.integers(0, 5))) for _ in range(600)]
    df = spark.createDataFrame(rows, "part_id int, g string, h string, x double, k int").cache()
    queries = [QuerySpec((Agg("sum", "x", "s"), Agg("count", "*", "n"), Agg("avg", "x", "m")), w, by) for w in (None, Clause("k", ">", 2.0), Clause("k", ">", 9.0)) for by in ((), ("g",), ("g", "h"))]
    parts = np.arange(9)
    got = contributions_of(df, queries, parts)
    for q, c, t in zip(queries, got, batch_partials(df, queries), strict=True):
        assert c == pytest.approx(Answers(q, t, parts).contribution())


def test_answers_errors_by_hand(spark):
    import pandas as pd

    from coarsesample.plans.query import Agg, QuerySpec
    from coarsesample.plans.training import Answers

    t = pd.DataFrame({"part_id": [1, 1, 2, 3], "g": ["a", "b", "a", "c"], "n_rows": [1, 1, 1, 1], "s__s": [10.0, 5.0, 30.0, 8.0]})
    a = Answers(QuerySpec((Agg("sum", "s", "s"),), None, ("g",)), t, np.array([1, 2, 3]))
    e = a.errors([(1, 2.0), (2, 1.0)])
    assert e["missed"] == pytest.approx(1 / 3) and e["rel"] == pytest.approx((0.25 + 1 + 1) / 3)
    some = a.of_parts(np.array([True, True, False]))
    assert some.n_groups == 2 and some.errors([(1, 1.0), (2, 1.0)])["rel"] == 0


def test_as_of_join_keeps_a_row_together(spark):
    from coarsesample.operators.relational import as_of_join

    left = spark.createDataFrame([(1, 10, "l")], "k int, at int, tag string")
    right = spark.createDataFrame([(1, 3, "old", 7), (1, 5, None, 8), (1, 10, "same", 9), (2, 1, "other", 1)], "k int, at int, v string, w int")
    assert [tuple(r) for r in as_of_join(left, right, "k", "at", ["v", "w"]).collect()] == [(1, 10, "l", None, 8)]


def test_generator_uses_every_form():
    from coarsesample.plans.query import Like, Not, Or
    from coarsesample.plans.workload import WORKLOADS, generate

    w = WORKLOADS["lineitem"]
    constants = {c: [1.0, 2.0, 3.0] for c in w.cfg.numeric} | {c: ["AB C", "DE", "F"] for c in w.cfg.strings}
    queries = generate(w, constants, 400, 1)

    def forms(p):
        return {type(p).__name__} | {f for x in getattr(p, "of", ()) if not isinstance(x, str) for f in forms(x)} if not isinstance(p, Not) else {"Not"} | forms(p.of)

    seen = set().union(*(forms(q.where) for q in queries if q.where is not None))
    assert {"Clause", "In", "Like", "And", "Or", "Not"} <= seen and len(queries) == 400 == len(set(queries))
    assert max(len(q.group_by) for q in queries) >= 4 and any(not q.group_by for q in queries) and len({q.group_by for q in queries}) <= 16
    assert Like and Or


def test_experiments_use_all_training_queries(spark, monkeypatch):
    import inspect

    from coarsesample.plans import experiments

    of = lambda f: {k: v.default for k, v in inspect.signature(f).parameters.items()}
    assert (of(experiments.trained)["n_train"], of(experiments.trained)["n_test"]) == (400, 100)
    assert of(experiments.curves)["seeds"] == 10 and of(experiments.unseen)["instances"] == 20
    asked = []

    def noted(p, queries, *a, **b):
        asked.append(len(queries))
        return np.ones(len(p.schema), bool), [0.0]

    monkeypatch.setattr(experiments, "select_features", noted)
    assert of(experiments.trained)["selection_queries"] == 40 and 0.01 in experiments.BUDGETS
    p, *_, train = experiments.trained(spark, "/root/testdata/sf0.001", "events", "user", 10, n_train=30, n_test=3)
    assert asked == [len(train[0])] and asked[0] > 16 and len(p.models) == 4


def test_answers_stay_in_a_table(spark, monkeypatch):
    """Answers by group never come to the driver, and measured in tasks they equal those of the driver's form."""
    from coarsesample.plans import experiments, training
    from coarsesample.plans.query import Agg, Clause, QuerySpec

    rng = np.random.default_rng(6)
    rows = [(int(rng.integers(0, 9)), rng.choice(["a", "None", None]), float(rng.normal()), int(rng.integers(0, 5))) for _ in range(400)]
    df = spark.createDataFrame(rows, "part_id int, g string, x double, k int").cache()
    queries = [QuerySpec((Agg("sum", "x", "s"), Agg("avg", "x", "m")), w, by) for by in ((), ("g",)) for w in (None, Clause("k", ">", 9.0), Clause("k", ">", 2.0))]
    parts = np.arange(9)
    table = training.answers_table(df, queries, parts)
    assert table.ids == [0, 2, 3, 5] and table.rows().columns == ["query", "packed"]
    for r in table.rows().collect():
        q = queries[r["query"]]
        got, (want,) = training.Answers.unpack(q, parts, bytes(r["packed"])), training.batch_partials(df, [q])
        assert got.n_groups == (3 if q.group_by else 1) and got.rows.sum() == want["n_rows"].sum()
        assert got.errors([(int(p), 1.0) for p in parts])["rel"] == pytest.approx(0)
        if want.notna().all(axis=None):
            assert got.contribution() == pytest.approx(training.Answers(q, want, parts).contribution())
    monkeypatch.setattr(training, "batch_partials", None)
    answers = experiments.trained(spark, "/root/testdata/sf0.001", "events", "user", 10, n_train=30, n_test=3)[2]
    assert isinstance(answers, training.AnswerTable)


def test_whole_scans_read_few_files(spark):
    """Training and exact answers over all partitions don't open a file for each."""
    from conftest import TINY

    from coarsesample.plans.training import prepare

    p = prepare(spark, TINY, "events", "user", 60)
    assert len(p.df.inputFiles()) == 60 and len(p.flat.inputFiles()) <= 8
    assert p.flat.select(p.df.columns).exceptAll(p.df).isEmpty() and p.flat.count() == p.df.count()
    assert p.flat.groupBy("part_id").count().count() == 60 and p.light().flat is None


def test_driver_is_settled_between_jobs(spark, monkeypatch):
    from coarsesample.plans import training
    from coarsesample.plans.query import Agg, Clause, QuerySpec

    df = spark.range(200).selectExpr("cast(id % 8 as int) AS part_id", "cast(id AS double) AS x")
    queries, parts = [QuerySpec((Agg("sum", "x", "s"),), Clause("x", ">", float(i))) for i in range(10)], np.arange(8)
    want, calls, real = training.contributions_of(df, queries, parts), [], training.settle
    monkeypatch.setattr(training, "QUERIES_A_JOB", 1)
    monkeypatch.setattr(training, "settle", lambda s: (calls.append(s), real(s)))
    assert np.allclose(training.contributions_of(df, queries, parts), want) and len(calls) == 2
    assert len(training.answers_table(df, queries, parts)) == 10 and len(calls) == 4


def test_many_queries_share_a_scan(spark, monkeypatch):
    """Partial answers of all queries come from a fixed number of jobs, and equal those of SQL, odd values and cut partitions included."""
    import datetime

    from coarsesample.plans import partials, training
    from coarsesample.plans.query import Agg, And, Clause, In, Like, Not, Or, QuerySpec

    rng = np.random.default_rng(8)
    pick = lambda *v: v[int(rng.integers(0, len(v)))]
    day = datetime.date(2020, 1, 1)
    rows = [(i // 70, pick("a", "b%", "é\n", "", "null", None), pick(0.0, -0.0, 1.5, None), pick(float("nan"), -2.0, 3.0, None), pick(2**53, 2**53 + 1, 5, None), pick(1.0, 2.5, None), pick(day, None)) for i in range(700)]
    df = spark.createDataFrame(rows, "part_id int, g string, h double, x double, k long, v double, d date").repartition(3).cache()
    leaves = [Clause("g", "<>", "a"), In("g", ("a", "")), In("g", ("null", "b%"), True), Like("g", "%\n"), Like("g", "_%", True), Clause("x", ">", 2.0), Clause("x", "<=", 3.0), Clause("k", ">", float(2**53)), Clause("k", "<", 5.5), In("h", (0.0, 1.5), True), Clause("d", "=", "2020-01-01"), Like("g", "b\\%")]
    trees = [None, *leaves, Not(leaves[0]), And(tuple(leaves[1:3])), Or((leaves[2], leaves[5])), Not(And((leaves[5], leaves[2]))), And((Or((leaves[0], leaves[7])), leaves[9]))]
    aggs = (Agg("sum", "v * 2", "s"), Agg("avg", "v", "m"), Agg("count", "*", "n", leaves[5]), Agg("count", "v", "c"))
    queries = [QuerySpec(aggs[: 1 + i % 4], t, by) for i, t in enumerate(trees) for by in ((), ("g",), ("g", "h"), ("d",))]
    parts = np.arange(10)
    want = [training.Answers(q, t, parts) for q, t in zip(queries, training.batch_partials(df, queries), strict=True)]
    monkeypatch.setattr(partials, "BLOCK_ROWS", 50)
    spark.sparkContext.setJobGroup("one scan", "one scan")
    shares, table = training.contributions_of(df, queries, parts), training.answers_table(df, queries, parts)
    spark.sparkContext.setJobGroup("", "")
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("one scan")) < len(queries) // 4
    for q, c, w in zip(queries, shares, want, strict=True):
        assert c == pytest.approx(w.contribution()), q
    got = {r["query"]: training.Answers.unpack(queries[r["query"]], parts, bytes(r["packed"])) for r in table.rows().collect()}
    assert sorted(got) == [i for i, w in enumerate(want) if w.rows.sum()]
    for i, a in got.items():
        assert (a.rows == want[i].rows).all() and a.n_groups == want[i].n_groups, queries[i]
        assert sorted(map(tuple, a.total.round(9))) == sorted(map(tuple, want[i].total.round(9))), queries[i]
    monkeypatch.setattr(training, "MOST_TOTALS", 0)
    assert np.allclose(training.contributions_of(df, queries[:8], parts), shares[:8])


def test_rows_that_lie_by_partition_are_not_dealt_again(spark, monkeypatch):
    """Contributions and answers don't shuffle rows of whole partitions; a partition found in two places is still right."""
    from coarsesample.plans import training
    from coarsesample.plans.query import Agg, Clause, QuerySpec

    rows = [(p, i % 3, float(i)) for p in (4, 1, 3, 0, 2) for i in range(50 + p)]
    df = spark.createDataFrame(rows, "part_id int, g int, x double").coalesce(1).cache()
    queries, parts = [QuerySpec((Agg("sum", "x", "s"), Agg("count", "*", "n")), w, ("g",)) for w in (None, Clause("x", ">", 20.0))], np.arange(5)
    want = training.contributions_of(df, queries, parts)
    dealt, real = [], training._by_partition
    monkeypatch.setattr(training, "_by_partition", lambda t: (dealt.append(t), real(t))[1])
    assert np.allclose(training.contributions_of(df, queries, parts, whole=True), want)
    table = training.answers_table(df, queries, parts, whole=True)
    assert not dealt and np.allclose([training.Answers.unpack(queries[r["query"]], parts, bytes(r["packed"])).contribution() for r in sorted(table.rows().collect())], want)
    assert np.allclose(training.contributions_of(df.repartition(4), queries, parts, whole=True), want) and len(dealt) == 1
