"""Sketches on small hand-made partitions."""

from collections import Counter
import random

from pyspark.sql import functions as F

from coarsesample.operators import sketches as S


def frame(spark, rows):
    return spark.createDataFrame(rows, "part_id int, x double, s string")


def test_histogram_keeps_a_value_in_one_bucket(spark):
    rows = [(1, float(v), "a") for v in [1] * 50 + list(range(2, 52))] + [(2, None, "b")]
    h = S.histogram(S.value_counts(frame(spark, rows), ["x"], "double")).orderBy("lo").collect()
    assert sum(r["n_rows"] for r in h) == 100 and sum(r["ndv"] for r in h) == 51
    assert h[0]["lo"] == h[0]["hi"] == 1.0 and h[0]["n_rows"] == 50
    assert all(a["hi"] < b["lo"] for a, b in zip(h, h[1:]))


def test_heavy_hitter_needs_support(spark):
    rows = [(1, 1.0, "big")] * 999 + [(1, 2.0, "one")]
    found = S.heavy_hitters(S.value_counts(frame(spark, rows), ["s"], "string")).collect()
    assert [(r["value"], r["n"]) for r in found] == [("big", 999)]


def test_few_distinct_values_are_exact(spark):
    rows = [(1, float(i % 20), str(i % 20)) for i in range(400)]
    f = S.kmv_features(S.kmv(S.value_counts(frame(spark, rows), ["s"], "string"))).first()
    assert f["ndv"] == 20 and f["freq_sum"] == 400


def test_merge_equals_sketch_of_union(spark):
    rows = [(1, float(i), str(i)) for i in range(600)]
    df = frame(spark, rows)
    k = lambda d: S.kmv(S.value_counts(d, ["s"], "string"))
    merged = S.kmv_merge(k(df.where("x < 350")), k(df.where("x >= 350")))
    assert sorted(map(tuple, merged.collect())) == sorted(map(tuple, k(df).collect()))
    est = S.kmv_features(k(df)).first()["ndv"]
    assert 400 < est < 800


def test_measures_with_nulls(spark):
    m = S.measures(frame(spark, [(1, 2.0, "a"), (1, None, "a"), (1, 4.0, "b"), (2, None, None)]), ["x"]).orderBy("part_id").collect()
    assert (m[0]["n_rows"], m[0]["n_null"], m[0]["mean"], m[0]["mean_sq"]) == (3, 1, 3.0, 10.0)
    assert m[1]["n_null"] == 1 and m[1]["mean"] is None


def test_lossy_counting_guarantees():
    rng = random.Random(3)
    for trial in range(5):
        values = [min(int(rng.expovariate(0.05)), 400) for _ in range(20_000)]
        eps, support = 0.002, 0.02
        c = S.LossyCounter(eps)
        for v in values:
            c.add(v)
        true = Counter(values)
        got = {v: f for v, f, _ in c.report(support, eps)}
        assert all(v in got for v, n in true.items() if n >= support * len(values))
        assert all(f <= true[v] <= f + eps * len(values) for v, f in got.items())


def test_built_in_top_items(spark):
    df = spark.createDataFrame([(1, "a")] * 5 + [(1, "b")] * 3, "part_id int, s string")
    top = S.frequent_items(df, "s", 1).select(F.explode("items").alias("i")).first()["i"]
    assert top["item"] == "a" and top["count"] == 5


def test_runs_have_bounded_state():
    """Streamed statistics are exact up to a number of distinct values, and near beyond it."""
    import numpy as np

    from coarsesample.operators.streamed import Numbers, Texts

    rng = np.random.default_rng(3)
    x = np.concatenate([rng.random(20_000), np.full(3_000, 0.5), np.full(500, -0.25)])
    rng.shuffle(x)
    exact, near, ordered = Numbers(), Numbers(500), np.sort(x)
    for at in range(0, len(x), 1_000):
        exact.add(x[at : at + 1_000])
        near.add(x[at : at + 1_000])
    want = [ordered[int(np.ceil(k * len(x) / 10)) - 1] for k in range(1, 10)]
    assert exact.cuts(10) == want and exact.distinct() == 20_002 and exact.top()[:2] == [{"item": 0.5, "count": 3_000}, {"item": -0.25, "count": 500}]
    assert len(near.values) <= 500 and len(near.points[0]) <= 1_000 and (near.low, near.high, near.n) == (ordered[0], ordered[-1], len(x))
    assert np.allclose(near.cuts(10), want, atol=0.05) and abs(near.distinct() - 20_002) < 2_000
    assert near.top()[0]["item"] == 0.5 and 3_000 - len(x) / 500 <= near.top()[0]["count"] <= 3_000
    words = Texts(50)
    for at in range(100):
        words.add(["a", f"w{at}"], np.array([1.0, 2.0 + at]), np.array([5, 1]))
    assert len(words.counts) <= 50 and words.top()[0]["item"] == "a" and words.n == 600 and words.distinct() == 101
