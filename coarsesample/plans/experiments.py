"""The experiments: error curves of all methods, ablations, clusterers, layouts, bands, overheads.

One scan per columnset answers all queries of an experiment per partition; every method, budget and
seed is then evaluated on those answers in the tasks that hold them, so no sweep rescans the data, none
runs on the driver and no answers come to it. A prepared view is kept for the session and never changed; variants are copies.
"""

from __future__ import annotations

import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.operators import baselines
from coarsesample.operators.picker import select_full
from coarsesample.plans.training import Answers, AnswerTable, Prepared, answers_table, constants_of, contributions_of, in_tasks, prepare, select_features
from coarsesample.plans.workload import generate, templates
from coarsesample.runtime import read_table, settle, ship_package

_held: dict[tuple, tuple] = {}
BUDGETS = (0.01, 0.02, 0.05, 0.1, 0.2, 0.4, 0.8)
VIEWS = (("lineitem", "shipdate"), ("orders", "day"), ("events", "user"), ("documents", "n_chars"), ("embeddings", "e0"))
FLAGS = {
    "full": {},
    "no_clusters": {"use_clusters": False},
    "no_outliers": {"use_outliers": False},
    "no_models": {"use_models": False},
    "random": {"use_filter": False, "use_outliers": False, "use_models": False, "use_clusters": False},
    "filter": {"use_outliers": False, "use_models": False, "use_clusters": False},
    "filter_outliers": {"use_models": False, "use_clusters": False},
    "filter_clusters": {"use_outliers": False, "use_models": False},
    "filter_models": {"use_outliers": False, "use_clusters": False},
}


#: Rows of the base table to a partition, and the least count of partitions, by view.
PART_ROWS = {"lineitem": (600, 50), "orders": (300, 30), "events": (200, 20), "documents": (50, 20), "embeddings": (100, 10)}


def n_parts_of(spark: SparkSession, sf_dir: str, name: str, most: int = 1000) -> int:
    """Partitions of an experiment: by the table's rows, ``most`` at most."""
    rows, least = PART_ROWS[name]
    return min(most, max(least, read_table(spark, sf_dir, name).count() // rows))


def trained(spark: SparkSession, sf_dir: str, name: str, layout: str, n_parts: int | None = None, n_train: int = 400, n_test: int = 100, selection_queries: int = 40) -> tuple:
    """Prepared view with models, test queries, their answers and selectivities; kept for the session.

    Models learn from the contributions of all training queries; features are selected on the first
    ``selection_queries`` of them that have an answer.
    """
    n_parts = n_parts or n_parts_of(spark, sf_dir, name)
    key = (spark.sparkContext.applicationId, sf_dir, name, layout, n_parts, n_train, n_test)
    if key not in _held:
        p = prepare(spark, sf_dir, name, layout, n_parts)
        both = generate(p.w, constants_of(p), n_train + n_test, seed=17)
        sels = p.selectivities(both)
        shares = contributions_of(p.flat, both[:n_train], p.parts, whole=True)
        train = [i for i in range(len(shares)) if shares[i].any()]
        seen = ([both[i] for i in train], [shares[i] for i in train], [sels[i] for i in train])
        p = p.fit(*seen)
        asked = [*both[n_train:], *seen[0][:selection_queries]]
        answers = answers_table(p.flat, asked, p.parts, whole=True)
        rest = [i for i in answers.ids if i < len(both) - n_train]
        learnt = answers.of(list(range(len(both) - n_train, len(asked))))
        p.keep = select_features(p, seen[0][:selection_queries], learnt, seen[2][:selection_queries])[0]
        _held[key] = (p, [asked[i] for i in rest], answers.of(rest), [sels[n_train + i] for i in rest], (*seen, learnt))
    return _held[key]


def each_query(p: Prepared, queries, answers: AnswerTable, sels, work: Callable, schema: str) -> DataFrame:
    """Rows of ``work(p, query, answers, selectivities)`` for every query that has an answer, some queries to a task."""
    spark = p.df.sparkSession
    ship_package(spark)
    names = [c.split()[0] for c in schema.split(", ")]
    held = spark.sparkContext.broadcast(pickle.dumps((p.light(), dict(zip(answers.ids, zip(queries, sels, strict=True), strict=True)))))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        light, known = None, {}
        for batch in batches:
            if light is None:
                light, known = pickle.loads(held.value)
            for i, packed in zip(batch["query"], batch["packed"], strict=True):
                q, s = known[i]
                yield pd.DataFrame(list(work(light, q, Answers.unpack(q, light.parts, packed), s)), columns=names)

    rows = answers.rows().repartition(max(1, len(answers)), "query").mapInPandas(run, schema).collect()
    held.unpersist()
    settle(spark)
    return spark.createDataFrame([tuple(r) for r in rows], schema)


def pick(p: Prepared, method: str, q, sel: np.ndarray, n: int, seed: int) -> list[tuple]:
    """A method's selection for a query."""
    if method == "uniform":
        return baselines.uniform_rows(p.parts, n, seed)
    alive = p.parts[sel[:, 0] > 0]
    if method == "filtered":
        return baselines.uniform_rows(alive, min(n, len(alive)), seed)
    if method == "strata":
        score = p.scorer(p.raw(q, sel))[sel[:, 0] > 0]
        return baselines.strata_rows(alive, score, min(n, len(alive)), 5, seed)
    return select_full(p.candidates(q, sel), n, p.models, seed=seed, **FLAGS[method])


CURVE = "method string, budget double, missed double, rel_error double, abs_over_true double"


def curves(p: Prepared, queries, answers, sels, methods, budgets=BUDGETS, seeds: int = 10) -> DataFrame:
    """method, budget, missed, rel_error, abs_over_true: means over queries and seeds."""

    def work(p: Prepared, q, a, s):
        for m in methods:
            draws = m in ("uniform", "filtered", "strata") or not FLAGS[m].get("use_clusters", True)
            for b in budgets:
                n = max(1, round(b * len(p.parts)))
                found = [a.errors(pick(p, m, q, s, n, seed)) for seed in range(seeds if draws else 1)]
                yield (m, float(b), *(float(np.mean([f[e] for f in found])) for e in ("missed", "rel", "abs")))

    each = each_query(p, queries, answers, sels, work, CURVE)
    return each.groupBy("method", "budget").agg(*[F.round(F.avg(c), 9).alias(c) for c in ("missed", "rel_error", "abs_over_true")])


def mean_error(p: Prepared, queries, answers, sels, choose: Callable) -> float:
    """Mean relative error of ``choose(p, query, selectivities)`` over queries."""
    rows = each_query(p, queries, answers, sels, lambda p, q, a, s: [(a.errors(choose(p, q, s))["rel"],)], "e double")
    return float(rows.agg(F.avg("e")).first()[0] or 0.0)


def frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def sweep(spark: SparkSession, sf_dir: str, name: str, layout: str, methods=("uniform", "filtered", "strata", "full"), n_parts: int | None = None) -> DataFrame:
    """Main error curves of one view and layout; kept for the measures that follow from them."""
    key = (spark.sparkContext.applicationId, "sweep", sf_dir, name, layout, methods, n_parts)
    if key not in _held:
        p, q, a, s, _ = trained(spark, sf_dir, name, layout, n_parts)
        rows = curves(p, q, a, s, methods).select(F.lit(name).alias("view"), F.lit(layout).alias("layout"), F.lit(len(p.parts)).alias("parts"), "*")
        _held[key] = ([tuple(r) for r in rows.collect()], rows.schema)
    return spark.createDataFrame(*_held[key])


def lesion(spark: SparkSession, sf_dir: str, methods: tuple[str, ...] = tuple(FLAGS)) -> DataFrame:
    """Each part left out, and each part alone on top of the filter."""
    p, q, a, s, _ = trained(spark, sf_dir, "events", "user")
    return curves(p, q, a, s, methods, budgets=(0.05, 0.1, 0.2))


def knobs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rate factor, outlier budget, exemplar."""
    p, q, a, s, _ = trained(spark, sf_dir, "events", "user")
    n, rows = max(1, round(0.1 * len(p.parts))), []
    for knob, values in {"alpha": (1.0, 2.0, 4.0, 8.0), "outlier_share": (0.0, 0.1, 0.2, 0.4), "exemplar": ("median", "random")}.items():
        for v in values:
            rows.append((knob, str(v), mean_error(p, q, a, s, lambda p, x, z, knob=knob, v=v: select_full(p.candidates(x, z), n, p.models, **{knob: v}))))
    return frame(spark, rows, "knob string, setting string, rel_error double")


def model_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of regressors in the funnel."""
    p, q, a, s, train = trained(spark, sf_dir, "events", "user")
    n, rows = max(1, round(0.1 * len(p.parts))), []
    for k in (1, 2, 4, 6):
        rows.append((k, mean_error(p.fit(*train[:3], k=k), q, a, s, lambda p, x, z: select_full(p.candidates(x, z), n, p.models))))
    return frame(spark, rows, "models int, rel_error double")


def clusterers(spark: SparkSession, sf_dir: str, views=(("orders", "day"), ("events", "user"), ("documents", "n_chars"))) -> DataFrame:
    """Area under the error curve of clustering alone, by algorithm and view."""
    rows = []
    for name, layout in views:
        p, q, a, s, _ = trained(spark, sf_dir, name, layout)
        algos = ("hac_single", "hac_ward", "kmeans")

        def work(p: Prepared, x, y: Answers, z):
            c = p.candidates(x, z)
            for algo in algos:
                for b in BUDGETS:
                    yield algo, b, y.errors(select_full(c, max(1, round(b * len(p.parts))), None, algo=algo, use_outliers=False, use_models=False))["rel"]

        found = {(r["algo"], r["b"]): r["e"] for r in each_query(p, q, a, s, work, "algo string, b double, e double").groupBy("algo", "b").agg(F.avg("e").alias("e")).collect()}
        rows += [(name, algo, float(np.trapezoid([found.get((algo, b), 0.0) for b in BUDGETS], BUDGETS))) for algo in algos]
    return frame(spark, rows, "view string, algorithm string, auc double")


def feature_kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Percent of gain by kind of statistic."""
    p = trained(spark, sf_dir, "lineitem", "shipdate")[0]
    return frame(spark, list(p.importance_by_kind().items()), "kind string, gain_percent double")


def feature_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clustering error with each kind left out, and with selected features."""
    p, q, a, s, _ = trained(spark, sf_dir, "events", "user")
    n = max(1, round(0.1 * len(p.parts)))
    sets = {"all": np.ones(len(p.schema), bool), "selected": p.keep} | {f"no_{k}": np.array([x != k for x in p.schema.kinds]) for k in ("measure", "heavy_hitter", "distinct", "selectivity")}
    rows = [(name, mean_error(replace(p, keep=cols), q, a, s, lambda p, x, z: select_full(p.candidates(x, z), n, p.models)), int(cols.sum())) for name, cols in sets.items()]
    return frame(spark, rows, "features string, rel_error double, dimensions int")


def bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of each test query at a tenth of partitions, with the query's true selectivity."""
    p, q, a, s, _ = trained(spark, sf_dir, "lineitem", "shipdate")
    total, n = p.flat.count(), max(1, round(0.1 * len(p.parts)))

    def work(p: Prepared, x, y: Answers, z):
        for m in ("uniform", "filtered", "full"):
            seeds = range(1 if m == "full" else 10)
            yield m, float(y.rows.sum() / total), float(np.mean([y.errors(pick(p, m, x, z, n, seed))["rel"] for seed in seeds]))

    return each_query(p, q, a, s, work, "method string, selectivity double, error double")


def picker_times(spark: SparkSession, sf_dir: str, budgets=(0.01, 0.05, 0.1, 0.2), queries: int = 20) -> DataFrame:
    """Milliseconds of a pick and of its clustering on the driver, by view and budget, over some test queries."""
    rows = []
    for name, layout in VIEWS:
        p, q, _, s, _ = trained(spark, sf_dir, name, layout)
        for b in budgets:
            times = []
            for x, z in list(zip(q, s, strict=True))[:queries]:
                c = p.candidates(x, z)
                select_full(c, max(1, round(b * len(p.parts))), p.models)
                if c.timing:
                    times.append((c.timing["total_ms"], c.timing["cluster_ms"]))
            t = np.array(times or [(0.0, 0.0)])
            rows.append((name, len(p.parts), b, *map(float, (t[:, 0].mean(), t[:, 0].std(), t[:, 1].mean(), t[:, 1].std()))))
    return frame(spark, rows, "view string, parts int, budget double, total_ms double, total_sd double, cluster_ms double, cluster_sd double")


def unseen(spark: SparkSession, sf_dir: str, instances: int = 20, budget: float = 0.1, methods=("uniform", "filtered", "strata", "full")) -> DataFrame:
    """Benchmark-like templates that training never saw: mean, best and worst error of each method over instances."""
    import random

    from coarsesample.operators.metrics import spread

    p = trained(spark, sf_dir, "lineitem", "shipdate")[0]
    rng = random.Random(5)
    named = [(t, q) for _ in range(instances) for t, q in templates(rng).items()]
    queries = [q for _, q in named]
    answers = answers_table(p.flat, queries, p.parts, whole=True)
    sels = p.selectivities(queries)
    n = max(1, round(budget * len(p.parts)))

    def work(p: Prepared, q, a: Answers, s):
        at = next(i for i, x in enumerate(queries) if x == q)
        for m in methods:
            yield f"{named[at][0]} {m}", a.errors(pick(p, m, q, s, n, 3))["rel"]

    each = spread(each_query(p, [queries[i] for i in answers.ids], answers, [sels[i] for i in answers.ids], work, "template string, error double"))
    return each.select(F.split("template", " ")[0].alias("template"), F.split("template", " ")[1].alias("method"), "mean_error", "best", "worst")


def task_seconds(spark: SparkSession, group: str) -> float:
    """Run time of all tasks of a job group, from the status store: the compute a query costs."""
    sc = spark.sparkContext
    store, total = sc._jsc.sc().statusStore(), 0
    sc._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    for job in sc.statusTracker().getJobIdsForGroup(group):
        for stage in sc.statusTracker().getJobInfo(job).stageIds:
            total += store.lastStageAttempt(stage).executorRunTime()
    return total / 1000


def speedups(spark: SparkSession, sf_dir: str, queries: int = 10) -> DataFrame:
    """Wall and task seconds of exact answers over those of the picker's samples, means over test queries.

    A sample's wall time includes the pick; both read the layout's files.
    """
    from coarsesample.operators.execute import weighted_aggregate
    from coarsesample.plans.query import exact

    p, q, _, s, _ = trained(spark, sf_dir, "lineitem", "shipdate")

    def timed(tag: str, make: Callable[[], DataFrame]) -> tuple[float, float]:
        began = time.perf_counter()
        spark.sparkContext.setJobGroup(tag, tag)
        make().collect()
        spark.sparkContext.setJobGroup("", "")
        return time.perf_counter() - began, task_seconds(spark, tag)

    some, tag = list(zip(q, s, strict=True))[:queries], f"speedup-{time.monotonic_ns()}"
    timed(f"{tag}-warm", lambda: exact(p.df, some[0][0]))
    full = np.array([timed(f"{tag}-full-{i}", lambda x=x: exact(p.df, x)) for i, (x, _) in enumerate(some)])
    rows = []
    for b in (0.01, 0.05, 0.1):
        n = max(1, round(b * len(p.parts)))
        took = np.array([timed(f"{tag}-{b}-{i}", lambda x=x, z=z: weighted_aggregate(p.scan(select_full(p.candidates(x, z), n, p.models)), x)) for i, (x, z) in enumerate(some)])
        wall, compute = full.mean(0) / np.maximum(took.mean(0), 1e-3)
        rows.append((b, n / len(p.parts), float(wall), float(compute)))
    return frame(spark, rows, "budget double, parts_read double, latency_speedup double, compute_speedup double")
