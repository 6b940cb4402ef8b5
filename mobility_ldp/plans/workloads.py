"""The experiments, over the given tables. Each returns its table of results.

The registered ones make one run of each setting; the functions take any
sources, budgets and seeds. Published sets are measured a few at a time, as
the many small jobs of a measure leave most of the executors idle.
"""

from __future__ import annotations

import math
import time
from dataclasses import replace
from multiprocessing.pool import ThreadPool

import numpy as np
from pyspark import StorageLevel, inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import ablations, attacks, errors, granularity, metrics, models, ngram, oue, synthesis, trajectory
from ..operators.grid import Grid, make_grid
from ..sources import files, walks
from . import relational

INF = math.inf
METHODS = ("synthesizer", "ngram")
SOURCES = ("order_walk", "customer_walk", "userday_walk", "poi_walk")
AT_ONCE = 4
#: Tasks for each core that trips are dealt over.
TASKS = 4


def _gathered(spark: SparkSession, sf_dir: str, source: str) -> tuple[DataFrame, Grid]:
    """The points of a source, a row per trip, and their box."""
    p = walks.WALKS[source](spark, sf_dir)
    # by number, so that Spark does not put all trips into one task for being small: their bits are not; the shuffle is the one of gathered()
    return trajectory.gathered(p.repartition(TASKS * spark.sparkContext.defaultParallelism, "traj_id")), make_grid(p, 1)


def _on(lists: DataFrame, box: Grid, n: int):
    """Trips over a grid of side n from gathered points."""
    grid = replace(box, n=n)
    return trajectory.walked(lists, grid).persist(StorageLevel.MEMORY_AND_DISK), grid


def _trips(spark: SparkSession, sf_dir: str, source: str, n: int):
    return _on(*_gathered(spark, sf_dir, source), n)


def _published(spark, trips, grid, method: str, eps: float, seed: int, **options) -> DataFrame:
    """A published set of as many trips, by either method."""
    if method == "ngram":
        return ngram.ngram_perturb(trips, grid, eps, seed=seed)
    if method == "non_private":
        return ablations.non_private(spark, trips, grid, trips.count(), seed)
    return ablations.VARIANTS["full" if method == "synthesizer" else method](spark, trips, grid, eps, trips.count(), seed, **options)


def published(spark, trips, grid, method: str, eps: float, seed: int, **options) -> DataFrame:
    """The same, kept for several uses."""
    return _published(spark, trips, grid, method, eps, seed, **options).persist(StorageLevel.MEMORY_AND_DISK)


def _tagged(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in tags.items()], *df.columns)


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _measured(spark, trips, grid, settings) -> list[list[tuple[str, float]]]:
    """The nine (metric, value) of each setting (method, eps, seed), in order. A set's counts by cells and short runs reach the driver, which a grid bounds; if they are too many, nine numbers."""
    real, boxes = metrics.tallied(trips, grid), metrics.range_queries(spark, grid).collect()

    def one(setting):
        syn = _published(spark, trips, grid, *setting)
        counts = None if real is None else metrics.tallied(syn, grid)
        if counts is not None:
            return list(metrics.measures(real, counts, grid, boxes).items())
        syn = syn.persist(StorageLevel.MEMORY_AND_DISK)
        out = [(r["metric"], r["value"]) for r in metrics.evaluate_all(trips, syn, grid).collect()]
        syn.unpersist()
        return out

    with ThreadPool(AT_ONCE) as pool:
        return pool.map(inheritable_thread_target(spark)(one), settings, chunksize=1)


def utility(spark, sf_dir, sources=SOURCES, epses=(0.5, 1.0, 1.5), methods=METHODS, seeds=(1,), n=4) -> DataFrame:
    """Nine measures by source, eps and method, averaged over seeds."""
    settings = [(eps, m, seed) for eps in epses for m in methods for seed in seeds]
    rows = []
    for s in sources:
        trips, grid = _trips(spark, sf_dir, s, n)
        trips.count()
        found = _measured(spark, trips, grid, [(m, eps, seed) for eps, m, seed in settings])
        rows += [(s, float(eps), m, seed, *r) for (eps, m, seed), part in zip(settings, found, strict=True) for r in part]
        trips.unpersist()
    out = spark.createDataFrame(rows, "source string, eps double, method string, seed int, metric string, value double")
    return out.groupBy("source", "eps", "method", "metric").agg(F.avg("value").alias("value"))


def ablation(spark, sf_dir, sources=SOURCES, eps=1.0, n=4, seed=1) -> DataFrame:
    """Nine measures of the full method and of three with a part taken out, by source."""
    variants, rows = (*ablations.VARIANTS, "non_private"), []
    for s in sources:
        trips, grid = _trips(spark, sf_dir, s, n)
        trips.count()
        found = _measured(spark, trips, grid, [(v, eps, seed) for v in variants])
        rows += [(s, v, *r) for v, part in zip(variants, found, strict=True) for r in part]
        trips.unpersist()
    return spark.createDataFrame(rows, "source string, variant string, metric string, value double")


def component_times(spark, sf_dir, source="order_walk", n=6, eps=1.0, with_ngram=True, seed=1) -> DataFrame:
    """(component, seconds, per_1000): time of each part, forced by a sink that keeps nothing. Both methods run on all trips."""
    trips, grid = _trips(spark, sf_dir, source, n)
    total = trips.count()
    model = models.fit(trips, grid, eps, seed=seed)
    l_k, e = model.plan.l_k, model.plan
    rows = []

    def timed(name, df, size=total):
        t = time.perf_counter()
        out = df() if callable(df) else files.force(df)
        s = time.perf_counter() - t
        rows.append((name, s, s / max(1, size) * 1000))
        return out

    length = ("length", models.length_item(grid.cells), 0, grid.cells, e.e1)
    moves = ("intra", models.kept_moves(models.state_items(grid), l_k), l_k, grid.states, e.per_move)
    ends = [("begin", F.col("cells")[0], 0, grid.cells, e.per_end), ("end", F.element_at("cells", -1), 0, grid.cells, e.per_end)]
    timed("user: length", oue.fused(trips, [length], seed))
    timed("user: moves", oue.fused(trips, [moves], seed))
    timed("user: ends", oue.fused(trips, ends, seed))
    counts = oue.fused(trips, [length], seed).persist()
    counts.count()
    timed("curator: preparation", lambda: models.length_quantile(models.length_model(oue.settle(oue.estimate(counts, e.e1)))).collect())
    reported = oue.fused(trips, [moves, *ends], seed).collect()

    def patterns():
        parts = [models._vector(reported, name, d, each, total) for name, d, each in (("intra", grid.states, e.per_move), ("begin", grid.cells, e.per_end), ("end", grid.cells, e.per_end))]
        return models.build_model(grid, model.lengths, np.maximum(np.concatenate(parts), 0))

    timed("curator: patterns", patterns)
    timed("curator: synthesis", synthesis.synthesize(spark, model, total, seed))
    rows.append(("synthesizer total", sum(r[1] for r in rows), sum(r[2] for r in rows)))
    if with_ngram:
        timed("ngram total", ngram.ngram_perturb(trips, grid, eps, seed=seed))
    return spark.createDataFrame(rows, "component string, seconds double, per_1000 double")


def side_sweep(spark, sf_dir, source="order_walk", sides=(2, 4, 6, 8, 10, 12), eps=50.0, methods=METHODS, seed=1) -> DataFrame:
    """(n, method, query_error, seconds, recommended): query error and run time by the grid's side, the guideline's choice marked."""
    p = walks.WALKS[source](spark, sf_dir)
    best = granularity.recommend_for(p, 1 / 15, eps)
    lists, box = _gathered(spark, sf_dir, source)
    lists, rows = lists.persist(StorageLevel.MEMORY_AND_DISK), []
    for n in sides:
        trips, grid = _on(lists, box, n)
        trips.count()
        real = metrics.spots(trips, grid, "uniform", 7).persist()
        for m in methods:
            t = time.perf_counter()
            syn = published(spark, trips, grid, m, eps, seed)
            syn.count()
            s = time.perf_counter() - t
            # one fine grid for all sides: errors are compared on the same boxes
            rows.append((n, m, metrics.query_error(trips, syn, grid, points="uniform", seed=7, known=real).first()["value"], s, n == best))
            syn.unpersist()
        real.unpersist()
        trips.unpersist()
    lists.unpersist()
    return spark.createDataFrame(rows, "n int, method string, query_error double, seconds double, recommended boolean")


def lambda_sweep(spark, sf_dir, source="order_walk", lams=(0.5, 1.5, 2.5, 3.5), eps=1.0, seed=1) -> DataFrame:
    """(lam, n, query_error): the guideline's factor, through the side that it gives."""
    of = granularity.statistics(walks.WALKS[source](spark, sf_dir)).first()
    lists, box = _gathered(spark, sf_dir, source)
    lists, rows, known = lists.persist(StorageLevel.MEMORY_AND_DISK), [], {}
    for lam in lams:
        n = granularity.recommend(of["users"], of["mean_points"], 1 / 15, eps, lam)[1]
        if n not in known:
            trips, grid = _on(lists, box, n)
            # read once, so not kept
            syn = _published(spark, trips, grid, "synthesizer", eps, seed)
            known[n] = metrics.query_error(trips, syn, grid, points="uniform", seed=7).first()["value"]
            trips.unpersist()
        rows.append((float(lam), n, known[n]))
    lists.unpersist()
    return spark.createDataFrame(rows, "lam double, n int, query_error double")


def query_size_sweep(spark, sf_dir, source="order_walk", sizes=(1 / 36, 1 / 16, 1 / 9, 1 / 4, 4 / 9), eps=50.0, n=6, seed=1) -> DataFrame:
    """(r, query_error) by the share of the space that a query covers."""
    trips, grid = _trips(spark, sf_dir, source, n)
    syn = published(spark, trips, grid, "synthesizer", eps, seed)
    return _all([_tagged(metrics.query_error(trips, syn, grid, r=r, points="uniform"), r=float(r)) for r in sizes])


def quantile_sweep(spark, sf_dir, source="order_walk", ks=(0.5, 0.6, 0.7, 0.8, 0.9, 1.0), eps=50.0, n=4, seed=1) -> DataFrame:
    """(k, metric, value): query error, diameter error, pattern F1, and seconds, by the quantile of lengths; beside them the analytic error of moves."""
    trips, grid = _trips(spark, sf_dir, source, n)
    real, boxes, rows = metrics.tallied(trips, grid), metrics.range_queries(spark, grid).collect(), []
    for k in ks:
        t = time.perf_counter()
        syn = published(spark, trips, grid, "synthesizer", eps, seed, k=k)
        syn.count()
        s = time.perf_counter() - t
        counts = None if real is None else metrics.tallied(syn, grid)
        if counts is not None:
            found = metrics.measures(real, counts, grid, boxes)
            found = [(m, found[m]) for m in ("query_error", "diameter_error", "pattern_f1")]
        else:
            found = [(r["metric"], r["value"]) for x in (metrics.query_error(trips, syn, grid), metrics.diameter_error(trips, syn, grid), metrics.pattern_f1(trips, syn)) for r in x.collect()]
        syn.unpersist()
        rows += [(float(k), m, v) for m, v in [*found, ("seconds", s)]]
    parts = [spark.createDataFrame(rows, "k double, metric string, value double")]
    freqs = trajectory.transitions(trips).groupBy("src", "dst").agg(F.count("*").alias("f"))
    lens = trips.groupBy(F.col("n_cells").alias("len")).agg(F.count("*").alias("f"))
    curve = errors.transition_error_curve(freqs, lens, trips.count(), eps, list(ks))
    parts.append(curve.select(F.col("k").cast("double").alias("k"), F.lit("analytic_error").alias("metric"), (F.col("noise") + F.col("bias")).alias("value")))
    return _all(parts)


def scalability(spark, sf_dir, sources=("order_walk", "userday_walk"), multiples=(1, 2, 4), eps=1.0, n=6, seed=1, methods=METHODS) -> DataFrame:
    """(source, method, trips, seconds, per_1000): both methods over copies of a source under new ids."""
    rows = []
    for source in sources:
        base, grid = _trips(spark, sf_dir, source, n)
        size = base.count()
        for m in multiples:
            trips = base.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(m)))).select(F.xxhash64("traj_id", "copy").alias("traj_id"), "cells", "n_cells")
            for method in methods:
                t = time.perf_counter()
                files.force(ngram.ngram_perturb(trips, grid, eps, seed=seed) if method == "ngram" else synthesis.synthesize(spark, models.fit(trips, grid, eps, seed=seed), size * m, seed))
                s = time.perf_counter() - t
                rows.append((source, method, size * m, s, s / max(1, size * m) * 1000))
        base.unpersist()
    return spark.createDataFrame(rows, "source string, method string, trips long, seconds double, per_1000 double")


def stage_costs(spark, sf_dir, source="order_walk", n=6, eps=1.0, seed=1) -> DataFrame:
    """(component, stages, input_bytes, shuffle_bytes, spilled_bytes, task_seconds): what Spark's own counters say of each step."""
    sc = spark.sparkContext
    rows = []

    def counted(name, action):
        group = f"{name}-{time.time_ns()}"
        sc.setJobGroup(group, name)
        try:
            action()
        finally:
            sc.setLocalProperty("spark.jobGroup.id", None)
            sc.setLocalProperty("spark.job.description", None)
        jvm = sc._jsc.sc()
        jvm.listenerBus().waitUntilEmpty()
        store, ran = jvm.statusStore(), []
        for job in sc.statusTracker().getJobIdsForGroup(group):
            for stage in sc.statusTracker().getJobInfo(job).stageIds:
                s = store.lastStageAttempt(stage)
                if s.numCompleteTasks():  # a stage whose shuffle was there already runs no task
                    ran.append((s.inputBytes(), s.shuffleWriteBytes(), s.memoryBytesSpilled() + s.diskBytesSpilled(), s.executorRunTime() / 1000))
        sums = [sum(c) for c in zip(*ran, strict=True)] or [0, 0, 0, 0.0]
        rows.append((name, len(ran), *sums[:3], float(sums[3])))

    trips, grid = _trips(spark, sf_dir, source, n)
    counted("assemble", trips.count)
    size, fitted = trips.count(), []
    counted("collect and fit", lambda: fitted.append(models.fit(trips, grid, eps, seed=seed)))
    counted("synthesize", lambda: files.force(synthesis.synthesize(spark, fitted[0], size, seed)))
    counted("ngram", lambda: files.force(ngram.ngram_perturb(trips, grid, eps, seed=seed)))
    trips.unpersist()
    return spark.createDataFrame(rows, "component string, stages int, input_bytes long, shuffle_bytes long, spilled_bytes long, task_seconds double")


def knowledge_comparison(spark, sf_dir, eps=1.0, n=4, seed=1, walkers=1000) -> DataFrame:
    """Nine measures on walks between places: both forms of the compared method, and the synthesizer."""
    p = walks.poi_walk(spark, sf_dir, walkers)
    grid = make_grid(p, n)
    trips = trajectory.assemble(p, grid).persist()
    know = ngram.knowledge_from_sites(walks.sites(spark, sf_dir), grid)
    sets = {"ngram": published(spark, trips, grid, "ngram", eps, seed), "knowledge_ngram": ngram.ngram_perturb(trips.withColumn("hour", F.pmod("traj_id", F.lit(24))), grid, eps, 2, seed, know).persist(), "synthesizer": published(spark, trips, grid, "synthesizer", eps, seed)}
    return _all([_tagged(metrics.evaluate_all(trips, s, grid), method=m) for m, s in sets.items()])


def attack_comparison(spark, sf_dir, sources=("order_walk", "userday_walk"), eps=1.0, n=6, seed=1, kappas=attacks.KAPPAS, methods=METHODS) -> DataFrame:
    """(source, attack, method, kappa, ratio): both attacks against both methods."""
    parts = []
    for source in sources:
        trips, grid = _trips(spark, sf_dir, source, n)
        for m in methods:
            syn = published(spark, trips, grid, m, eps, seed)
            parts.append(_tagged(attacks.resilience(attacks.reidentification(trips, syn, grid), kappas), source=source, attack="reidentification", method=m))
            parts.append(_tagged(attacks.resilience(attacks.outlier_matches(trips, syn, grid), kappas), source=source, attack="outlier", method=m))
    return _all(parts)


def estimate_error(spark, sf_dir, source="customer_walk", n=3, eps=1.0, seeds=range(1, 21)) -> DataFrame:
    """(item, z): the mean estimate of each length over seeds, in standard errors from the truth."""
    trips, grid = _trips(spark, sf_dir, source, n)
    size = trips.count()
    truth = trips.groupBy(models.length_item(grid.cells).alias("item")).agg(F.count("*").alias("f"))
    runs = _all([_tagged(oue.fused(trips, [("length", models.length_item(grid.cells), 0, grid.cells, eps)], int(s)), seed=int(s)) for s in seeds])
    est = oue.estimate(runs, eps).groupBy("item").agg(F.avg("est").alias("mean"), F.var_samp("est").alias("var"), F.count("*").alias("runs"))
    sd = math.sqrt(oue.variance(size, eps))
    return est.join(F.broadcast(truth), "item", "left").na.fill(0, ["f"]).select("item", ((F.col("mean") - F.col("f")) / F.lit(sd) * F.sqrt("runs")).alias("z"), (F.col("var") / F.lit(sd * sd)).alias("variance_ratio"))


def role_changes(spark, sf_dir, eps=2.0, seed=3) -> DataFrame:
    """A domain without space: changes of role in conversations, perturbed, counted and estimated beside the truth."""
    from pyspark.sql import Window

    c = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role")
    pair = F.concat_ws(">", F.lag("role").over(Window.partitionBy("conv_id").orderBy("turn", "role")), "role")
    steps = c.withColumn("pair", pair).where(F.col("pair").contains(">"))
    names = [r[0] for r in steps.select("pair").distinct().orderBy("pair").collect()]
    item = F.array_position(F.array(*[F.lit(x) for x in names]), F.col("pair")).cast("int") - 1
    counts = oue.fused(steps.select(F.xxhash64("conv_id", "turn").alias("traj_id"), item.alias("item")), [("pair", F.col("item"), 0, len(names), eps)], seed)
    truth = steps.groupBy("pair").agg(F.count("*").alias("f"))
    est = oue.estimate(counts, eps).withColumn("pair", F.get(F.array(*[F.lit(x) for x in names]), F.col("item")))
    return est.join(truth, "pair").select("pair", "f", F.round("est", 3).alias("est"))


QUERIES = [
    ("workload_utility", utility),
    ("workload_ablation", ablation),
    ("workload_component_times", component_times),
    ("workload_side_sweep", side_sweep),
    ("workload_lambda_sweep", lambda_sweep),
    ("workload_query_size_sweep", query_size_sweep),
    ("workload_quantile_sweep", quantile_sweep),
    ("workload_scalability", scalability),
    ("workload_stage_costs", stage_costs),
    ("workload_knowledge_comparison", knowledge_comparison),
    ("workload_attacks", attack_comparison),
    ("workload_estimate_error", estimate_error),
    ("workload_role_changes", role_changes),
]
