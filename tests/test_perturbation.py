import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from mobility_ldp.functions import rng
from mobility_ldp.operators import budget, errors, models, oue, trajectory
from mobility_ldp.operators.grid import Grid, make_grid
from mobility_ldp.plans import workloads
from mobility_ldp.sources import walks


def test_keyed_uniform(spark):
    got = spark.range(1).select(rng.u01(1, 2, 3).alias("u")).first()["u"]
    assert got == 2960013855883 / 2**48


@pytest.mark.parametrize("eps, q, v", [(0.5, 0.3775407, 15.670792), (1.0, 0.2689414, 3.682694), (2.0, 0.1192029, 0.724062)])
def test_constants(eps, q, v):
    assert abs(oue.q_of(eps) - q) < 1e-7 and abs(oue.variance(1, eps) - v) < 1e-6


def test_estimate(spark):
    c = spark.createDataFrame([(0, 40, 100)], "item int, ones bigint, n bigint")
    assert abs(oue.estimate(c, 1.0).first()["est"] - 56.720931) < 1e-6
    with pytest.raises(ValueError):
        oue.estimate(c.withColumn("eps", F.lit(1.0)), 1.0)


@pytest.mark.parametrize("d", [2, 3, 4])
@pytest.mark.parametrize("eps", [0.5, 1.0, 2.0])
def test_privacy_is_tight(d, eps):
    assert abs(oue.worst_ratio(d, eps) - math.exp(eps)) < 1e-9
    assert oue.worst_ratio(d, eps, null_report=True) <= math.exp(eps) + 1e-9


def test_budget():
    b = budget.plan_budget(1.0, 8)
    assert (round(b.e1, 9), round(b.per_move, 9), round(b.e2, 9), round(b.e3, 9)) == (0.1, 0.09, 0.72, 0.18)
    b.spend("a", 0.6)
    with pytest.raises(ValueError):
        b.spend("b", 0.6)
    with pytest.raises(ValueError):
        budget.plan_budget(1.0, 8, "custom", (0.5, 0.5, 0.5))


def test_ratio_variance():
    assert abs(errors.ratio_variance(30.0, 120.0, 100.0, 100.0) - 0.0073785) < 1e-6


def test_ratio_variance_by_simulation():
    draw = np.random.default_rng(1)
    x, y = draw.normal(3000, 30, 200_000), draw.normal(12000, 30, 200_000)
    assert abs(np.var(x / y) / errors.ratio_variance(3000.0, 12000.0, 900.0, 900.0) - 1) < 0.05


def test_estimates_are_unbiased(spark, sf):
    z = workloads.estimate_error(spark, sf, seeds=range(1, 16)).collect()
    assert max(abs(r["z"]) for r in z) < 4.5
    assert 0.4 < np.mean([r["variance_ratio"] for r in z]) < 1.8


def test_fused_does_not_depend_on_partitions(spark, sf):
    p = walks.order_walk(spark, sf)
    g = make_grid(p, 3)
    t = trajectory.assemble(p, g)
    f = [("length", models.length_item(9), 0, 9, 1.0), ("intra", models.kept_moves(models.state_items(g), 4), 4, g.states, 0.5)]
    a = sorted(map(tuple, oue.fused(t.repartition(7), f, 3).collect()))
    b = sorted(map(tuple, oue.fused(t.coalesce(1), f, 3).collect()))
    assert a == b
    n = t.count()
    assert {r[3] for r in a if r[0] == "intra"} == {n * 4}  # padded: the number of reports tells nothing


def test_only_counts_leave_the_users(spark, sf):
    p = walks.order_walk(spark, sf)
    t = trajectory.assemble(p, make_grid(p, 3))
    out = oue.fused(t, [("length", models.length_item(9), 0, 9, 1.0)], 3)
    assert out.columns == ["feature", "item", "ones", "n"]
    plan = out._jdf.queryExecution().executedPlan().toString()
    after = plan[: plan.index("MapInArrow")]
    assert "traj_id" not in after


def test_simulation_has_the_same_law():
    counts, n = {0: 300, 1: 100}, 1000
    draws = np.array([oue.simulate(counts, n, 3, 1.0, s) for s in range(400)])
    est = (draws - n * oue.q_of(1.0)) / (0.5 - oue.q_of(1.0))
    sd = (oue.variance(n, 1.0, 300, exact=True) / 400) ** 0.5
    assert np.abs(est.mean(0) - [300, 100, 0]).max() < 4.5 * sd


def test_own_length_split_is_biased():
    """Reports with different budgets cannot be estimated with one."""
    n, d = 20000, 5
    keys = rng.keyed(1, np.arange(2 * n))
    a, b = oue.raised(keys[:n], np.zeros(n, int), d, 0.5), oue.raised(keys[n:], np.ones(n, int), d, 3.0)
    ones = a.sum(0) + b.sum(0)
    est = (ones - 2 * n * oue.q_of(1.75)) / (0.5 - oue.q_of(1.75))
    assert abs(est[2]) > 10 * oue.variance(2 * n, 1.75) ** 0.5


def test_norm_sub():
    x = models.norm_sub(np.array([5.0, 3.0, -2.0, 0.5]), 6.0)
    assert abs(x.sum() - 6) < 1e-12 and x.min() >= 0 and x[2] == 0


def test_best_quantile_curve(spark, sf):
    from mobility_ldp.plans import queries

    rows = queries.error_curve(spark, sf).orderBy("k").collect()
    assert rows[0]["bias"] > rows[-1]["bias"] == 0 and rows[0]["noise"] < rows[-1]["noise"]


def test_state_items(spark):
    g = Grid(3, 0.0, 1.0, 0.0, 1.0)
    ids = {p: k for k, p in enumerate(g.pairs())}
    df = spark.createDataFrame([([0, 1, 4, 8],), ([5],), ([0, 8],)], "cells array<int>")
    got = [r["x"] for r in df.select(models.state_items(g).alias("x")).collect()]
    assert got == [[ids[0, 1], ids[1, 4], ids[4, 8]], [], [-1]]


def test_noise_is_secret_by_default(spark, sf):
    p = walks.order_walk(spark, sf)
    t = trajectory.assemble(p, make_grid(p, 3))
    f = [("length", models.length_item(9), 0, 9, 1.0), ("intra", models.kept_moves(models.state_items(make_grid(p, 3)), 3), 3, 40, 1.0)]
    ask = lambda **k: oue.fused(t, f, **k)
    one = ask()
    a, again, b = (sorted(map(tuple, x.collect())) for x in (one, one, ask()))
    assert a == again and a != b  # a retry raises the same bits, another collection others
    assert sorted(map(tuple, ask(secret=b"x").collect())) == sorted(map(tuple, ask(secret=b"x").collect()))
    # both estimate the truth
    n = t.count()
    truth = {r[0]: r[1] for r in t.groupBy(models.length_item(9).alias("i")).count().collect()}
    q, sd = oue.q_of(1.0), oue.variance(n, 1.0, n, exact=True) ** 0.5
    for rows in (a, b):
        for name, item, ones, total in rows:
            if name == "length":
                assert abs((ones - total * q) / (0.5 - q) - truth.get(item, 0)) < 5 * sd
    words = rng.secret_words(b"k", np.arange(200), 0, 500)
    assert abs(words.mean() / 2**32 - 0.5) < 0.01 and len(np.unique(words)) > 99_000


def test_knowledge_keeps_its_promise():
    """Brute force over a tiny grid: the ratio of chances under any two windows, at every hour, and the levels by hand."""
    from mobility_ldp.operators import ngram

    g = Grid(3, 0.0, 3.0, 0.0, 3.0)
    hours = np.array([[True] * 24, [h < 12 for h in range(24)], [h >= 6 for h in range(24)]])
    know = ngram.Knowledge(np.arange(9) % 3, np.array([0, 0, 1, 0, 0, 1, 2, 2, 1]), hours)
    w = ngram.Perturber(g, 1.0, 2, know)
    for hour in (0, 8, 20):
        p = np.array([w.chances(np.array(x), 1.5, hour) for x in w.grams[2]])
        assert np.allclose(p.sum(1), 1)
        open_ = hours[know.category[w.grams[2]], hour].all(1)
        assert (p[:, ~open_] == 0).all() and (p[:, open_] > 0).all()
        on = p[:, open_]
        assert (on.max(0) / on.min(0)).max() <= np.exp(1.5) + 1e-9
    window, total = w.grams[2][5], np.zeros(3)
    for r in range(3):
        total[r] = np.exp(-0.75 * w.apart[know.region[window[0]], r] / 2)
    by_region = np.bincount(know.region[w.grams[2][:, 0]], w.chances(window, 1.5, 8), 3)
    assert np.allclose(by_region, total / total.sum())
    plain = ngram.Perturber(g, 1.0, 2)
    p = np.array([plain.chances(np.array(x), 1.5, 8) for x in plain.grams[2]])
    assert (p.max(0) / p.min(0)).max() <= np.exp(1.5) + 1e-9


def test_streams_draw_the_bits_of_long_reports(monkeypatch):
    eps, d, each, n = 0.05, 150, 60, 400
    keys, items = rng.keyed(2, np.arange(n)), np.full((n, each), -1)
    items[:, 0] = 7
    got = oue.streamed(keys, items, d, eps)
    q, size = oue.q_of(eps), n * each
    z = (np.delete(got, 7) - size * q) / (size * q * (1 - q)) ** 0.5
    assert abs(z.mean()) < 4 / d**0.5 and 0.75 < z.std() < 1.25 and abs(got[7] - (size - n) * q - n / 2) < 4 * size**0.5 / 2
    # one trip at a time, and with so few gaps foreseen that most trips need more
    parts = sum(oue.streamed(keys[k : k + 1], items[k : k + 1], d, eps) for k in range(n))
    monkeypatch.setattr(oue.math, "sqrt", lambda x: 0.0)
    few = oue.streamed(keys, items, d, eps)
    assert (parts == got).all() and (few == got).all()


def test_trips_of_experiments_are_dealt_over_all_cores(spark, sf):
    trips, _ = workloads._trips(spark, sf, "order_walk", 3)
    assert trips.rdd.getNumPartitions() >= 2 * spark.sparkContext.defaultParallelism
    trips.unpersist()


def test_lambda_sweep_equals_its_side(spark, sf):
    rows = workloads.lambda_sweep(spark, sf, lams=(0.5, 2.5)).collect()
    assert rows[1]["query_error"] == workloads.side_sweep(spark, sf, sides=(rows[1]["n"],), eps=1.0, methods=("synthesizer",)).first()["query_error"]
