import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from mobility_ldp.operators import attacks, granularity, metrics, ngram
from mobility_ldp.operators.grid import Grid

G = Grid(6, 0.0, 6.0, 0.0, 6.0)


def trips(spark, rows):
    return spark.createDataFrame([(k, r) for k, r in enumerate(rows)], "traj_id bigint, cells array<int>").withColumn("n_cells", F.size("cells"))


def value(df):
    return df.first()["value"]


def counts(spark, xs):
    return spark.createDataFrame(list(enumerate(xs)), "k int, n double").where("n > 0")


@pytest.mark.parametrize("p, q, nat, two", [((0.5, 0.5), (1, 0), 0.2157616, 0.3112781), ((0.25, 0.25, 0.5), (0.5, 0.25, 0.25), 0.0424748, None)])
def test_jsd(spark, p, q, nat, two):
    a, b = counts(spark, list(map(float, p))), counts(spark, list(map(float, q)))
    assert abs(value(metrics.jsd(a, b, ["k"])) - nat) < 1e-6
    if two:
        assert abs(value(metrics.jsd(a, b, ["k"], 2)) - two) < 1e-6


@pytest.mark.parametrize("order, want", [("12345", 0), ("12354", 0.0013), ("13245", 0.0131), ("1234x", 0.0464), ("1235x", 0.0593), ("3421x", 0.2972), ("x2xxx", 0.8108), ("xxxxx", 1)])
def test_hotspot_values(spark, order, want):
    real = trips(spark, [[c] for c in range(5) for _ in range(50 - c)])
    syn = trips(spark, [[int(c) - 1 if c != "x" else 20 + k] for k, c in enumerate(order) for _ in range(50 - k)])
    assert abs(value(metrics.hotspot_error(real, syn)) - want) < 1e-4


@pytest.mark.parametrize("s, want", [((4, 4, 0), 1), ((1, 3, 5), -1), ((3, 5, 1), 1 / 3)])
def test_kendall(spark, s, want):
    # three cells of four; the fourth is made the least on both sides of all pairs by leaving it out of the expectation
    g = Grid(2, 0.0, 1.0, 0.0, 1.0)
    mk = lambda v: trips(spark, [[c] for c, n in enumerate(v) for _ in range(n)])
    full = value(metrics.kendall(mk((5, 3, 1)), mk(s), g)) * 6
    extra = sum(1 for _ in range(3))  # pairs with the empty cell are alike or tied
    assert abs((full - extra) / 3 - want) < 1e-9


def test_identical_and_disjoint(spark):
    a = trips(spark, [[0, 1, 2], [7, 8], [14]] * 5)
    m = {r["metric"]: r["value"] for r in metrics.evaluate_all(a, a, G).collect()}
    assert m["kendall"] == 1 and m["pattern_f1"] == 1
    assert all(abs(v) < 1e-12 for k, v in m.items() if k not in ("kendall", "pattern_f1"))
    b = trips(spark, [[35, 34]] * 15)
    assert abs(value(metrics.density_error(a, b)) - math.log(2)) < 1e-12
    assert value(metrics.pattern_f1(a, b)) == 0 and value(metrics.pattern_error(a, b)) == 1


def test_pattern_error(spark):
    a = trips(spark, [[0, 1]] * 10 + [[1, 2]] * 4)
    b = trips(spark, [[0, 1]] * 5 + [[1, 2]] * 4)
    assert value(metrics.pattern_error(a, b)) == 0.25
    assert value(metrics.pattern_error(a, b, outside="zero")) == 0.25


def test_distances(spark):
    t = trips(spark, [[0, 1, 8], [3], [0, 7, 14, 7]])
    d = [r["d"] for r in t.select(metrics.travelled("cells", G).alias("d")).collect()]
    assert np.allclose(d, [1 + 2**0.5, 0, 3 * 2**0.5])
    d = [r["d"] for r in t.select(metrics.diameter("cells", G).alias("d")).collect()]
    assert np.allclose(d, [5**0.5, 0, 8**0.5])


def test_query_modes(spark):
    a = trips(spark, [[0, 1, 2], [7, 8]] * 20)
    for mode in ("centre", "uniform"):
        assert value(metrics.query_error(a, a, G, points=mode)) == 0
    for mode in ("joint", "marginal"):
        assert value(metrics.trip_error(a, a, mode)) == 0


def test_warping_distance():
    c = np.array([(0, 0), (1, 0), (1, 1)], float)
    assert attacks.dtw([0, 1], [0, 2], c) == 1 and attacks.dtw([0, 1, 2], [0, 2], c) == 1


def brute_dtw(a, b, c):
    d = np.full((len(a) + 1, len(b) + 1), np.inf)
    d[0, 0] = 0
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            d[i, j] = np.linalg.norm(c[a[i - 1]] - c[b[j - 1]]) + min(d[i - 1, j], d[i, j - 1], d[i - 1, j - 1])
    return d[-1, -1]


def test_attacks_against_brute_force(spark):
    draw = np.random.default_rng(2)

    def some(n):
        out = []
        for _ in range(n):
            w = [int(draw.integers(36))]
            for _ in range(int(draw.integers(8))):
                w.append(int(draw.choice(G.neighbours(w[-1]))))
            out.append(w)
        return out

    real, syn = some(120), some(120)
    zone = set(attacks.central_zone(G))
    assert zone == {14, 15, 20, 21}
    c = np.array([G.centre(k) for k in range(36)])
    zr, zs = [[x for x in w if x in zone] for w in real], [[x for x in w if x in zone] for w in syn]
    zr, zs = [w for w in zr if w], [w for w in zs if w]
    limit = 0.2 * max(brute_dtw(a, b, c) for a in zr for b in zr)
    want = sorted(sum(brute_dtw(a, b, c) <= limit + 1e-9 for b in zs) for a in zr)
    got = attacks.reidentification(trips(spark, real), trips(spark, syn), G)
    assert sorted(m for r in got.collect() for m in [r["matches"]] * r["n"]) == want
    ratios = [r["ratio"] for r in attacks.resilience(got).orderBy("kappa").collect()]
    assert ratios == sorted(ratios, reverse=True)
    length = lambda w: sum(np.linalg.norm(c[a] - c[b]) for a, b in zip(w, w[1:]))
    lr = np.array([length(w) for w in real])
    for r in attacks.outlier_matches(trips(spark, real), trips(spark, syn), G).collect():
        assert r["matches"] == int((np.abs(lr - r["d"]) <= 0.25 * (lr.max() - lr.min()) + 1e-6).sum())
    for method in ("iqr", "ends"):
        attacks.outlier_matches(trips(spark, real), trips(spark, syn), G, method=method).collect()


@pytest.mark.parametrize("users, points, f, root, printed", [(500_000, 69.75, 15.6, 5.82, 13.57), (361_591, 34.13, 15, 6.55, 17.15), (348_144, 125.02, 5, 8.12, 26.39), (1_000_000, 35.98, 25, 6.46, 16.67)])
def test_guideline(users, points, f, root, printed):
    assert abs(granularity.recommend(users, points, 1 / f, 1.0)[0] - root) < 0.01
    assert abs(granularity.recommend(users, points, 1 / f, 1.0, form="printed")[0] - printed) < 0.01
    eps_t = 1.0 / f / points
    n = users * points
    assert abs(granularity.argmin_grid(n, n, 1 / 9, eps_t) - root / 2.5) < 1


def test_ngram_perturber(spark):
    g = Grid(3, 0.0, 3.0, 0.0, 3.0)
    w = ngram.Perturber(g, 1.0, 2)
    draw = np.random.default_rng(0)
    for _ in range(30):
        cost = draw.random((int(draw.integers(1, 5)), 9))
        got = w.rebuild(cost)
        import itertools

        best = min((sum(cost[k, c] for k, c in enumerate(p)) for p in itertools.product(range(9), repeat=len(cost)) if all(b in g.neighbours(a) for a, b in zip(p, p[1:]))))
        assert abs(sum(cost[k, c] for k, c in enumerate(got)) - best) < 1e-12
    rows = [[0, 1, 2, 5], [4], [8, 7, 6, 3, 0]]
    t = trips(spark, rows)
    for n in (1, 2, 3):
        out = ngram.ngram_perturb(t, g, 1.0, n, 1).orderBy("traj_id").collect()
        assert [r["n_cells"] for r in out] == [4, 1, 5]
        assert all(b in g.neighbours(a) for r in out for a, b in zip(r["cells"], r["cells"][1:]))
    sure = ngram.ngram_perturb(t, g, 1e6, 2, 1).orderBy("traj_id").collect()
    assert [r["cells"] for r in sure] == rows


def test_knowledge(spark, sf):
    from mobility_ldp.sources import walks

    g = Grid(4, -4.0, 4.0, -4.0, 4.0)
    k = ngram.knowledge_from_sites(walks.sites(spark, sf), g)
    assert len(k.category) == 16 and set(k.region) == {0, 1, 2, 3}
    t = trips(spark, [[0, 1, 5], [10, 11]]).withColumn("hour", F.lit(9))
    assert ngram.ngram_perturb(t, g, 1.0, 2, 1, k).count() == 2


def test_compared_method_is_timed_on_all_trips(spark, monkeypatch):
    from mobility_ldp.plans import workloads

    seen = []
    monkeypatch.setattr(workloads.ngram, "ngram_perturb", lambda trips, *a, **k: seen.append(trips.count()) or trips)
    workloads.component_times(spark, "/root/testdata/sf0.01", n=3)
    assert seen == [workloads._trips(spark, "/root/testdata/sf0.01", "order_walk", 3)[0].count()] and seen[0] > 2000


def test_trips_perturbed_together_are_those_perturbed_alone(spark, monkeypatch):
    r = np.random.default_rng(4)
    monkeypatch.setattr(ngram, "BLOCK", 4000)
    monkeypatch.setattr(ngram, "TABLE", 1000)
    g = Grid(4, 0.0, 8.0, 0.0, 4.0)
    know = ngram.Knowledge(np.arange(16) % 3, np.arange(16) // 8, np.array([[h % 3 != k for h in range(24)] for k in range(3)]))
    rows = [(k, [int(c) for c in r.integers(0, 16, r.integers(0, 9))] if k % 50 else None, int(r.integers(0, 24))) for k in range(400)]
    t = spark.createDataFrame(rows, "traj_id bigint, cells array<int>, hour int").coalesce(1)
    for n, k in ((1, None), (2, None), (3, None), (2, know)):
        alone = ngram.Perturber(g, 5.0, n, k)
        got = {x["traj_id"]: (x["cells"], x["n_cells"]) for x in ngram.ngram_perturb(t, g, 5.0, n, 3, k).collect()}
        want = {i: (alone.perturb(i, np.array(c), 3, h).tolist(), len(c)) if c else ([], 0) for i, c, h in rows}
        assert got == want
    secret = b"s" * 32
    alone, ids = ngram.Perturber(g, 5.0, 2), np.arange(30)
    many = alone.perturb_many(ids, np.tile([0, 1, 6], (30, 1)), secret)
    assert [alone.perturb(int(i), np.array([0, 1, 6]), secret).tolist() for i in ids] == many.tolist()


def test_trips_are_perturbed_a_batch_at_a_time():
    import time

    g = Grid(6, 0.0, 6.0, 0.0, 6.0)
    w, cells = ngram.Perturber(g, 1.0, 2), np.random.default_rng(1).integers(0, 36, (2000, 8))
    t = time.thread_time()
    w.perturb_many(np.arange(2000), cells, 1)
    many = time.thread_time() - t
    t = time.thread_time()
    for k in range(200):
        w.perturb(k, cells[k], 1)
    assert many < time.thread_time() - t  # ten times as many


def test_measures_of_a_tally_are_those_of_the_frames(spark, monkeypatch):
    r = np.random.default_rng(6)
    for g in (Grid(4, 0.0, 4.0, 0.0, 9.0), Grid(3, -1.0, -1.0, 0.0, 2.0)):
        def some(n, skew, g=g):
            return trips(spark, [[int(c * skew) % g.cells for c in r.integers(0, g.cells, r.integers(1, 9))] for _ in range(n)])

        real = some(300, 1.0)
        for syn in (some(200, 0.7), real, trips(spark, [[g.cells - 1]] * 3)):
            want = {x["metric"]: x["value"] for x in metrics.evaluate_all(real, syn, g).collect()}
            got = metrics.measures(metrics.tallied(real, g), metrics.tallied(syn, g), g, metrics.range_queries(spark, g).collect())
            assert list(got) == list(want) and all(abs(got[k] - want[k]) < 1e-9 for k in want), (got, want)
    # two touching rows of one trip, merged within a task
    monkeypatch.setattr(metrics, "MAX_TALLY", 3)
    assert metrics.tallied(real, g) is None


def test_experiments_take_one_pass_a_set(spark, sf, monkeypatch):
    from mobility_ldp.plans import workloads

    monkeypatch.setattr(metrics, "evaluate_all", None)
    t = workloads.ablation(spark, sf, ("customer_walk",), n=3)
    assert t.count() == 45
    monkeypatch.undo()
    monkeypatch.setattr(metrics, "MAX_TALLY", 3)  # the way of large tallies
    slow = {(x["variant"], x["metric"]): x["value"] for x in workloads.ablation(spark, sf, ("customer_walk",), n=3).collect()}
    assert all(abs(slow[x["variant"], x["metric"]] - x["value"]) < 1e-9 for x in t.collect())


def test_warping_of_many_walks_and_their_tasks(spark, monkeypatch):
    r = np.random.default_rng(8)
    centres = np.array([G.centre(c) for c in range(36)])

    def plain(a, b):
        d = np.full((len(a) + 1, len(b) + 1), np.inf)
        d[0, 0] = 0.0
        for i in range(1, len(a) + 1):
            for j in range(1, len(b) + 1):
                d[i, j] = np.linalg.norm(centres[a[i - 1]] - centres[b[j - 1]]) + min(d[i - 1, j], d[i - 1, j - 1], d[i, j - 1])
        return d[-1, -1]

    walks = [[int(c) for c in r.integers(0, 36, r.integers(1, 7))] for _ in range(40)]
    known, size = attacks._padded(walks)
    for a in walks[:5]:
        assert np.allclose(attacks.dtw_many(np.array(a), known, size, centres), [plain(a, b) for b in walks])
    seen = []
    real = attacks.zone_walks
    monkeypatch.setattr(attacks, "zone_walks", lambda *a: seen.append(real(*a)) or seen[-1])
    t = trips(spark, [[14, 15, 20][: 1 + k % 3] for k in range(30)])
    out = attacks.reidentification(t, t, G)
    assert sum(x["n"] for x in out.collect()) == 30
    assert "RepartitionByExpression" in out._jdf.queryExecution().toString() or "REPARTITION" in out._jdf.queryExecution().toString()
