"""Quicker ways of large tables, held against the plain ones."""

import numpy as np
from pyspark.sql import functions as F

from mobility_ldp.functions import rng
from mobility_ldp.operators import attacks, metrics, models, ngram, oue, trajectory
from mobility_ldp.operators.grid import Grid, make_grid
from mobility_ldp.plans import workloads
from mobility_ldp.sources import walks

G = Grid(6, 0.0, 6.0, 0.0, 3.0)
CENTRES = np.array([G.centre(c) for c in range(36)])


def some_walks(n, seed, longest=9):
    r = np.random.default_rng(seed)
    return [list(w) for w in sorted({tuple(r.choice([14, 15, 20, 21], r.integers(1, longest)).tolist()) for _ in range(n)})]


def test_walks_that_begin_alike_share_their_warping():
    a, b = some_walks(200, 1), [w for w in some_walks(300, 2) if w[0] == 14]
    known, size = attacks._padded(b)
    want = np.array([attacks.dtw_many(np.array(w), known, size, CENTRES) for w in a])
    mine, other = attacks.Beginnings(*attacks._padded(a)), attacks.Beginnings(known, size)
    assert len(other.parent) - 1 == len({tuple(w[:k]) for w in b for k in range(1, len(w) + 1)})
    apart = attacks.distances_of(CENTRES)
    got = dict((k, row[other.ends].copy()) for k, row in mine.against(other, apart, np.inf))
    assert all((got[k] == want[k]).all() for k in range(len(a)))
    limit, left = float(np.quantile(want, 0.01)), 0
    for k, row in mine.against(other, apart, limit):
        left += row is None
        assert (want[k] > limit).all() if row is None else (row[other.ends] <= limit).tolist() == (want[k] <= limit).tolist()
    assert left


def test_attacks_know_the_beginnings_of_walks(spark, monkeypatch):
    plain = attacks.dtw_many
    monkeypatch.setattr(attacks, "BLOCK", 7)
    monkeypatch.setattr(attacks, "MAX_WALKS", 20)  # several sets of walks, in several blocks each
    real, syn = some_walks(40, 3, 6), some_walks(60, 4, 6)
    table = lambda ws: spark.createDataFrame([(k, w, len(w)) for k, w in enumerate(ws)], "traj_id long, cells array<int>, n_cells int")
    padded = lambda ws: attacks._padded(ws)
    limit = 0.2 * max(plain(np.array(w), *padded(real), CENTRES).max() for w in real)
    want = {tuple(w): int((plain(np.array(w), *padded(syn), CENTRES) <= limit + 1e-9).sum()) for w in real}
    assert {tuple(r["walk"]): r["matches"] for r in attacks.reidentification(table(real), table(syn), G).collect()} == want


def test_distances_are_those_of_the_column(spark):
    r = np.random.default_rng(5)
    rows = [(k, r.integers(0, 36, r.integers(0, 9)).tolist()) for k in range(300)]
    t = spark.createDataFrame(rows, "traj_id long, cells array<int>")
    want = t.select(F.round(metrics.travelled("cells", G), 9).alias("d")).groupBy("d").agg(F.count("*").alias("n"))
    assert sorted(map(tuple, attacks.distances(t, G).collect())) == sorted(map(tuple, want.collect()))


def test_gathered_points_give_the_trips_of_assemble(spark, sf):
    rows = lambda df: sorted((r["traj_id"], r["cells"], r["n_cells"]) for r in df.collect())
    for source in ("order_walk", "customer_walk", "userday_walk", "poi_walk"):
        p = walks.WALKS[source](spark, sf)
        for n in (1, 2, 7):
            g = make_grid(p, n)
            assert rows(trajectory.walked(trajectory.gathered(p), g)) == rows(trajectory.assemble(p, g))
    # points of one order, without a place, outside the box, and not numbers
    inf, nan = float("inf"), float("nan")
    odd = [(1, 2, 5.5, 0.1), (1, 2, 0.5, 2.9), (1, 1, 9.0, -4.0), (1, 3, None, 1.0), (2, 1, None, None), (3, 1, inf, -inf), (3, 2, nan, 1.0), (4, 7, 3.1, 1.6), (4, 7, 0.1, 1.4), (4, 7, 3.1, 1.6)]
    p = spark.createDataFrame(odd, "traj_id int, ord int, x double, y double").coalesce(1)
    assert rows(trajectory.walked(trajectory.gathered(p), G)) == rows(trajectory.assemble(p, G))
    assert trajectory.walked(trajectory.gathered(p), G).schema["traj_id"].dataType == p.schema["traj_id"].dataType


def test_summed_reports_have_the_law_of_their_bits():
    for each, d, eps, n in ((8, 5, 1.0, 6000), (40, 60, 0.05, 3000), (700, 31, 0.001, 3000), (9, 1, 4.0, 5000)):
        keys, items = rng.keyed(4, np.arange(n)), np.full((n, each), -1)
        items[:, 0], items[:, 1] = 0, np.arange(n) % d
        items[::2, 2] = 0
        drawn = oue.Summed(each, d, eps)
        one = np.stack([drawn.add(keys[k : k + 1], items[k : k + 1]) for k in range(n)])
        assert (one.sum(0) == drawn.add(keys, items)).all() and one.min() >= 0 and one.max() <= each
        q, true = drawn.q, np.stack([(items == c).sum(1) for c in range(d)], 1)
        mean, var = (each - true) * q + true / 2, (each - true) * q * (1 - q) + true / 4
        z = (one - mean) / np.sqrt(var)
        # means by place, the spread, no tie between places nor between trips
        assert (np.abs(z.mean(0)) < 4.5 / n**0.5).all()
        assert abs((z**2).mean() - 1) < 5 * (2 + (1 / var).mean()) ** 0.5 / (n * d) ** 0.5
        if d > 1:
            assert abs((z[:, 0] * z[:, 1]).mean()) < 4.5 / n**0.5
        assert abs((z[1:] * z[:-1]).mean()) < 4.5 / (n * d) ** 0.5
    # all values, by a place without reports of its own
    each, n = 12, 40_000
    got = oue.Summed(each, 1, 1.0)
    seen = np.bincount([int(got.add(rng.keyed(9, np.array([k])), np.full((1, each), -1))[0]) for k in range(n)], minlength=each + 1)
    want = n * np.diff(np.concatenate([[0.0], oue._cdf(each, oue.q_of(1.0)), [1.0]]))
    assert ((seen - want)[want > 5] ** 2 / want[want > 5]).sum() < 40
    exact = np.array([sum(float(np.prod([(each - i) / (i + 1) for i in range(j)])) * 0.3**j * 0.7 ** (each - j) for j in range(k + 1)) for k in range(each)])
    assert np.allclose(oue._cdf(each, 0.3), exact, atol=1e-13)


def test_parts_of_cells_are_those_of_the_hashed_column(spark):
    r = np.random.default_rng(6)
    rows = [(int(r.integers(-(1 << 62), 1 << 62)), r.integers(0, 36, r.integers(0, 40)).tolist()) for _ in range(200)]
    t = spark.createDataFrame(rows, "traj_id long, cells array<int>")
    for ids in (t, t.withColumn("traj_id", (F.col("traj_id") % 100_000).cast("int")), t.withColumn("traj_id", F.col("traj_id").cast("string"))):
        for sub in (1, 8):
            part = lambda axis: F.floor(rng.u01(7, F.col("traj_id"), F.col("pos"), axis, engine="xx") * sub)  # noqa: B023, E731
            p = ids.select("traj_id", F.posexplode("cells").alias("pos", "cell"))
            want = p.select("cell", part("x").alias("a"), part("y").alias("b")).groupBy("cell", "a", "b").agg(F.count("*").alias("n")).collect()
            at = lambda c, k, size: (c + (k + 0.5) / sub) * size  # noqa: B023, E731
            want = sorted((at(c % 6, a, 1.0), at(c // 6, b, 0.5), n) for c, a, b, n in want)
            got = sorted(map(tuple, metrics.spots(ids, G, "uniform", 7, sub).collect()))
            assert np.allclose(got, want, atol=1e-12)
    # the real set's may be kept
    a = metrics.query_error(t, t.limit(50), G, points="uniform", seed=7).first()["value"]
    assert a == metrics.query_error(t, t.limit(50), G, points="uniform", seed=7, known=metrics.spots(t, G, "uniform", 7)).first()["value"]


def test_moves_of_a_batch_are_those_of_the_column(spark, sf):
    p = walks.order_walk(spark, sf)
    g = make_grid(p, 5)
    t = trajectory.assemble(p, g).unionByName(spark.createDataFrame([(-1, [3], 1), (-2, [], 0), (-3, [0, 24, 18, 18, 0, 1], 6)], "traj_id long, cells array<int>, n_cells int"))
    for l_k in (1, 4, 30):
        want = {r[0]: r[1] for r in t.select("traj_id", F.filter(models.kept_moves(models.state_items(g), l_k), lambda x: x >= 0)).collect()}
        table = t.select("traj_id", "cells").toArrow().combine_chunks()
        got = models.Moves(g, l_k)(table.column("cells").chunk(0)).to_pylist()
        assert dict(zip(table.column("traj_id").to_pylist(), got, strict=True)) == want
        col = F.filter(models.kept_moves(models.state_items(g), l_k), lambda x: x >= 0)
        by = lambda items: sorted(map(tuple, oue.fused(t, [("intra", items, l_k, g.states, 0.1)], 3).collect()))  # noqa: B023, E731
        assert by(col) == by((F.col("cells"), models.Moves(g, l_k)))


def test_sweeps_read_and_order_the_points_once(spark, sf, monkeypatch):
    asked, real = [], trajectory.gathered
    monkeypatch.setattr(trajectory, "gathered", lambda p: asked.append(1) or real(p))
    rows = workloads.side_sweep(spark, sf, sides=(2, 3), methods=("ngram",)).collect()
    assert len(rows) == 2 and len(asked) == 1
    monkeypatch.undo()
    for r in rows:
        trips, grid = workloads._trips(spark, sf, "order_walk", r["n"])
        syn = workloads.published(spark, trips, grid, "ngram", 50.0, 1)
        assert metrics.query_error(trips, syn, grid, points="uniform", seed=7).first()["value"] == r["query_error"]


def test_pairs_and_ways_of_many_trips_are_those_of_one_by_one(monkeypatch):
    r = np.random.default_rng(1)
    for n, m, eps in ((12, 18, 50.0), (6, 10, 1.0), (2, 4, 50.0), (12, 1, 50.0), (3, 2, 5.0)):
        g = Grid(n, 0.0, 50.0, 0.0, 100.0)
        w, cells = ngram.Perturber(g, eps), r.integers(0, n * n, (40, m))
        ids, asked = np.arange(40) * 7 + 3, []
        real = w.tables
        monkeypatch.setattr(w, "tables", lambda rows, *a: asked.append(rows.shape[1]) or real(rows, *a))  # noqa: B023
        got = w.perturb_many(ids, cells, 5)
        assert all((w.perturb(int(k), c, 5) == x).all() for k, c, x in zip(ids, cells, got, strict=True))
        assert set(asked) <= {1}  # no table over all pairs
    # least ways where all costs are alike: the same of several
    assert (w.rebuild_many(np.zeros((5, 9, 3))) == w.rebuild(np.zeros((5, 9)))).all()
