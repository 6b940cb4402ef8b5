"""Length distribution and mobility model: reports, estimates, and the fitted whole."""

from __future__ import annotations

import json
import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.cells import cell_x, cell_y
from . import oue
from .budget import BudgetPlan, plan_budget
from .grid import END, START, Grid, state_domain

# ---- reports ---------------------------------------------------------------


def length_item(max_len: int) -> Column:
    """The place of a trip's length: lengths 1..max_len, longer ones counted as max_len."""
    return F.least(F.col("n_cells"), F.lit(max_len)) - 1


def state_items(grid: Grid, cells: str = "cells") -> Column:
    """The state ids of a trip's moves, by a table of 9 entries per cell; moves between cells that do not touch are null."""
    ids = {p: k for k, p in enumerate(grid.pairs())}
    flat = []
    for c in range(grid.cells):
        for dy in (-1, 0, 1):
            for dx in (-1, 0, 1):
                x, y = c % grid.n + dx, c // grid.n + dy
                flat.append(ids.get((c, y * grid.n + x), -1) if 0 <= x < grid.n and 0 <= y < grid.n else -1)
    table = F.array(*[F.lit(v) for v in flat])
    n = grid.n
    c = F.col(cells)

    def item(dst, i):
        src = F.get(c, i)
        dx, dy = cell_x(dst, n) - cell_x(src, n), cell_y(dst, n) - cell_y(src, n)
        ok = (F.abs(dx) <= 1) & (F.abs(dy) <= 1)
        return F.when(ok, F.get(table, src * 9 + (dy + 1) * 3 + dx + 1)).otherwise(F.lit(-1))

    return F.transform(F.slice(c, 2, F.greatest(F.size(c) - 1, F.lit(0))), item)


def speed_item(points: DataFrame, bins: int = 8, top: float = 1e-3) -> DataFrame:
    """(traj_id, item): the bucket of each trip's mean speed, way over time, for points whose order has a time ts; trips of no time have none."""
    w = Window.partitionBy("traj_id").orderBy("ord")
    ts = F.unix_micros(F.col("ord.ts").cast("timestamp")) / 1e6
    step = F.sqrt(F.pow(F.col("x") - F.lag("x").over(w), 2) + F.pow(F.col("y") - F.lag("y").over(w), 2))
    s = points.select("traj_id", step.alias("d"), ts.alias("t")).groupBy("traj_id").agg(F.sum("d").alias("d"), (F.max("t") - F.min("t")).alias("t"))
    v = F.try_divide(F.col("d"), F.col("t"))
    # least() skips nulls, so a trip of no time is kept apart
    return s.select("traj_id", F.when(v.isNotNull(), F.least(F.floor(v / top * bins), F.lit(bins - 1))).cast("int").alias("item"))


def kept_moves(items: Column, l_k: int, which: str = "first", seed: int = 0) -> Column:
    """The l_k moves that are reported: the first, or a seeded even sample."""
    if which == "first":
        return F.slice(items, 1, l_k)
    ranked = F.transform(items, lambda s, i: F.struct(F.xxhash64(F.lit(seed), F.col("traj_id"), i).alias("r"), s.alias("s")))
    return F.transform(F.slice(F.array_sort(ranked), 1, l_k), lambda x: x["s"])


class Moves:
    """state_items() of a batch of trips: of the first l_k moves those between cells that touch, as Arrow's lists."""

    def __init__(self, grid: Grid, l_k: int):
        self.n, self.l_k = grid.n, l_k
        pairs = np.array(grid.pairs(), np.int64).reshape(-1, 2)
        self.table = np.full(grid.cells * 9, -1, np.int32)
        self.table[self._at(pairs[:, 0], pairs[:, 1])[1]] = np.arange(len(pairs))

    def _at(self, src, dst):
        dx, dy = dst % self.n - src % self.n, dst // self.n - src // self.n
        return (np.abs(dx) <= 1) & (np.abs(dy) <= 1), src * 9 + (dy + 1) * 3 + dx + 1

    def __call__(self, lists: pa.Array) -> pa.Array:
        size, v = lists.value_lengths().fill_null(0).to_numpy().astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False)
        trip, end = np.repeat(np.arange(len(size)), size), np.cumsum(size)
        left = end[trip] - np.arange(len(v))
        at = np.flatnonzero((left > 1) & (size[trip] - left < self.l_k))
        touch, place = self._at(v[at].astype(np.int64), v[at + 1].astype(np.int64))
        item = self.table[np.where(touch, place, 0)]
        known = touch & (item >= 0)
        count = np.bincount(trip[at][known], minlength=len(size))
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count)]), pa.int32()), pa.array(item[known]))


# ---- estimates as tables -----------------------------------------------------


def length_model(estimates: DataFrame) -> DataFrame:
    """(len, p, cum) from settled estimates of lengths (item = len - 1)."""
    whole = Window.partitionBy()
    p = F.try_divide(F.col("clipped"), F.sum("clipped").over(whole))
    out = estimates.select((F.col("item") + 1).alias("len"), p.alias("p"))
    return out.withColumn("cum", F.sum("p").over(Window.orderBy("len").rowsBetween(Window.unboundedPreceding, 0)))


def length_quantile(model: DataFrame, k: float = 0.9) -> DataFrame:
    """(l_k): the least length at which the running sum reaches k."""
    return model.where(F.col("cum") >= k - 1e-12).agg(F.min("len").alias("l_k"))


def mobility_model(spark: SparkSession, grid: Grid, estimates: DataFrame) -> DataFrame:
    """(src, dst, est, p, cum) over all states, from settled estimates (state_id, clipped); p shares each row's total over its neighbours and the end."""
    states = state_domain(spark, grid)
    m = states.join(F.broadcast(estimates.select("state_id", "clipped")), "state_id", "left").select("src", "dst", F.coalesce("clipped", F.lit(0.0)).alias("est"))
    m = m.withColumn("p", F.coalesce(F.try_divide(F.col("est"), F.sum("est").over(Window.partitionBy("src"))), F.lit(0.0)))
    return m.withColumn("cum", F.sum("p").over(Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)))


def exact_counts(trips: DataFrame, grid: Grid) -> DataFrame:
    """(state_id, clipped): true counts of all states, for the non-private reference."""
    s, c = grid.states, grid.cells
    ends = F.array(F.col("cells")[0] + s, F.element_at("cells", -1) + s + c)
    return trips.where(F.size("cells") > 0).select(F.explode(F.concat(state_items(grid), ends)).alias("state_id")).where("state_id >= 0").groupBy("state_id").agg(F.count("*").cast("double").alias("clipped"))


# ---- the fitted model --------------------------------------------------------


@dataclass
class Model:
    """What the curator publishes: small arrays. intra: cells x 8 probabilities of the neighbours in near; end: per cell."""

    grid: Grid
    lengths: np.ndarray
    begin: np.ndarray
    near: np.ndarray
    intra: np.ndarray
    end: np.ndarray
    alpha: float = 0.3
    beta: float = 0.2
    uses_end: bool = True
    plan: BudgetPlan | None = None

    def to_json(self) -> str:
        g = self.grid
        return json.dumps({"grid": [g.n, g.xmin, g.xmax, g.ymin, g.ymax], "alpha": self.alpha, "beta": self.beta, "uses_end": self.uses_end, **{k: getattr(self, k).tolist() for k in ("lengths", "begin", "near", "intra", "end")}})

    @classmethod
    def from_json(cls, text: str) -> Model:
        d = json.loads(text)
        return cls(Grid(*d["grid"]), *[np.array(d[k]) for k in ("lengths", "begin", "near", "intra", "end")], d["alpha"], d["beta"], d["uses_end"])

    def save(self, spark: SparkSession, path: str) -> None:
        spark.createDataFrame([(self.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Model:
        return cls.from_json(spark.read.text(path).first()[0])


def neighbour_table(grid: Grid) -> np.ndarray:
    out = np.full((grid.cells, 8), -1)
    for c in range(grid.cells):
        own = grid.neighbours(c)
        out[c, : len(own)] = own
    return out


def build_model(grid: Grid, lengths: np.ndarray, states: np.ndarray, alpha=0.3, beta=0.2, dead_row="uniform", uses_end=True, plan=None) -> Model:
    """A model from settled counts: lengths (max_len), states (all pairs, begins, ends). A cell without any mass goes on evenly to its neighbours and the end, or stops (dead_row="stop")."""
    s, c = grid.states, grid.cells
    near = neighbour_table(grid)
    intra = np.zeros((c, 8))
    place = np.cumsum((near >= 0).sum(1)) - (near >= 0).sum(1)
    for cell in range(c):
        k = int((near[cell] >= 0).sum())
        intra[cell, :k] = states[place[cell] : place[cell] + k]
    end = states[s + c :].astype(float).copy() if uses_end else np.zeros(c)
    begin = states[s : s + c].astype(float)
    begin = begin / begin.sum() if begin.sum() > 0 else np.full(c, 1 / c)
    total = intra.sum(1) + end
    dead = total <= 0
    if dead_row == "stop" and uses_end:
        end[dead] = 1.0
    else:
        intra[dead] = (near[dead] >= 0).astype(float)
        end[dead] = 1.0 if uses_end else 0.0
    total = intra.sum(1) + end
    lengths = np.asarray(lengths, float)
    lengths = lengths / lengths.sum() if lengths.sum() > 0 else np.full(len(lengths), 1 / len(lengths))
    return Model(grid, lengths, begin, near, intra / total[:, None], end / total, alpha, beta, uses_end, plan)


def _vector(counts: list, feature: str, d: int, eps: float, n_default: int = 0) -> np.ndarray:
    """Unbiased estimates of a feature's d places, negatives cut to 0."""
    ones, n = np.zeros(d), n_default
    for r in counts:
        if r["feature"] == feature:
            ones[r["item"]] = r["ones"]
            n = r["n"]
    q, p = oue.q_of(eps), oue.p_of(eps)
    return (ones - n * q) / (p - q)


def norm_sub(est: np.ndarray, n: float) -> np.ndarray:
    """Shift so that the positive part sums to n."""
    s = np.sort(est)[::-1]
    k = np.arange(1, len(s) + 1)
    shift = (np.cumsum(s) - n) / k
    ok = np.flatnonzero(s - shift > 0)
    return np.maximum(est - shift[ok[-1]], 0) if len(ok) else np.zeros_like(est)


def fit(
    trips: DataFrame,
    grid: Grid,
    eps: float,
    k: float = 0.9,
    scheme: str = "default",
    seed: int | None = None,
    max_len: int | None = None,
    shares: tuple[float, float, float] | None = None,
    which: str = "first",
    policy: str = "padded",
    alpha: float = 0.3,
    beta: float = 0.2,
    dead_row: str = "uniform",
    post: str = "clip",
    endpoints: bool = True,
    pooled: bool = False,
    l_k: int | None = None,
) -> Model:
    """Collect all reports and fit the model. Two passes over the trips (keep them, or write them, before).

    The first pass collects lengths; l_k, their k-quantile, is then public, and the second pass collects moves,
    begins and ends. policy="padded" sends l_k reports of moves for every trip; "as_described" sends one per move.
    seed: None for reports whose noise is secret; a number repeats an experiment, and protects nobody.
    endpoints=False: no virtual cells; their budget goes to the moves. pooled=True: one domain for all transitions.
    """
    max_len = max_len or grid.cells
    second = None if seed is None else seed + 1
    e1 = eps if math.isinf(eps) else (shares[0] if scheme == "custom" and shares else eps / 10)
    got = oue.fused(trips, [("length", length_item(max_len), 0, max_len, e1)], seed).collect()
    lengths = np.maximum(_vector(got, "length", max_len, e1), 0)
    share = np.cumsum(lengths) / lengths.sum() if lengths.sum() > 0 else np.linspace(1 / max_len, 1, max_len)
    l_k = l_k or int(np.searchsorted(share, k - 1e-12) + 1)
    l_k = max(1, min(l_k, max_len))
    plan = plan_budget(eps, l_k, scheme, shares, max_len)
    plan.spend("length", plan.e1 if not math.isinf(eps) else 0.0)
    s, c = grid.states, grid.cells
    moves = F.filter(kept_moves(state_items(grid), l_k, which, rng.public(seed)), lambda x: x >= 0)
    first, last = F.col("cells")[0], F.element_at("cells", -1)
    cut = (lambda x, n: norm_sub(x, n)) if post == "norm_sub" else (lambda x, n: np.maximum(x, 0))
    n_trips = sum(r["n"] for r in got if r["item"] == 0)
    if pooled:
        each = plan.per_move if not math.isinf(eps) else eps
        own = F.concat(F.array(first + s, last + s + c), moves)
        counts = oue.fused(trips, [("all", own, l_k + 2, s + 2 * c, each)], second).collect()
        plan.spend("all", each * (l_k + 2) if not math.isinf(eps) else 0.0)
        states = cut(_vector(counts, "all", s + 2 * c, each), n_trips * (l_k + 2))
    else:
        e_move = eps if math.isinf(eps) else (plan.per_move if endpoints else 0.9 * eps / l_k)
        many = which == "first" and policy != "as_described"
        features = [("intra", (F.col("cells"), Moves(grid, l_k)) if many else moves, l_k, s, e_move)]
        if endpoints:
            e_end = eps if math.isinf(eps) else plan.per_end
            features += [("begin", first, 0, c, e_end), ("end", last, 0, c, e_end)]
        if policy == "as_described":
            # one report for each move: rows of single moves, keyed by trip and step
            each = trips.select("traj_id", F.posexplode(moves).alias("k", "m")).select((F.xxhash64("traj_id", "k")).alias("traj_id"), "m")
            counts = oue.fused(each, [("intra", F.col("m"), 0, s, e_move)], second).collect()
            if endpoints:
                counts += oue.fused(trips, features[1:], second).collect()
        else:
            counts = oue.fused(trips, features, second).collect()
        plan.spend("moves", e_move * l_k if not math.isinf(eps) else 0.0)
        states = np.zeros(s + 2 * c)
        states[:s] = cut(_vector(counts, "intra", s, e_move), n_trips * l_k)
        if endpoints:
            plan.spend("ends", 2 * e_end if not math.isinf(eps) else 0.0)
            states[s : s + c] = cut(_vector(counts, "begin", c, e_end), n_trips)
            states[s + c :] = cut(_vector(counts, "end", c, e_end), n_trips)
        else:
            states[s : s + c] = 1.0
    return build_model(grid, lengths, states, alpha, beta, dead_row, endpoints, plan)


def fit_exact(trips: DataFrame, grid: Grid, max_len: int | None = None, alpha=0.3, beta=0.2) -> Model:
    """The non-private reference: true counts."""
    max_len = max_len or grid.cells
    s = grid.states + 2 * grid.cells
    states, lengths = np.zeros(s), np.zeros(max_len)
    for r in exact_counts(trips, grid).collect():
        states[r["state_id"]] = r["clipped"]
    for r in trips.groupBy(F.least("n_cells", F.lit(max_len)).alias("len")).count().collect():
        lengths[r["len"] - 1] = r["count"]
    return build_model(grid, lengths, states, alpha, beta)
