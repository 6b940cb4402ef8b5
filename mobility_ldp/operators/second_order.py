"""A chain of second order: the next cell depends on the last two.

The domain is all runs of three touching cells, about eight times that of
moves, so each report carries more noise; the first order is the default for
that reason. Ends and the first move come from a first-order model.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng
from . import models, oue
from .grid import Grid
from .synthesis import Walker


def runs(grid: Grid) -> list[tuple[int, int, int]]:
    """All (a, b, c) with a, b touching and b, c touching, in the order of their ids."""
    return [(a, b, c) for a, b in grid.pairs() for c in grid.neighbours(b)]


def run_items(grid: Grid) -> Column:
    """The run ids of a trip: from each move's state id and the place of the next cell among the neighbours of its end."""
    pairs = grid.pairs()
    starts, at = [], 0
    for _, b in pairs:
        starts.append(at)
        at += len(grid.neighbours(b))
    first = {}
    for k, (a, _) in enumerate(pairs):
        first.setdefault(a, k)
    start = F.array(*[F.lit(x) for x in starts])
    row = F.array(*[F.lit(first[c]) for c in range(grid.cells)])
    s = F.col("s__")
    # the place of a state within its row of states is that of its end among the neighbours
    return F.transform(F.slice(s, 2, F.greatest(F.size(s) - 1, F.lit(0))), lambda nxt, i: F.get(start, F.get(s, i)) + nxt - F.get(row, F.element_at("cells", (i + 2).cast("int"))))


def with_runs(trips: DataFrame, grid: Grid) -> DataFrame:
    """trips with the run ids of each (column runs)."""
    t = trips.select("traj_id", "cells", "n_cells", models.state_items(grid).alias("s__"))
    return t.select("traj_id", "cells", "n_cells", run_items(grid).alias("runs"))


def fit(trips: DataFrame, grid: Grid, eps: float, k: float = 0.9, seed: int | None = None, share: float = 0.5) -> tuple[models.Model, np.ndarray]:
    """A first-order model from the one part of eps, and settled counts of all runs from the other."""
    first = models.fit(trips, grid, eps if math.isinf(eps) else eps * share, k, seed=seed)
    l_k, d = max(1, first.plan.l_k - 1), len(runs(grid))
    each = eps if math.isinf(eps) else eps * (1 - share) / l_k
    counts = oue.fused(with_runs(trips, grid), [("runs", F.slice("runs", 1, l_k), l_k, d, each)], None if seed is None else seed + 7).collect()
    return first, np.maximum(models._vector(counts, "runs", d, each), 0)


class SecondWalker(Walker):
    """Walks by the last two cells; where no run of theirs was seen, by the last one."""

    def __init__(self, model: models.Model, counts: np.ndarray, reweight: bool = True):
        super().__init__(model, reweight)
        g = model.grid
        pairs = g.pairs()
        self.ids = {p: k for k, p in enumerate(pairs)}
        self.pair_of = np.full((g.cells, g.cells), -1)
        for p, k in self.ids.items():
            self.pair_of[p] = k
        self.next = np.zeros((len(pairs), 8))
        at = 0
        for k, (_, b) in enumerate(pairs):
            n = len(g.neighbours(b))
            own = counts[at : at + n]
            total = own.sum()
            self.next[k, :n] = own / total * model.intra[b].sum() if total > 0 else model.intra[b, :n]
            at += n
        self.ends = np.array([b for _, b in pairs])

    def walk(self, ids: np.ndarray, seed: int):
        m = self.model
        draw = lambda salt: rng.floats(rng.keyed(seed, ids, salt))
        cap = np.minimum(np.searchsorted(self.caps, draw(1) * self.caps[-1], "right"), len(self.caps) - 1) + 1
        now = np.minimum(np.searchsorted(self.starts, draw(2) * self.starts[-1], "right"), len(self.starts) - 1)
        cells = np.full((len(ids), int(cap.max(initial=1))), -1, np.int32)
        cells[:, 0] = now
        length, met, before = np.ones(len(ids), np.int64), np.zeros(len(ids), bool), np.full(len(ids), -1)
        for l in range(2, cells.shape[1] + 1):
            live = np.flatnonzero((cap >= l) & ~met & (length == l - 1))
            if not len(live):
                break
            pair = np.where(before[live] >= 0, self.pair_of[np.maximum(before[live], 0), now[live]], -1)
            w = np.where((pair >= 0)[:, None], self.next[np.maximum(pair, 0)], m.intra[now[live]])
            stop = m.end[now[live]] * ((m.alpha + m.beta * l) if self.reweight else 1.0)
            c = np.cumsum(np.concatenate([w, stop[:, None]], 1), 1)
            pick = np.minimum((rng.floats(rng.keyed(seed, ids[live], 16 + l))[:, None] * c[:, -1:] >= c).sum(1), 8)
            nxt = np.where(pick < 8, m.near[now[live], np.minimum(pick, 7)], -1)
            met[live[nxt < 0]] = True
            go = live[nxt >= 0]
            before[go], now[go] = now[go], nxt[nxt >= 0]
            cells[go, l - 1] = now[go]
            length[go] = l
        return cells, length, cap, met


def synthesize(spark: SparkSession, model: models.Model, counts: np.ndarray, n: int, seed: int = 0, reweight: bool = True) -> DataFrame:
    """(traj_id, cells, n_cells)."""
    walker = SecondWalker(model, counts, reweight)

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 8192):
                ids = batch.column(0).slice(a, 8192).to_numpy()
                cells, length, _, _ = walker.walk(ids, seed)
                inside = np.arange(cells.shape[1]) < length[:, None]
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]), pa.int32()), pa.array(cells[inside]))
                yield pa.RecordBatch.from_arrays([pa.array(ids), lists, pa.array(length.astype(np.int32))], ["traj_id", "cells", "n_cells"])

    return spark.range(n).mapInArrow(run, "traj_id long, cells array<int>, n_cells int")


__all__ = ["SecondWalker", "fit", "run_items", "runs", "synthesize", "with_runs"]
