"""The compared method: each trip is perturbed on its own, by overlapping n-grams.

Every window of n cells (shorter ones at both ends, so that each cell lies in
n windows) is replaced by a feasible n-gram drawn by the exponential mechanism
with an equal share of the trip's budget: the nearer, the likelier. The trip
is then put together anew: of all ways over touching cells, the one whose
cells are nearest to all sampled windows. That program is a chain, so dynamic
programming solves it exactly. n = 1 is the point-wise mechanism.

With Knowledge, distance also counts a change of category, of region and of
opening hours, and runs through places that are closed at the trip's hour are
not feasible. Runs are then drawn in two levels, each with half of the window's
budget: first the region of the run's first cell, by the distance of regions,
then a run that starts there.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rng
from .grid import Grid

#: Costs (positions x cells x trips), and chances of runs, that are held at once.
BLOCK, TABLE = 1 << 19, 1 << 19


@dataclass
class Knowledge:
    """What a public map tells of each cell: its category, its region, and the hours at which its category is open (categories x 24)."""

    category: np.ndarray
    region: np.ndarray
    open_hours: np.ndarray
    category_weight: float = 1.0
    region_weight: float = 0.5
    time_weight: float = 0.5


def feasible(grid: Grid, n: int) -> np.ndarray:
    """All runs of n touching cells."""
    runs = [[c] for c in range(grid.cells)]
    for _ in range(n - 1):
        runs = [r + [d] for r in runs for d in grid.neighbours(r[-1])]
    return np.array(runs)


class Perturber:
    def __init__(self, grid: Grid, eps: float, n: int = 2, knowledge: Knowledge | None = None):
        self.grid, self.eps, self.n, self.know = grid, eps, n, knowledge
        centre = np.array([grid.centre(c) for c in range(grid.cells)])
        self.dist = np.linalg.norm(centre[:, None] - centre[None], axis=-1)
        self.dist = self.dist / (self.dist.max() or 1.0)
        if knowledge is not None:
            self.dist = self.dist + knowledge.category_weight * (knowledge.category[:, None] != knowledge.category[None]) + knowledge.region_weight * (knowledge.region[:, None] != knowledge.region[None])
            hours = knowledge.open_hours[knowledge.category].astype(float)
            either = np.maximum(hours[:, None], hours[None]).sum(2)
            self.dist = self.dist + knowledge.time_weight * (1 - np.minimum(hours[:, None], hours[None]).sum(2) / np.maximum(either, 1))
            self.regions = np.unique(knowledge.region)
            middle = np.array([centre[knowledge.region == r].mean(0) for r in self.regions])
            apart = np.linalg.norm(middle[:, None] - middle[None], axis=-1)
            self.apart = apart / (apart.max() or 1.0)
        self.grams = {k: feasible(grid, k) for k in range(1, n + 1)}
        near = np.array([[c, *grid.neighbours(c)] + [-1] * (8 - len(grid.neighbours(c))) for c in range(grid.cells)])
        self.near = near[:, 1:]

    def chances(self, window: np.ndarray, eps_w: float, hour: int) -> np.ndarray:
        """The probability of each feasible run of the window's length, by the exponential mechanism."""
        runs = self.grams[len(window)]
        if self.know is not None:
            eps_w = eps_w / 2  # the other half is for the region
        d = sum(self.dist[window[k]][runs[:, k]] for k in range(len(window)))
        widest = self.dist.max() * len(window) or 1.0
        score = -eps_w * d / (2 * widest)
        if self.know is None:
            w = np.exp(score - score.max())
            return w / w.sum()
        # what is closed depends on the hour alone, which is public
        shut = ~self.know.open_hours[self.know.category[runs], hour].all(1)
        if not shut.all():
            score[shut] = -np.inf
        own = np.searchsorted(self.regions, self.know.region[runs[:, 0]])
        level = -eps_w * self.apart[np.searchsorted(self.regions, self.know.region[window[0]])] / 2
        top = np.full(len(self.regions), -np.inf)
        np.maximum.at(top, own, score)
        there = np.isfinite(top)
        first = np.where(there, np.exp(level - level[there].max()), 0.0)
        w = np.where(np.isfinite(score), np.exp(score - np.where(there, top, 0.0)[own]), 0.0)
        return (first / first.sum())[own] * w / np.bincount(own, w, len(self.regions))[own].clip(1e-300)

    def draw(self, window: np.ndarray, eps_w: float, u: float, hour: int) -> np.ndarray:
        """One feasible run in place of the window."""
        runs, c = self.grams[len(window)], np.cumsum(self.chances(window, eps_w, hour))
        return runs[min(int(np.searchsorted(c, u * c[-1], "right")), len(runs) - 1)]

    def rebuild(self, cost: np.ndarray) -> np.ndarray:
        """The way over touching cells with the least total cost (positions x cells)."""
        m, _ = cost.shape
        best, came = cost[0].copy(), np.zeros(cost.shape, np.int64)
        padded = np.where(self.near < 0, 0, self.near)
        for k in range(1, m):
            z = np.where(self.near < 0, np.inf, best[padded])
            at = z.argmin(1)
            came[k] = padded[np.arange(len(at)), at]
            best = z[np.arange(len(at)), at] + cost[k]
        out = np.empty(m, np.int64)
        out[-1] = best.argmin()
        for k in range(m - 1, 0, -1):
            out[k - 1] = came[k, out[k]]
        return out

    def perturb(self, traj_id: int, cells: np.ndarray, seed: int | bytes, hour: int = 12) -> np.ndarray:
        """A trip in place of cells; seed is a number for experiments, or a secret key."""
        m, n = len(cells), self.n
        spans = [(max(0, a), min(m, a + n)) for a in range(1 - n, m)]
        eps_w = self.eps / len(spans)
        if isinstance(seed, bytes):
            u = rng.floats(rng.secret_words(seed, np.array([traj_id]), 5, 2 * len(spans)).reshape(-1).view(np.uint64))
        else:
            u = rng.floats(rng.mix(rng.keyed(seed, np.array([traj_id]), 5) + np.arange(len(spans), dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93)))
        cost = np.zeros((m, self.grid.cells))
        for (a, b), x in zip(spans, u, strict=True):
            for k, c in enumerate(self.draw(cells[a:b], eps_w, float(x), hour)):
                cost[a + k] += self.dist[c]
        return self.rebuild(cost) if self.grid.cells > 1 else np.zeros(m, np.int64)

    def tables(self, windows: np.ndarray, eps_w: float, hour: int) -> np.ndarray:
        """Running sums of chances() for each row of windows."""
        if self.know is not None:
            return np.cumsum([self.chances(w, eps_w, hour) for w in windows], axis=1)
        runs = self.grams[windows.shape[1]]
        d = sum(self.dist[windows[:, k]][:, runs[:, k]] for k in range(windows.shape[1]))
        score = -eps_w * d / (2 * (self.dist.max() * windows.shape[1] or 1.0))
        w = np.exp(score - score.max(1, keepdims=True))
        return np.cumsum(w / w.sum(1, keepdims=True), axis=1)

    def draw_many(self, windows: np.ndarray, eps_w: float, u: np.ndarray, hour: int) -> np.ndarray:
        """One feasible run in place of each row of windows; rows that are alike share their table."""
        runs, code = self.grams[windows.shape[1]], np.zeros(len(windows), np.int64)
        for k in range(windows.shape[1]):
            code = code * self.grid.cells + windows[:, k]
        if self.know is None and windows.shape[1] == 2:
            return self.draw_pairs(code, eps_w, u)
        order = np.argsort(code, kind="stable")
        first = np.flatnonzero(np.diff(code[order], prepend=-1))
        pick, ends = np.empty(len(windows), np.int64), np.append(first, len(code))
        step = max(1, TABLE // len(runs))
        for a in range(0, len(first), step):
            for k, c in enumerate(self.tables(windows[order[first[a : a + step]]], eps_w, hour), a):
                own = order[ends[k] : ends[k + 1]]
                pick[own] = np.searchsorted(c, u[own] * c[-1], "right")
        return runs[np.minimum(pick, len(runs) - 1)]

    def draw_pairs(self, code: np.ndarray, eps_w: float, u: np.ndarray) -> np.ndarray:
        """draw_many() of pairs (first cell * cells + second) by distance alone: a run's chance is a product, so its first cell is found by sums over its neighbours, then the second among these."""
        cells, out = self.grid.cells, np.empty((len(code), 2), np.int64)
        weight = np.exp(-eps_w * self.dist / (2 * (self.dist.max() * 2 or 1.0)))
        more = np.concatenate([weight, np.zeros((cells, 1))], 1)  # place -1: no neighbour
        around = more[:, self.near].sum(2)
        known, which = np.unique(code, return_inverse=True)
        order = np.argsort(which, kind="stable")
        cuts, step = np.searchsorted(which[order], np.arange(len(known) + 1)), max(1, TABLE // cells)
        for a in range(0, len(known), step):
            one, two = np.divmod(known[a : a + step], cells)
            sums = np.cumsum(weight[one] * around[two], axis=1)
            own = order[cuts[a] : cuts[min(a + step, len(known))]]
            row = which[own] - a
            target, flat, at = u[own] * sums[row, -1], sums.reshape(-1), np.zeros(len(own), np.int64)
            for k in reversed(range(cells.bit_length())):  # how many sums are not above the target
                to = at + (1 << k)
                at = np.where((to <= cells) & (flat[row * cells + np.minimum(to, cells) - 1] <= target), to, at)
            at = np.minimum(at, cells - 1)
            rest = target - np.where(at > 0, flat[row * cells + np.maximum(at, 1) - 1], 0.0)
            near = self.near[at]
            parts = np.cumsum(weight[one[row], at][:, None] * more[two[row][:, None], near], axis=1)
            last = (near >= 0).sum(1) - 1
            out[own, 0], out[own, 1] = at, near[np.arange(len(own)), np.minimum((parts <= rest[:, None]).sum(1), last)]
        return out

    def rebuild_many(self, cost: np.ndarray) -> np.ndarray:
        """rebuild() for many trips of one length: cost is positions x cells x trips, the result trips x positions.

        Least costs go from cell to neighbours by whole rows and columns of the grid; where they come from is looked up on the way back, for the cells of the way only.
        """
        (m, _, trips), n = cost.shape, self.grid.n
        best, wide = np.empty((m, n, n, trips)), np.full((n, n + 2, trips), np.inf)
        tall, beside = np.full((n + 2, n, trips), np.inf), np.empty((n, n, trips))
        best[0] = cost[0].reshape(n, n, trips)
        for k in range(1, m):
            wide[:, 1:-1] = best[k - 1]
            np.minimum(wide[:, :-2], wide[:, 2:], out=beside)
            np.minimum(beside, best[k - 1], out=tall[1:-1])
            np.minimum(beside, tall[:-2], out=beside)
            np.minimum(beside, tall[2:], out=beside)
            np.add(beside, cost[k].reshape(n, n, trips), out=best[k])
        best, all_ = best.reshape(m, n * n, trips), np.arange(trips)
        out = np.empty((m, trips), np.int64)
        out[-1] = best[-1].argmin(0)
        for k in range(m - 1, 0, -1):
            near = self.near[out[k]]
            z = np.where(near < 0, np.inf, best[k - 1][np.maximum(near, 0), all_[:, None]])
            out[k - 1] = near[all_, z.argmin(1)]
        return out.T

    def perturb_many(self, ids: np.ndarray, cells: np.ndarray, seed: int | bytes, hour: int = 12) -> np.ndarray:
        """perturb() for many trips of one length (trips x positions) at one hour."""
        (_, m), n = cells.shape, self.n
        spans = [(max(0, a), min(m, a + n)) for a in range(1 - n, m)]
        out, step = np.zeros(cells.shape, np.int64), max(1, BLOCK // (m * self.grid.cells))
        if self.grid.cells == 1:
            return out
        to = np.ascontiguousarray(self.dist.T)
        for low in range(0, len(ids), step):
            own, part = ids[low : low + step], cells[low : low + step]
            if isinstance(seed, bytes):
                u = rng.floats(rng.secret_words(seed, own, 5, 2 * len(spans)).view(np.uint64))
            else:
                u = rng.floats(rng.mix(rng.keyed(seed, own, 5)[:, None] + np.arange(len(spans), dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93)))
            drawn = {}
            for size in {b - a for a, b in spans}:
                at = [k for k, (a, b) in enumerate(spans) if b - a == size]
                rows = np.concatenate([part[:, spans[k][0] : spans[k][1]] for k in at])
                runs = self.draw_many(rows, self.eps / len(spans), u[:, at].T.reshape(-1), hour)
                drawn |= dict(zip(at, runs.reshape(len(at), len(own), size), strict=True))
            cost = np.zeros((m, self.grid.cells, len(own)))
            for k, (a, _) in enumerate(spans):
                for j in range(drawn[k].shape[1]):
                    cost[a + j] += np.take(to, drawn[k][:, j], axis=1)
            out[low : low + step] = self.rebuild_many(cost)
        return out


def ngram_perturb(trips: DataFrame, grid: Grid, eps: float, n: int = 2, seed: int | None = None, knowledge: Knowledge | None = None) -> DataFrame:
    """(traj_id, cells, n_cells): each trip perturbed in place, with its own id and length. With knowledge, an hour column (0..23) is used if there is one.

    Trips of a batch that have one length and hour are perturbed together, to the same result as one by one.
    """
    worker = Perturber(grid, eps, n, knowledge)
    key = rng.new_secret() if seed is None else seed

    def run(batches):
        for batch in batches:
            ids, lists, hours = batch.column(0).to_numpy(), batch.column(1), batch.column(2).to_numpy()
            size = lists.value_lengths().fill_null(0).to_numpy().astype(np.int64)
            start, end = lists.offsets.to_numpy()[:-1].astype(np.int64), np.cumsum(size)
            values, out = lists.values.to_numpy(), np.zeros(int(size.sum()), np.int32)
            kind = size * 24 + (hours if knowledge is not None else 0)
            for own in np.split(order := np.argsort(kind, kind="stable"), np.flatnonzero(np.diff(kind[order])) + 1):
                if len(own) and (m := int(size[own[0]])):
                    place = np.arange(m)
                    out[(end[own] - m)[:, None] + place] = worker.perturb_many(ids[own], values[start[own][:, None] + place], key, int(hours[own[0]]))
            done = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], end]), pa.int32()), pa.array(out))
            yield pa.RecordBatch.from_arrays([batch.column(0), done, pa.array(size.astype(np.int32))], ["traj_id", "cells", "n_cells"])

    hour = F.col("hour").cast("int") if "hour" in trips.columns else F.lit(12)
    return trips.select(F.col("traj_id").cast("bigint").alias("traj_id"), "cells", hour.alias("hour")).mapInArrow(run, "traj_id long, cells array<int>, n_cells int")


def knowledge_from_sites(sites: DataFrame, grid: Grid, categories: int = 10, regions: int = 4) -> Knowledge:
    """Each cell's most frequent category of place (cell modulo where there is none), its region (blocks of cells), and opening hours by category."""
    from ..functions.cells import grid_cell

    rows = sites.select(grid_cell(F.col("x"), F.col("y"), grid).alias("cell"), "category").groupBy("cell", "category").count().groupBy("cell").agg(F.max_by("category", F.struct("count", -F.col("category"))).alias("category")).collect()
    category = np.arange(grid.cells) % categories
    for r in rows:
        category[r["cell"]] = r["category"] % categories
    half = max(1, -(-grid.n // 2))
    c = np.arange(grid.cells)
    region = (c // grid.n // half) * 2 + (c % grid.n) // half
    hours = np.array([[(h >= 6 + k % 4) and (h < 18 + k % 6) or k % 5 == 0 for h in range(24)] for k in range(categories)])
    return Knowledge(category, region, hours)
