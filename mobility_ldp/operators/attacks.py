"""Two attacks on a published set, and the share of trips that withstand them."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .grid import Grid

KAPPAS = (2, 4, 6, 8, 10)
#: Distinct zone walks of the published set, with counts, up to which they are sent to all tasks.
MAX_WALKS = 200_000


def central_zone(grid: Grid) -> list[int]:
    """The 2 x 2 cells in the middle."""
    a = max(0, grid.n // 2 - 1)
    side = [a, min(a + 1, grid.n - 1)]
    return sorted({y * grid.n + x for y in side for x in side})


def dtw_many(a: np.ndarray, b: np.ndarray, size: np.ndarray, centres: np.ndarray, apart: np.ndarray | None = None) -> np.ndarray:
    """Warping distance of one walk a to many walks b (padded rows, with their sizes), over cell centres; apart has the distances of all centres, if known."""
    apart = distances_of(centres) if apart is None else apart
    longest, at = int(size.max(initial=1)), np.ascontiguousarray(np.maximum(b, 0).T)
    row = np.full((longest + 1, len(b)), np.inf)
    row[0] = 0.0
    for c in a:
        new = np.full_like(row, np.inf)
        for j in range(1, longest + 1):
            np.minimum(row[j], row[j - 1], out=new[j])
            np.minimum(new[j], new[j - 1], out=new[j])
            new[j] += apart[c][at[j - 1]]
        row = new
    return row[size, np.arange(len(b))]


def distances_of(centres: np.ndarray) -> np.ndarray:
    return np.linalg.norm(centres[:, None] - centres[None], axis=-1)


def dtw(a, b, centres: np.ndarray) -> float:
    return float(dtw_many(np.asarray(a), np.asarray([b]), np.array([len(b)]), centres)[0])


def zone_walks(trips: DataFrame, zone: list[int]) -> DataFrame:
    """(walk, n): the distinct parts of trips inside the zone, with how many trips have them."""
    inside = F.filter("cells", lambda c: c.isin(zone))
    return trips.select(inside.alias("walk")).where(F.size("walk") > 0).groupBy("walk").agg(F.count("*").alias("n"))


def _padded_lists(lists) -> tuple[np.ndarray, np.ndarray]:
    """_padded() of Arrow's lists."""
    size, values = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False)
    out = np.full((len(size), int(size.max(initial=1))), -1, np.int32)
    out[np.arange(out.shape[1]) < size[:, None]] = values
    return out, size


def _padded(walks) -> tuple[np.ndarray, np.ndarray]:
    size = np.array([len(w) for w in walks], np.int64)
    out = np.full((len(walks), int(size.max(initial=1))), -1, np.int64)
    for k, w in enumerate(walks):
        out[k, : len(w)] = w
    return out, size


#: Walks whose common beginnings are known as one tree.
BLOCK = 1 << 14


class Beginnings:
    """The distinct beginnings of walks (padded rows, with their sizes) as a tree, by length: node 0 is the empty one, ends has the node of each walk."""

    def __init__(self, walks: np.ndarray, size: np.ndarray):
        # other: how many cells a walk shares with the one before it, in their order
        order = np.lexsort(walks.T[::-1])
        walks, size = walks[order], size[order]
        place = np.arange(walks.shape[1])
        shared = np.zeros(len(walks), np.int64)
        if len(walks) > 1:
            same = walks[1:] == walks[:-1]
            shared[1:] = np.where(same.all(1), walks.shape[1], same.argmin(1))
        self.shared, self.size, self.walks = shared, size, walks
        new = (place >= shared[:, None]) & (place < size[:, None])
        count = new.sum(0)
        self.starts = 1 + np.concatenate([[0], np.cumsum(count)])
        own = np.cumsum(new, 0) - 1 + self.starts[:-1]
        row, at = np.nonzero(new.T)[::-1]
        self.parent, self.cell = np.zeros(int(self.starts[-1]), np.int64), np.zeros(int(self.starts[-1]), np.int64)
        self.parent[1:], self.cell[1:] = np.where(at > 0, own[row, at - 1], 0), walks[row, at]
        self.ends = np.empty(len(walks), np.int64)
        self.ends[order] = own[np.arange(len(walks)), size - 1]
        self.levels = [(int(a), int(b)) for a, b in zip(self.starts[:-1], self.starts[1:], strict=True) if b > a]
        self.order = order

    def against(self, other: Beginnings, apart: np.ndarray, limit: float):
        """(walk, row) for each walk: its warping distances to all nodes of the other tree, None if all are beyond the limit.

        Each beginning is held once against each other one: the distance of two comes from those of the two without their last cells.
        """
        nodes = len(other.parent)
        rows = np.full((self.walks.shape[1] + 1, nodes), np.inf)
        rows[0, 0] = 0.0
        diagonal, costs, dead = np.empty(nodes), {}, self.walks.shape[1] + 1
        for k in range(len(self.walks)):
            if dead > self.shared[k]:  # else it begins like one that is beyond the limit throughout
                dead = self.walks.shape[1] + 1
                for j in range(int(self.shared[k]), int(self.size[k])):
                    c, was, row = int(self.walks[k, j]), rows[j], rows[j + 1]
                    if c not in costs:
                        costs[c] = apart[c][other.cell]
                    np.take(was, other.parent, out=diagonal, mode="clip")
                    np.minimum(diagonal, was, out=diagonal)
                    row[0] = np.inf
                    for a, b in other.levels:
                        part = row[a:b]
                        np.take(row, other.parent[a:b], out=part, mode="clip")
                        np.minimum(part, diagonal[a:b], out=part)
                        part += costs[c][a:b]
                    if row.min() > limit:  # every longer walk passes through this row
                        dead = j + 1
                        break
            yield int(self.order[k]), None if dead <= self.size[k] else rows[self.size[k]]


def _matching(known, size, n, centres, limit, mode):
    """mode "max": the largest distance of each walk; "count": how many trips lie within the limit."""
    order = np.lexsort(known.T[::-1])  # walks that begin alike share a block
    known, size, n, apart = known[order], size[order], n[order], distances_of(centres)

    def run(batches):
        for batch in batches:
            mine, out = Beginnings(*_padded_lists(batch.column(0))), np.zeros(batch.num_rows)
            for a in range(0, len(known), BLOCK):
                block = Beginnings(known[a : a + BLOCK], size[a : a + BLOCK])
                trips = np.zeros(len(block.parent), np.int64)
                trips[block.ends] = n[a : a + BLOCK]
                for k, row in mine.against(block, apart, np.inf if mode == "max" else limit):
                    if mode == "max":
                        out[k] = max(out[k], row[block.ends].max())
                    elif row is not None:
                        out[k] += int(trips[row <= limit].sum())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.float64())], ["walk", "n", "x"])

    return run


def reidentification(real: DataFrame, syn: DataFrame, grid: Grid, theta: float = 0.2, zone: list[int] | None = None) -> DataFrame:
    """(walk, n, matches): for each distinct real walk through the zone, how many published trips pass it alike.

    Distances are computed between distinct walks only. The published ones are sent to all tasks if there are few
    enough, else they are joined in blocks of that size.
    """
    spark = real.sparkSession
    zone = central_zone(grid) if zone is None else zone
    centres = np.array([grid.centre(c) for c in range(grid.cells)])
    # few rows with much work each: else all of them may land in one task; in order, so that a task has walks that begin alike
    attacked = zone_walks(real, zone).repartitionByRange(4 * spark.sparkContext.defaultParallelism, "walk").cache()
    published = zone_walks(syn, zone).persist()
    schema = "walk array<int>, n long, x double"

    def against(walks: DataFrame, limit: float, mode: str) -> DataFrame:
        total = walks.count()
        blocks = max(1, -(-total // MAX_WALKS))
        out = None
        for k in range(blocks):
            rows = (walks if blocks == 1 else walks.where(F.pmod(F.xxhash64("walk"), F.lit(blocks)) == k)).toArrow().combine_chunks()
            walk = rows.column("walk")
            known, size = _padded_lists(walk.chunk(0) if walk.num_chunks else pa.array([], pa.list_(pa.int32())))
            n = rows.column("n").to_numpy().astype(np.int64)
            part = attacked.mapInArrow(_matching(known, size, n, centres, limit, mode), schema)
            out = part if out is None else out.unionByName(part)
        return out.groupBy("walk", "n").agg((F.max if mode == "max" else F.sum)("x").alias("x"))

    widest = against(attacked, 0.0, "max").agg(F.max("x")).first()[0] or 0.0
    limit = theta * widest + 1e-9 * max(1.0, widest)
    return against(published, limit, "count").select("walk", "n", F.col("x").cast("bigint").alias("matches"))


def _ways(n: int):
    """Counts of trips by how many steps they make along, across and diagonal."""

    def run(batches):
        for batch in batches:
            lists = batch.column(0)
            size, v = lists.value_lengths().fill_null(0).to_numpy().astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            trip = np.repeat(np.arange(len(size)), size)
            at = np.flatnonzero(trip[1:] == trip[:-1])
            both = np.abs(v[at] % n - v[at + 1] % n) * 2 + np.abs(v[at] // n - v[at + 1] // n)
            ways = np.stack([np.bincount(trip[at][both == kind], minlength=len(size)) for kind in (2, 1, 3)], 1)
            base = int(ways.max(initial=0)) + 1
            if base < 1 << 21:
                key, count = np.unique((ways[:, 0] * base + ways[:, 1]) * base + ways[:, 2], return_counts=True)
                ways = np.stack([key // base // base, key // base % base, key % base], 1)
            else:
                ways, count = np.unique(ways, axis=0, return_counts=True)
            yield pa.RecordBatch.from_arrays([*(pa.array(np.ascontiguousarray(ways[:, k])) for k in range(3)), pa.array(count.astype(np.int64))], ["along", "across", "diagonal", "n"])

    return run


def distances(trips: DataFrame, grid: Grid) -> DataFrame:
    """(d, n): travelled distances, of which a grid has few distinct ones."""
    w, h = grid.width, grid.height
    ways = trips.select("cells").mapInArrow(_ways(grid.n), "along long, across long, diagonal long, n long").groupBy("along", "across", "diagonal").agg(F.sum("n").alias("n"))
    d = F.col("along") * F.lit(w) + F.col("across") * F.lit(h) + F.col("diagonal") * F.lit(math.sqrt(w * w + h * h))
    return ways.select(F.round(d, 9).alias("d"), "n").groupBy("d").agg(F.sum("n").alias("n"))


def outliers(syn: DataFrame, grid: Grid, share: float = 0.05, k: int = 1, method: str = "gap") -> DataFrame:
    """(d, n): distances of outlying trips. "gap": the trips farthest from the k-th distinct distance beside theirs, up to a share
    of all (one distance at least); "iqr": above the upper or below the lower fence; "ends": those with the rarest (start, end)."""
    if method == "ends":
        e = syn.withColumn("first", F.col("cells")[0]).withColumn("last", F.element_at("cells", -1))
        freq = e.groupBy("first", "last").agg(F.count("*").alias("f"))
        w = Window.orderBy("f", "first", "last").rowsBetween(Window.unboundedPreceding, 0)
        rare = freq.withColumn("c", F.sum("f").over(w)).withColumn("all", F.sum("f").over(Window.partitionBy()))
        rare = rare.where((F.col("c") <= share * F.col("all")) | (F.col("c") == F.col("f"))).select("first", "last")
        return distances(e.join(F.broadcast(rare), ["first", "last"], "left_semi"), grid)
    d = distances(syn, grid)
    if method == "iqr":
        t = Window.orderBy("d").rowsBetween(Window.unboundedPreceding, 0)
        c = d.withColumn("c", F.sum("n").over(t) / F.sum("n").over(Window.partitionBy()))
        q = c.agg(F.min(F.when(F.col("c") >= 0.25, F.col("d"))).alias("q1"), F.min(F.when(F.col("c") >= 0.75, F.col("d"))).alias("q3"))
        return d.crossJoin(F.broadcast(q)).where((F.col("d") > 2.5 * F.col("q3") - 1.5 * F.col("q1")) | (F.col("d") < 2.5 * F.col("q1") - 1.5 * F.col("q3"))).select("d", "n")
    w = Window.orderBy("d")
    near = F.least(F.coalesce(F.col("d") - F.lag("d", k).over(w), F.lit(float("inf"))), F.coalesce(F.lead("d", k).over(w) - F.col("d"), F.lit(float("inf"))))
    g = d.withColumn("gap", F.round(near, 9))
    run = Window.orderBy(F.col("gap").desc(), F.col("d").desc()).rowsBetween(Window.unboundedPreceding, 0)
    g = g.withColumn("c", F.sum("n").over(run)).withColumn("all", F.sum("n").over(Window.partitionBy()))
    return g.where((F.col("c") <= share * F.col("all")) | (F.col("c") == F.col("n"))).select("d", "n")


def outlier_matches(real: DataFrame, syn: DataFrame, grid: Grid, delta: float = 0.25, **options) -> DataFrame:
    """(d, n, matches): for each outlying distance, how many real trips travel about as far. Both sides are tables of distinct distances."""
    r = distances(real, grid)
    wide = r.agg((F.max("d") - F.min("d")).alias("w"))
    o = outliers(syn, grid, **options).crossJoin(F.broadcast(wide))
    j = o.join(F.broadcast(r.select(F.col("d").alias("e"), F.col("n").alias("m"))), F.abs(F.col("d") - F.col("e")) <= delta * F.col("w") + 1e-9, "left")
    return j.groupBy("d", "n").agg(F.coalesce(F.sum("m"), F.lit(0)).alias("matches"))


def resilience(matches: DataFrame, kappas=KAPPAS) -> DataFrame:
    """(kappa, ratio): the share of attacked trips with more than kappa matches."""
    k = matches.sparkSession.createDataFrame([(int(x),) for x in kappas], "kappa int")
    hit = F.sum(F.when(F.col("matches") > F.col("kappa"), F.col("n")).otherwise(0))
    return matches.crossJoin(F.broadcast(k)).groupBy("kappa").agg((hit / F.sum("n")).alias("ratio"))
