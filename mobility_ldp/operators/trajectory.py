"""Trips of cells from points.

assemble() has one shuffle, by trip. A trip as one row suits all but very long
ones; form="rows" keeps a row per cell and sorts within windows that can spill.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.cells import cell_x, cell_y, is_adjacent
from .grid import Grid, assign_cell


def collapse(cells: Column) -> Column:
    """Runs of one cell become one."""
    return F.filter(cells, lambda c, i: (i == 0) | (c != F.get(cells, i - 1)))


def between(a: Column, b: Column, n: int) -> Column:
    """The cells from a (left out) to b (in), each touching the one before: whole-number steps along the line."""
    ax, ay = cell_x(a, n), cell_y(a, n)
    dx, dy = cell_x(b, n) - ax, cell_y(b, n) - ay
    g = F.greatest(F.abs(dx), F.abs(dy))
    at = lambda lo, d, i: lo + F.floor((2 * d * i + g) / (2 * g)).cast("int")
    return F.when(g <= 1, F.array(b)).otherwise(F.transform(F.sequence(F.lit(1), g), lambda i: at(ay, dy, i) * n + at(ax, dx, i)))


def interpolate(cells: Column, n: int, method: str = "chebyshev") -> Column:
    """Fill the gaps of a trip; method "none" leaves it."""
    if method == "none":
        return cells
    return F.flatten(F.transform(cells, lambda c, i: F.when(i == 0, F.array(c)).otherwise(between(F.get(cells, i - 1), c, n))))


def assemble(points: DataFrame, grid: Grid, method: str = "chebyshev", form: str = "array", outside: str = "clamp") -> DataFrame:
    """(traj_id, cells, n_cells), or with form="rows" (traj_id, pos, cell)."""
    at = assign_cell(points, grid, outside).select("traj_id", "ord", "cell")
    if form == "rows":
        return _rows(at, grid, method)
    # each step is a projection of its own: a list that lambdas read again is not computed again
    t = at.groupBy("traj_id").agg(F.sort_array(F.collect_list(F.struct("ord", "cell"))).alias("p"))
    t = t.select("traj_id", F.col("p.cell").alias("c"))
    t = t.select("traj_id", collapse(F.col("c")).alias("c"))
    # one list in a generator: a later filter on the cells stops here, where the optimiser would else write the steps into it, once for each use
    t = t.select("traj_id", F.explode_outer(F.array(interpolate(F.col("c"), grid.n, method))).alias("cells"))
    return t.withColumn("n_cells", F.size("cells"))


def _rows(at: DataFrame, grid: Grid, method: str) -> DataFrame:
    w = Window.partitionBy("traj_id").orderBy("ord")
    moved = at.withColumn("was", F.lag("cell").over(w)).where(F.col("was").isNull() | (F.col("was") != F.col("cell")))
    fill = F.array("cell") if method == "none" else F.when(F.col("was").isNull(), F.array("cell")).otherwise(between(F.col("was"), F.col("cell"), grid.n))
    out = moved.select("traj_id", "ord", F.posexplode(fill).alias("i", "c"))
    pos = F.row_number().over(Window.partitionBy("traj_id").orderBy("ord", "i"))
    return out.select("traj_id", pos.alias("pos"), F.col("c").alias("cell"))


def gathered(points: DataFrame) -> DataFrame:
    """(traj_id, tie, x, y): a row per trip with its points in order, to be put on any grid by walked(); tie tells points of one order."""
    known = points.where(F.col("x").isNotNull() & F.col("y").isNotNull())
    p = known.select("traj_id", "ord", F.xxhash64("ord").alias("tie"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"))
    t = p.groupBy("traj_id").agg(F.sort_array(F.collect_list(F.struct("ord", "tie", "x", "y"))).alias("p"))
    return t.select("traj_id", F.col("p.tie").alias("tie"), F.col("p.x").alias("x"), F.col("p.y").alias("y"))


def _axis(v: np.ndarray, lo: float, hi: float, n: int) -> np.ndarray:
    """cells.axis_index() of many numbers."""
    if hi == lo:
        return np.zeros(len(v), np.int64)
    with np.errstate(invalid="ignore"):
        return np.clip(np.nan_to_num(np.floor((v - lo) / (hi - lo) * n), nan=0.0), 0, n - 1).astype(np.int64)


def _values(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The values of all lists one after another, and their sizes."""
    at = lists.offsets.to_numpy()
    return lists.values.to_numpy(zero_copy_only=False)[at[0] : at[-1]], np.diff(at).astype(np.int64)


def walked(lists: DataFrame, grid: Grid) -> DataFrame:
    """assemble() of the points that gathered() has put in order: repeats collapsed, gaps filled, for a batch of trips at once."""
    n = grid.n

    def run(batches):
        for batch in batches:
            (tie, size), (x, _), (y, _) = (_values(batch.column(k)) for k in (1, 2, 3))
            trip, first = np.repeat(np.arange(len(size)), size), np.zeros(len(x), bool)
            first[(np.cumsum(size) - size)[size > 0]] = True
            cell = _axis(y, grid.ymin, grid.ymax, n) * n + _axis(x, grid.xmin, grid.xmax, n)
            run_of = np.cumsum(first | (tie != np.roll(tie, 1)))
            if len(run_of) and run_of[-1] < len(run_of):  # points of one order go by cell
                cell = cell[np.lexsort((cell, run_of))]
            kept = first | (cell != np.roll(cell, 1))
            cell, trip, first = cell[kept], trip[kept], first[kept]
            was = np.where(first, cell, np.roll(cell, 1))
            ax, ay = was % n, was // n
            dx, dy = cell % n - ax, cell // n - ay
            g = np.maximum(np.maximum(np.abs(dx), np.abs(dy)), 1)
            step, of = np.arange(1, int(g.sum()) + 1) - np.repeat(np.cumsum(g) - g, g), np.repeat(np.arange(len(g)), g)
            on = lambda a, d: a[of] + (2 * d[of] * step + g[of]) // (2 * g[of])
            out, sizes = (on(ay, dy) * n + on(ax, dx)).astype(np.int32), np.bincount(trip[of], minlength=len(size))
            cells = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(out))
            yield pa.RecordBatch.from_arrays([batch.column(0), cells, pa.array(sizes.astype(np.int32))], ["traj_id", "cells", "n_cells"])

    return lists.mapInArrow(run, f"traj_id {lists.schema['traj_id'].dataType.simpleString()}, cells array<int>, n_cells int")


def transitions(trips: DataFrame) -> DataFrame:
    """(traj_id, step, src, dst): the moves of each trip, from step 1."""
    steps = F.arrays_zip(F.slice("cells", 1, F.greatest(F.size("cells") - 1, F.lit(0))).alias("src"), F.slice("cells", 2, F.size("cells")).alias("dst"))
    return trips.select("traj_id", F.posexplode(steps).alias("k", "s")).select("traj_id", (F.col("k") + 1).alias("step"), F.col("s.src").alias("src"), F.col("s.dst").alias("dst"))


def endpoints(trips: DataFrame) -> DataFrame:
    return trips.where(F.size("cells") > 0).select("traj_id", F.col("cells")[0].alias("first"), F.element_at("cells", -1).alias("last"))


def visits(trips: DataFrame) -> DataFrame:
    """(cell, n): how often each cell is visited."""
    return trips.select(F.explode("cells").alias("cell")).groupBy("cell").agg(F.count("*").alias("n"))


def to_points(trips: DataFrame, grid: Grid, mode: str = "centre", seed: int = 0) -> DataFrame:
    """(traj_id, pos, x, y): cells back to points, at centres or drawn evenly in the cell."""
    p = trips.select("traj_id", F.posexplode("cells").alias("pos", "cell"))
    draw = lambda axis: F.lit(0.5) if mode == "centre" else rng.u01(seed, F.col("traj_id"), F.col("pos"), axis, engine="xx")
    return p.select("traj_id", "pos", (F.lit(grid.xmin) + (cell_x(F.col("cell"), grid.n) + draw("x")) * F.lit(grid.width)).alias("x"), (F.lit(grid.ymin) + (cell_y(F.col("cell"), grid.n) + draw("y")) * F.lit(grid.height)).alias("y"))


def broken(trips: DataFrame, grid: Grid) -> DataFrame:
    """Trips with a step between cells that do not touch."""
    return transitions(trips).where(~is_adjacent(F.col("src"), F.col("dst"), grid.n)).select("traj_id").distinct()


def in_zone(trips: DataFrame, zone: list[int]) -> DataFrame:
    """Trips through any cell of a zone."""
    return trips.where(F.arrays_overlap("cells", F.array(*[F.lit(c) for c in zone])))


def sample(trips: DataFrame, share: float, seed: int = 0, engine: str = "xx") -> DataFrame:
    """A Bernoulli sample of whole trips by hashed id: the same after a retry."""
    return trips.where(rng.u01(seed, F.col("traj_id"), engine=engine) < share)


def sample_by_start(trips: DataFrame, shares: dict[int, float], seed: int = 0, engine: str = "xx") -> DataFrame:
    """A sample whose share depends on the first cell."""
    share = F.lit(0.0)
    for cell, s in shares.items():
        share = F.when(F.col("cells")[0] == cell, s).otherwise(share)
    return trips.where(rng.u01(seed, F.col("traj_id"), engine=engine) < share)


def sql(source: str, n: int) -> str:
    """DuckDB WITH clauses: points p, bounds b, cells c, trips in rows t (traj_id, pos, cell)."""
    return f"""
p AS ({source}),
b AS (SELECT min(x) + 0.0 AS x0, max(x) + 0.0 AS x1, min(y) + 0.0 AS y0, max(y) + 0.0 AS y1 FROM p),
c AS (SELECT traj_id, k,
        CAST(CASE WHEN x1 = x0 THEN 0 ELSE greatest(0, least({n} - 1, floor((x - x0) / (x1 - x0) * {n}))) END AS INTEGER) AS cx,
        CAST(CASE WHEN y1 = y0 THEN 0 ELSE greatest(0, least({n} - 1, floor((y - y0) / (y1 - y0) * {n}))) END AS INTEGER) AS cy
      FROM p, b WHERE x IS NOT NULL AND y IS NOT NULL),
l AS (SELECT *, lag(cx) OVER w AS px, lag(cy) OVER w AS py FROM c WINDOW w AS (PARTITION BY traj_id ORDER BY k)),
m AS (SELECT *, greatest(abs(cx - px), abs(cy - py)) AS g FROM l WHERE px IS NULL OR px <> cx OR py <> cy),
f AS (SELECT traj_id, k, 0 AS i, cx, cy FROM m WHERE px IS NULL
      UNION ALL
      SELECT traj_id, k, i, CAST(px + floor((2 * (cx - px) * i + g) / (2.0 * g)) AS INTEGER), CAST(py + floor((2 * (cy - py) * i + g) / (2.0 * g)) AS INTEGER)
      FROM (SELECT *, unnest(generate_series(1, g)) AS i FROM m WHERE px IS NOT NULL)),
t AS (SELECT traj_id, row_number() OVER (PARTITION BY traj_id ORDER BY k, i) AS pos, cy * {n} + cx AS cell FROM f)
"""
