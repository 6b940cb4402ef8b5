"""Synthetic trips from a fitted model, with no shuffle.

A trip draws a length cap and a start, then walks: at position l the chance to
stop is scaled by alpha + beta * l and the row made a distribution again. The
walk of a batch of trips is one numpy loop over positions; uniforms are keyed
by (seed, trip, position), so retries and partitioning change nothing. The
"sql" engine does the same with whole-number weights and column functions, so
that another SQL engine gives the same trips.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng
from .grid import Grid
from .models import Model


class Walker:
    """Cumulative tables of a model. length_index: "position" counts the place to be filled (2, 3, ...), "cells" the cells so far."""

    def __init__(self, model: Model, reweight: bool = True, length_index: str = "position"):
        self.model, self.reweight, self.shift = model, reweight, 0 if length_index == "position" else -1
        self.caps, self.starts = np.cumsum(model.lengths), np.cumsum(model.begin)

    def table(self, l: int) -> np.ndarray:
        """cells x 9 running sums: the eight neighbours, then the end."""
        m = self.model
        stop = m.end * (m.alpha + m.beta * (l + self.shift)) if self.reweight else m.end
        w = np.concatenate([m.intra, stop[:, None]], 1)
        total = w.sum(1, keepdims=True)
        w = np.where(total > 0, w / np.where(total > 0, total, 1), 0)
        w[total[:, 0] <= 0, 8] = 1.0  # nowhere to go
        return np.cumsum(w, 1)

    def walk(self, ids: np.ndarray, seed: int):
        """cells (trips x longest), lengths, caps, and whether each trip met the end."""
        draw = lambda salt: rng.floats(rng.keyed(seed, ids, salt))
        cap = np.minimum(np.searchsorted(self.caps, draw(1) * self.caps[-1], "right"), len(self.caps) - 1) + 1
        now = np.minimum(np.searchsorted(self.starts, draw(2) * self.starts[-1], "right"), len(self.starts) - 1)
        longest = int(cap.max(initial=1))
        cells = np.full((len(ids), longest), -1, np.int32)
        cells[:, 0] = now
        length, met = np.ones(len(ids), np.int64), np.zeros(len(ids), bool)
        live = np.flatnonzero(cap > 1)
        for l in range(2, longest + 1):
            live = live[(cap[live] >= l) & ~met[live]]
            if not len(live):
                break
            u = rng.floats(rng.keyed(seed, ids[live], 16 + l))
            pick = np.minimum((u[:, None] >= self.table(l)[now[live]]).sum(1), 8)
            nxt = np.where(pick < 8, self.model.near[now[live], np.minimum(pick, 7)], -1)
            met[live[nxt < 0]] = True
            go = live[nxt >= 0]
            now[go] = nxt[nxt >= 0]
            cells[go, l - 1] = now[go]
            length[go] = l
            live = go
        return cells, length, cap, met


def synthesize(spark: SparkSession, model: Model, n: int, seed: int = 0, reweight: bool = True, slices: int | None = None, length_index: str = "position") -> DataFrame:
    """(traj_id, cells, n_cells, cap, stop): n trips; stop is virtual_end or cap."""
    walker = Walker(model, reweight, length_index)

    def run(batches):
        for batch in batches:
            for a in range(0, batch.num_rows, 8192):
                ids = batch.column(0).slice(a, 8192).to_numpy()
                cells, length, cap, met = walker.walk(ids, seed)
                inside = np.arange(cells.shape[1]) < length[:, None]
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]), pa.int32()), pa.array(cells[inside]))
                stop = pa.array(np.where(met, "virtual_end", "cap"))
                yield pa.RecordBatch.from_arrays([pa.array(ids), lists, pa.array(length.astype(np.int32)), pa.array(cap.astype(np.int32)), stop], ["traj_id", "cells", "n_cells", "cap", "stop"])

    base = spark.range(0, n, 1, slices) if slices else spark.range(n)
    return base.mapInArrow(run, "traj_id long, cells array<int>, n_cells int, cap int, stop string")


# ---- whole-number weights, for other SQL engines ------------------------------


def synthesize_sql(spark: SparkSession, grid: Grid, lengths: dict[int, int], weights: dict[tuple[int, int], int], n: int, seed: int, a: int = 3, b: int = 2, unit: int = 10) -> DataFrame:
    """Trips from whole-number weights: lengths {len: weight}, weights {(src, dst): weight} with START and END.

    Stop weights are scaled by (a + b * l) / unit. Each draw takes floor(u * total) and the first running sum above it.
    """
    from .grid import END, START

    lens = sorted(k for k, v in lengths.items() if v > 0)
    cum = np.cumsum([lengths[k] for k in lens]).tolist()
    first = [(c, weights.get((START, c), 0)) for c in range(grid.cells)]
    first_cum = np.cumsum([w for _, w in first]).tolist()
    rows = []
    for c in range(grid.cells):
        own = [(d, weights.get((c, d), 0) * unit) for d in grid.neighbours(c)]
        sums = np.cumsum([w for _, w in own]).tolist()
        rows.append(([d for d, _ in own], sums, weights.get((c, END), 0)))
    arr = lambda xs, kind: F.array(*[F.lit(int(x)) for x in xs]).cast(f"array<{kind}>")
    near = F.array(*[arr(r[0], "int") for r in rows])
    sums = F.array(*[arr(r[1], "bigint") for r in rows])
    ends = arr([r[2] for r in rows], "bigint")
    pick = lambda running, r: F.size(F.filter(running, lambda s: s <= r))
    draw = lambda total, *keys: F.floor(rng.u01(seed, F.col("traj_id"), *keys) * total)
    t = spark.range(n).withColumnRenamed("id", "traj_id")
    t = t.withColumn("cap", F.get(arr(lens, "int"), pick(arr(cum, "bigint"), draw(F.lit(cum[-1]), "len"))))
    t = t.withColumn("start", pick(arr(first_cum, "bigint"), draw(F.lit(first_cum[-1]), "start")))

    def step(state, l):
        cur = F.element_at(state["cells"], -1)
        moves = F.get(sums, cur)
        stop = F.get(ends, cur) * (F.lit(a) + F.lit(b) * l)
        total = F.element_at(moves, -1) + stop
        at = pick(moves, draw(total, l))
        over = state["done"] | (total <= 0) | (at >= F.size(moves))
        return F.struct(F.when(over, state["cells"]).otherwise(F.concat(state["cells"], F.array(F.get(F.get(near, cur), at)))).alias("cells"), over.alias("done"))

    path = F.aggregate(F.when(F.col("cap") >= 2, F.sequence(F.lit(2), F.col("cap"))).otherwise(F.array().cast("array<int>")), F.struct(F.array("start").alias("cells"), F.lit(False).alias("done")), step)
    return t.select("traj_id", path["cells"].alias("cells"), "cap").withColumn("n_cells", F.size("cells"))
