"""Nine measures of how well a synthetic set keeps a real one.

Each takes two sets of trips (traj_id, cells) and gives one row (metric,
value). All heavy work is counting by small keys: cells, pairs of ends, bins,
or runs of cells; what follows joins tables bounded by the grid.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.cells import cell_x, cell_y, encode_trip
from . import trajectory
from .grid import Grid

BINS, TOP, N_HOT, LENS = 20, 100, 5, (2, 5)


def _named(df: DataFrame, name: str) -> DataFrame:
    return df.select(F.lit(name).alias("metric"), F.col("value").cast("double").alias("value"))


def jsd(p: DataFrame, q: DataFrame, keys: list[str], base: float = math.e) -> DataFrame:
    """(value): Jensen-Shannon divergence of two counts (keys, n)."""
    share = lambda df, name: df.select(*keys, (F.col("n") / F.sum("n").over(Window.partitionBy())).alias(name))
    j = share(p, "p").join(share(q, "q"), keys, "full_outer").select(F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q"))
    m = (F.col("p") + F.col("q")) / 2
    part = lambda x: F.when(x > 0, x * F.log(x / m)).otherwise(0.0)
    return j.agg((F.sum(part(F.col("p")) + part(F.col("q"))) / 2 / F.lit(math.log(base))).alias("value"))


def density_error(real: DataFrame, syn: DataFrame, grid: Grid | None = None) -> DataFrame:
    return _named(jsd(trajectory.visits(real), trajectory.visits(syn), ["cell"]), "density_error")


def range_queries(spark, grid: Grid, r: float = 1 / 9, n: int = 200, seed: int = 0) -> DataFrame:
    """(qid, x0, x1, y0, y1): boxes of a share r of the space, at keyed places."""
    side = math.sqrt(r)
    w, h = (grid.xmax - grid.xmin), (grid.ymax - grid.ymin)
    q = spark.range(n).select(F.col("id").alias("qid"), (F.lit(grid.xmin) + rng.u01(seed, F.col("id"), "x") * F.lit((1 - side) * w)).alias("x0"), (F.lit(grid.ymin) + rng.u01(seed, F.col("id"), "y") * F.lit((1 - side) * h)).alias("y0"))
    return q.select("qid", "x0", (F.col("x0") + F.lit(side * w)).alias("x1"), "y0", (F.col("y0") + F.lit(side * h)).alias("y1"))


#: Cells whose parts are drawn at once.
PART_BLOCK = 1 << 15


def _parts(sub: int, cells: int):
    """Counts of visits by cell and part of it, of rows (hash of the seed and the trip, cells): u01() of the place and the axis, for a batch."""
    shift = np.uint64(65 - sub.bit_length()) if sub > 1 else None

    def run(batches):
        total = np.zeros(cells * sub * sub, np.int64)
        for batch in batches:
            lists, h = batch.column(1), batch.column(0).to_numpy().view(np.uint64)
            size, v = lists.value_lengths().fill_null(0).to_numpy().astype(np.int64), lists.flatten().to_numpy(zero_copy_only=False)
            end = np.cumsum(size)
            trip, start = np.repeat(np.arange(len(size)), size), end - size
            for a in range(0, len(v), PART_BLOCK):
                own = trip[a : a + PART_BLOCK]
                key = v[a : a + PART_BLOCK].astype(np.int64)
                if sub > 1:
                    at = rng.xx_int(h[own], np.arange(a, a + len(own)) - start[own])
                    for axis in b"xy":
                        key = key * sub + (rng.xx_byte(at, axis) >> shift).astype(np.int64)
                total += np.bincount(key, minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([*(pa.array(x.astype(np.int32)) for x in (at // (sub * sub), at // sub % sub, at % sub)), pa.array(total[at])], ["cell", "a", "b", "n"])

    return run


def spots(trips: DataFrame, grid: Grid, points: str, seed: int, sub: int = 8) -> DataFrame:
    """(x, y, n): points reduced to counts, at the centres of cells, or of sub x sub parts of cells for points drawn evenly."""
    if points == "centre":
        v = trajectory.visits(trips)
        return v.select((F.lit(grid.xmin) + (cell_x(F.col("cell"), grid.n) + 0.5) * F.lit(grid.width)).alias("x"), (F.lit(grid.ymin) + (cell_y(F.col("cell"), grid.n) + 0.5) * F.lit(grid.height)).alias("y"), "n")
    if sub & (sub - 1):
        p = trips.select("traj_id", F.posexplode("cells").alias("pos", "cell"))
        part = lambda axis: F.floor(rng.u01(seed, F.col("traj_id"), F.col("pos"), axis, engine="xx") * sub)
        v = p.select("cell", part("x").alias("a"), part("y").alias("b")).groupBy("cell", "a", "b").agg(F.count("*").alias("n"))
    else:  # the first bits of the same hash tell the part
        v = trips.select(F.xxhash64(F.lit(seed), "traj_id").alias("h"), "cells").mapInArrow(_parts(sub, grid.cells), "cell int, a int, b int, n long").groupBy("cell", "a", "b").agg(F.sum("n").alias("n"))
    at = lambda lo, c, k, size: F.lit(lo) + (c + (k + 0.5) / sub) * F.lit(size)
    return v.select(at(grid.xmin, cell_x(F.col("cell"), grid.n), F.col("a"), grid.width).alias("x"), at(grid.ymin, cell_y(F.col("cell"), grid.n), F.col("b"), grid.height).alias("y"), "n")


def query_detail(real: DataFrame, syn: DataFrame, grid: Grid, r: float = 1 / 9, n_queries: int = 200, seed: int = 0, points: str = "centre", known: DataFrame | None = None) -> DataFrame:
    """(qid, q_real, q_syn, z): counts of the boxes; z is a hundredth of the real total. known: the spots() of the real set, if they are kept."""
    q = F.broadcast(range_queries(real.sparkSession, grid, r, n_queries, seed))
    known = spots(real, grid, points, seed) if known is None else known
    both = known.select("x", "y", F.col("n").alias("r"), F.lit(0).cast("bigint").alias("s")).unionByName(spots(syn, grid, points, seed).select("x", "y", F.lit(0).cast("bigint").alias("r"), F.col("n").alias("s")))
    inside = F.col("x").between(F.col("x0"), F.col("x1")) & F.col("y").between(F.col("y0"), F.col("y1"))
    hit = both.join(q, inside).groupBy("qid").agg(F.sum("r").alias("q_real"), F.sum("s").alias("q_syn"))
    total = known.agg((F.sum("n") / 100).alias("z"))
    return q.select("qid").join(hit, "qid", "left").na.fill(0).crossJoin(F.broadcast(total))


def query_error(real: DataFrame, syn: DataFrame, grid: Grid, **options) -> DataFrame:
    d = query_detail(real, syn, grid, **options)
    return _named(d.agg(F.avg(F.abs(F.col("q_real") - F.col("q_syn")) / F.greatest(F.col("q_real").cast("double"), F.col("z"))).alias("value")), "query_error")


def hotspots(trips: DataFrame, n_h: int = N_HOT) -> DataFrame:
    """(cell, place): the n_h most visited cells; ties go to the smaller cell."""
    top = trajectory.visits(trips).orderBy(F.col("n").desc(), "cell").limit(n_h)
    return top.select("cell", F.row_number().over(Window.orderBy(F.col("n").desc(), "cell")).alias("place"))


def hotspot_error(real: DataFrame, syn: DataFrame, n_h: int = N_HOT) -> DataFrame:
    h = hotspots(real, n_h).withColumnRenamed("place", "a")
    s = hotspots(syn, n_h).withColumnRenamed("place", "b")
    best = sum(1 / (j * math.log(j + 1)) for j in range(1, n_h + 1))
    gain = F.coalesce(F.sum(1 / F.col("a") / F.log(F.col("b") + 1.0)), F.lit(0.0))
    return _named(s.join(h, "cell").agg((1 - gain / F.lit(best)).alias("value")), "hotspot_error")


def kendall(real: DataFrame, syn: DataFrame, grid: Grid, ties: str = "printed") -> DataFrame:
    """Pairs of cells ordered alike less those ordered otherwise. "printed": a tie on either side is alike; "tau_a": it counts as neither."""
    spark = real.sparkSession
    c = spark.range(grid.cells).select(F.col("id").cast("int").alias("cell"))
    v = lambda t, name: trajectory.visits(t).withColumnRenamed("n", name)
    d = c.join(v(real, "r"), "cell", "left").join(v(syn, "s"), "cell", "left").na.fill(0)
    a, b = d.select(F.col("cell").alias("c1"), F.col("r").alias("r1"), F.col("s").alias("s1")), d.select(F.col("cell").alias("c2"), F.col("r").alias("r2"), F.col("s").alias("s2"))
    x = F.signum(F.col("r1") - F.col("r2")) * F.signum(F.col("s1") - F.col("s2"))
    value = F.when(x < 0, -1).otherwise(1) if ties == "printed" else x
    pairs = a.join(F.broadcast(b), F.col("c1") < F.col("c2"))
    return _named(pairs.agg((F.sum(value) / F.lit(grid.cells * (grid.cells - 1) / 2)).alias("value")), "kendall")


def trip_error(real: DataFrame, syn: DataFrame, mode: str = "joint") -> DataFrame:
    """Divergence of (start, end) pairs, or the mean of those of starts and of ends."""
    e = lambda t, *by: trajectory.endpoints(t).groupBy(*by).agg(F.count("*").alias("n"))
    if mode == "joint":
        return _named(jsd(e(real, "first", "last"), e(syn, "first", "last"), ["first", "last"]), "trip_error")
    parts = [jsd(e(real, c), e(syn, c), [c]) for c in ("first", "last")]
    return _named(parts[0].unionByName(parts[1]).agg(F.avg("value").alias("value")), "trip_error")


def travelled(cells: str, grid: Grid) -> Column:
    """Length of the way over the centres: whole numbers of steps along, across and diagonal, so that the sum is exact."""
    c = F.col(cells)
    src, dst = F.slice(c, 1, F.greatest(F.size(c) - 1, F.lit(0))), F.slice(c, 2, F.size(c))
    dx = F.zip_with(src, dst, lambda a, b: F.abs(cell_x(a, grid.n) - cell_x(b, grid.n)))
    dy = F.zip_with(src, dst, lambda a, b: F.abs(cell_y(a, grid.n) - cell_y(b, grid.n)))
    both = F.zip_with(dx, dy, lambda a, b: a * 2 + b)  # touching cells: 2 along, 1 across, 3 diagonal
    count = lambda k: F.size(F.filter(both, lambda v: v == k))
    w, h = grid.width, grid.height
    return count(2) * F.lit(w) + count(1) * F.lit(h) + count(3) * F.lit(math.sqrt(w * w + h * h))


def diameter(cells: str, grid: Grid) -> Column:
    """The largest distance between two cells of a trip."""
    own = F.array_distinct(F.col(cells))
    far = lambda a, b: F.pow((cell_x(a, grid.n) - cell_x(b, grid.n)) * F.lit(grid.width), F.lit(2.0)) + F.pow((cell_y(a, grid.n) - cell_y(b, grid.n)) * F.lit(grid.height), F.lit(2.0))
    return F.sqrt(F.array_max(F.transform(own, lambda a: F.array_max(F.transform(own, lambda b: far(a, b))))))


def _binned(real: DataFrame, syn: DataFrame, value: Column, bins: int, name: str, limit: str) -> DataFrame:
    r, s = real.select(value.alias("v")), syn.select(value.alias("v"))
    if limit == "both":
        top = r.unionByName(s).agg(F.max("v").alias("top"))
    else:
        top = r.agg(F.max("v").alias("top"))
    at = F.when(F.col("top") > 0, F.least(F.floor(F.col("v") / F.col("top") * bins), F.lit(bins - 1))).otherwise(0)
    hist = lambda df: df.crossJoin(F.broadcast(top)).select(at.alias("bin")).groupBy("bin").agg(F.count("*").alias("n"))
    return _named(jsd(hist(r), hist(s), ["bin"]), name)


def length_error(real: DataFrame, syn: DataFrame, grid: Grid, bins: int = BINS, limit: str = "both") -> DataFrame:
    return _binned(real, syn, travelled("cells", grid), bins, "length_error", limit)


def diameter_error(real: DataFrame, syn: DataFrame, grid: Grid, bins: int = BINS, limit: str = "both") -> DataFrame:
    return _binned(real, syn, diameter("cells", grid), bins, "diameter_error", limit)


def patterns(trips: DataFrame, lens: tuple[int, int] = LENS) -> DataFrame:
    """(pattern, n): runs of consecutive cells, as text."""
    def of(k):
        return F.when(F.size("cells") >= k, F.transform(F.sequence(F.lit(1), F.size("cells") - (k - 1)), lambda i: encode_trip(F.slice("cells", i, k)))).otherwise(F.array().cast("array<string>"))

    runs = [of(k) for k in range(lens[0], lens[1] + 1)]
    return trips.select(F.explode(F.concat(*runs)).alias("pattern")).groupBy("pattern").agg(F.count("*").alias("n"))


def top_patterns(trips: DataFrame, k: int = TOP, lens: tuple[int, int] = LENS) -> DataFrame:
    return patterns(trips, lens).orderBy(F.col("n").desc(), "pattern").limit(k)


def pattern_f1(real: DataFrame, syn: DataFrame, k: int = TOP, lens: tuple[int, int] = LENS) -> DataFrame:
    r, s = top_patterns(real, k, lens), top_patterns(syn, k, lens)
    both = r.join(s.select("pattern"), "pattern").agg(F.count("*").alias("x"))
    sizes = r.agg(F.count("*").alias("a")).crossJoin(s.agg(F.count("*").alias("b")))
    return _named(both.crossJoin(sizes).select(F.coalesce(F.try_divide(2.0 * F.col("x"), (F.col("a") + F.col("b")).cast("double")), F.lit(0.0)).alias("value")), "pattern_f1")


def pattern_error(real: DataFrame, syn: DataFrame, k: int = TOP, lens: tuple[int, int] = LENS, outside: str = "counted") -> DataFrame:
    """Mean relative gap over the real top; a synthetic count comes from the whole set, or is 0 outside its top with outside="zero"."""
    s = patterns(syn, lens) if outside == "counted" else top_patterns(syn, k, lens)
    j = top_patterns(real, k, lens).join(s.withColumnRenamed("n", "m"), "pattern", "left").na.fill(0)
    return _named(j.agg(F.avg(F.abs(F.col("n") - F.col("m")) / F.col("n")).alias("value")), "pattern_error")


def evaluate_all(real: DataFrame, syn: DataFrame, grid: Grid, r: float = 1 / 9, n_queries: int = 200, seed: int = 0) -> DataFrame:
    """Nine rows (metric, value)."""
    parts = [
        density_error(real, syn),
        query_error(real, syn, grid, r=r, n_queries=n_queries, seed=seed),
        hotspot_error(real, syn),
        kendall(real, syn, grid),
        trip_error(real, syn),
        length_error(real, syn, grid),
        diameter_error(real, syn, grid),
        pattern_f1(real, syn),
        pattern_error(real, syn),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# ---- many published sets of one grid: all counts of a set in one pass ----------------

#: Rows of a tally up to which it is collected. A grid of 12 x 12 has about 400,000 runs of five touching cells.
MAX_TALLY = 1_000_000
VISITS, ENDS, WAYS, WIDTHS, RUNS, TOO_LONG = range(6)
_BITS = 21


def _summed(keys: list[np.ndarray], n: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    own, at = np.unique(np.concatenate(keys), return_inverse=True)
    return own, np.bincount(at, np.concatenate(n), len(own)).astype(np.int64)


def _farthest(v: np.ndarray, trip: np.ndarray, size: int, grid: Grid) -> np.ndarray:
    """For each trip dx * n + dy of its two cells that are farthest apart: of each row of the grid only the outermost cells can be."""
    n = grid.n
    lo, hi = np.full(size * n, n, np.int64), np.full(size * n, -1, np.int64)
    np.minimum.at(lo, trip * n + v // n, v % n)
    np.maximum.at(hi, trip * n + v // n, v % n)
    lo, hi = lo.reshape(size, n), hi.reshape(size, n)
    best, key = np.full(size, -1.0), np.zeros(size, np.int64)
    for a in range(n):
        for b in range(a, n):
            dx = np.maximum(hi[:, a] - lo[:, b], hi[:, b] - lo[:, a])
            far = (dx * grid.width) ** 2 + ((b - a) * grid.height) ** 2
            more = (hi[:, a] >= 0) & (hi[:, b] >= 0) & (far > best)
            best[more], key[more] = far[more], dx[more] * n + (b - a)
    return key


def _tally(grid: Grid, lens: tuple[int, int]):
    n, cells = grid.n, grid.cells

    def keys_of(lists):
        size = lists.value_lengths().fill_null(0).to_numpy().astype(np.int64)
        start, size = lists.offsets.to_numpy()[:-1][size > 0].astype(np.int64), size[size > 0]
        trip, end = np.repeat(np.arange(len(size)), size), np.cumsum(size)
        left = end[trip] - np.arange(int(size.sum()))  # cells of the trip from here on
        v = lists.values.to_numpy().astype(np.int64)[start[trip] + size[trip] - left]
        yield VISITS, v
        yield ENDS, v[end - size] * cells + v[end - 1]
        at = np.flatnonzero(left > 1)
        both = np.abs(v[at] % n - v[at + 1] % n) * 2 + np.abs(v[at] // n - v[at + 1] // n)
        way = np.zeros(len(size), np.int64)
        for kind in (2, 1, 3):
            way = (way << _BITS) + np.bincount(trip[at][both == kind], minlength=len(size))
        yield WAYS, way
        if len(size) and size.max() >> _BITS:
            yield TOO_LONG, size[size >> _BITS > 0]
        yield WIDTHS, _farthest(v, trip, len(size), grid)
        code = v
        for k in range(2, lens[1] + 1):
            code = code[:-1] * cells + v[k - 1 :]
            if k >= lens[0]:
                yield RUNS + k, code[left[: len(code)] >= k]

    def run(batches):
        found: dict[int, tuple[list, list]] = {}
        held = 0

        def merge():
            return {kind: tuple([x] for x in _summed(*parts)) for kind, parts in found.items()}

        for batch in batches:
            for kind, keys in keys_of(batch.column(0)):
                own, count = np.unique(keys, return_counts=True)
                parts = found.setdefault(kind, ([], []))
                parts[0].append(own)
                parts[1].append(count)
                held += len(own)
            if held > 1 << 20:
                found = merge()
                held = sum(len(parts[0][0]) for parts in found.values()) // 2
        for kind, (keys, count) in merge().items():
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys[0]), kind, np.int32)), pa.array(keys[0]), pa.array(count[0])], ["kind", "key", "n"])

    return run


def tally(trips: DataFrame, grid: Grid, lens: tuple[int, int] = LENS) -> DataFrame:
    """(kind, key, n): all counts that the nine measures need, from one pass over trips of at least one cell. Their number is bounded by the grid, but for the ways of long trips."""
    return trips.select("cells").mapInArrow(_tally(grid, lens), "kind int, key long, n long").groupBy("kind", "key").agg(F.sum("n").alias("n"))


def tallied(trips: DataFrame, grid: Grid, lens: tuple[int, int] = LENS) -> dict[int, tuple[np.ndarray, np.ndarray]] | None:
    """The tally by kind, as keys and counts; None if it is too large for the driver, or a key for a number."""
    if grid.cells ** lens[1] >= 1 << 63:
        return None
    t = tally(trips, grid, lens).persist()
    try:
        if t.count() > MAX_TALLY or not t.where(F.col("kind") == TOO_LONG).isEmpty():
            return None
        rows = t.toArrow()
    finally:
        t.unpersist()
    kind, key, n = (rows.column(c).to_numpy() for c in ("kind", "key", "n"))
    out = {}
    for k in [VISITS, ENDS, WAYS, WIDTHS, *range(RUNS + lens[0], RUNS + lens[1] + 1)]:
        order = np.argsort(key[kind == k])
        out[k] = key[kind == k][order], n[kind == k][order]
    return out


def _jsd(p, q) -> float:
    """jsd() of two (keys, n)."""
    keys, at = np.unique(np.concatenate([p[0], q[0]]), return_inverse=True)
    a, b = np.bincount(at[: len(p[0])], p[1] / p[1].sum(), len(keys)), np.bincount(at[len(p[0]) :], q[1] / q[1].sum(), len(keys))
    m = (a + b) / 2
    part = lambda x: float((x[x > 0] * np.log(x[x > 0] / m[x > 0])).sum())
    return (part(a) + part(b)) / 2


def _hist(value: np.ndarray, n: np.ndarray, top: float, bins: int):
    at = np.minimum(np.floor(value / top * bins), bins - 1).astype(np.int64) if top > 0 else np.zeros(len(value), np.int64)
    count = np.bincount(at, n, bins)
    return np.flatnonzero(count), count[count > 0]


def _binned_tally(real, syn, value, bins: int) -> float:
    r, s = value(real[0]), value(syn[0])
    top = max(r.max(), s.max())
    return _jsd(_hist(r, real[1], top, bins), _hist(s, syn[1], top, bins))


def _way(key: np.ndarray, grid: Grid) -> np.ndarray:
    low, (w, h) = (1 << _BITS) - 1, (grid.width, grid.height)
    return (key >> 2 * _BITS) * w + (key >> _BITS & low) * h + (key & low) * math.sqrt(w * w + h * h)


def _width(key: np.ndarray, grid: Grid) -> np.ndarray:
    return np.sqrt((key // grid.n * grid.width) ** 2 + (key % grid.n * grid.height) ** 2)


def _text(code: int, k: int, cells: int) -> str:
    out = []
    for _ in range(k):
        code, c = divmod(code, cells)
        out.append(str(c))
    return "-".join(reversed(out))


def _top_runs(t, grid: Grid, lens: tuple[int, int], k: int) -> dict[tuple[int, int], int]:
    """{(length, code): n} of the k most frequent runs; ties go to the lesser text."""
    n = np.concatenate([t[RUNS + j][1] for j in range(lens[0], lens[1] + 1)])
    least = np.partition(n, -k)[-k] if len(n) > k else 0
    found = [(-int(c), _text(int(x), j, grid.cells), j, int(x)) for j in range(lens[0], lens[1] + 1) for x, c in zip(*(v[t[RUNS + j][1] >= least] for v in t[RUNS + j]), strict=True)]
    return {(j, x): -c for c, _, j, x in sorted(found)[:k]}


def measures(real: dict, syn: dict, grid: Grid, boxes: list, lens: tuple[int, int] = LENS) -> dict[str, float | None]:
    """The nine values of evaluate_all() from two tallies; boxes: the rows of range_queries()."""
    x, y = (grid.xmin + (np.arange(grid.cells) % grid.n + 0.5) * grid.width), (grid.ymin + (np.arange(grid.cells) // grid.n + 0.5) * grid.height)
    r, s = (np.bincount(t[VISITS][0], t[VISITS][1], grid.cells).astype(np.int64) for t in (real, syn))
    box = {c: np.array([b[c] for b in boxes])[:, None] for c in ("x0", "x1", "y0", "y1")}
    inside = (x >= box["x0"]) & (x <= box["x1"]) & (y >= box["y0"]) & (y <= box["y1"])
    in_r, in_s = inside @ r, inside @ s
    hot = lambda v: {int(c): k + 1 for k, c in enumerate([c for c in np.argsort(-v, kind="stable")[:N_HOT] if v[c]])}
    a, b = hot(r), hot(s)
    gain = sum(1 / a[c] / math.log(b[c] + 1.0) for c in a if c in b)
    one, two = np.triu_indices(grid.cells, 1)
    alike = np.where(np.sign(r[one] - r[two]) * np.sign(s[one] - s[two]) < 0, -1, 1)
    top_r, top_s = _top_runs(real, grid, lens, TOP), _top_runs(syn, grid, lens, TOP)
    gaps = []
    for (j, code), n in top_r.items():
        keys, count = syn[RUNS + j]
        at = int(np.searchsorted(keys, code))
        gaps.append(abs(n - (int(count[at]) if at < len(keys) and keys[at] == code else 0)) / n)
    return {
        "density_error": _jsd(real[VISITS], syn[VISITS]),
        "query_error": float((np.abs(in_r - in_s) / np.maximum(in_r.astype(float), r.sum() / 100)).mean()),
        "hotspot_error": 1 - gain / sum(1 / (j * math.log(j + 1)) for j in range(1, N_HOT + 1)),
        "kendall": float(alike.sum() / (grid.cells * (grid.cells - 1) / 2)) if grid.cells > 1 else None,
        "trip_error": _jsd(real[ENDS], syn[ENDS]),
        "length_error": _binned_tally(real[WAYS], syn[WAYS], lambda k: _way(k, grid), BINS),
        "diameter_error": _binned_tally(real[WIDTHS], syn[WIDTHS], lambda k: _width(k, grid), BINS),
        "pattern_f1": 2.0 * len(top_r.keys() & top_s.keys()) / (len(top_r) + len(top_s)) if top_r or top_s else 0.0,
        "pattern_error": sum(gaps) / len(gaps) if gaps else None,
    }
