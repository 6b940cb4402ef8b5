"""Optimized unary encoding: perturbing one-hot vectors, counting, estimating.

A true bit stays with probability 1/2; a false one is raised with probability
q = 1 / (e^eps + 1). eps = inf gives exact counts (the non-private reference).
The "sql" engine is built of column functions over keyed md5 uniforms and can
be repeated by other SQL engines. The fused engine perturbs and counts in one
pass over Arrow batches and hands on sums only, so no report is ever stored;
its uniforms are keyed too, so retries and partitioning change nothing. The key
is a secret, drawn anew for each collection: who knew it and the ids could take
the noise off again. A seed in its place is for experiments and tests only, as
its noise protects nobody.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng


def q_of(eps: float) -> float:
    # in falling powers, so that no budget overflows
    return 0.0 if math.isinf(eps) else math.exp(-eps) / (1.0 + math.exp(-eps))


def p_of(eps: float) -> float:
    return 1.0 if math.isinf(eps) else 0.5


def perturb(item: Column, d: int, eps: float, *keys, engine: str = "md5") -> Column:
    """The raised places of a report on item in 0..d-1; a null or outside item gives the null report (all bits false before)."""
    chance = lambda i: F.when(F.coalesce(i == item, F.lit(False)), p_of(eps)).otherwise(q_of(eps))
    return F.filter(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: rng.u01(*keys, i, engine=engine) < chance(i))


def count(reports: DataFrame, bits: str = "bits", by: list[str] | None = None) -> DataFrame:
    """(item, ones, n) per group: how often each place is raised, and how many reports there are. Places that nobody raised have no row."""
    by = by or []
    n = reports.groupBy(*by).agg(F.count("*").alias("n"))
    ones = reports.select(*by, F.explode(bits).alias("item")).groupBy(*by, "item").agg(F.count("*").alias("ones"))
    return ones.join(F.broadcast(n), by) if by else ones.crossJoin(F.broadcast(n))


def estimate(counts: DataFrame, eps: float) -> DataFrame:
    """counts with the unbiased count est. One eps for all reports: mixed budgets cannot be estimated this way."""
    if "eps" in counts.columns:
        raise ValueError("the reports must all have the same eps")
    q = q_of(eps)
    return counts.withColumn("est", (F.col("ones") - F.col("n") * F.lit(q)) / F.lit(p_of(eps) - q))


def settle(estimates: DataFrame, how: str = "clip", by: list[str] | None = None) -> DataFrame:
    """Post-processing: clipped >= 0. "clip" cuts negatives; "norm_sub" shifts all so that the positives sum to n; "none" keeps them."""
    if how == "none":
        return estimates.withColumn("clipped", F.col("est"))
    if how == "clip":
        return estimates.withColumn("clipped", F.greatest(F.col("est"), F.lit(0.0)))
    if how != "norm_sub":
        raise ValueError(f"no post-processing {how}")
    # the shift: over the k largest, (their sum - n) / k, for the largest k whose least stays positive
    part = Window.partitionBy(*(by or [])).orderBy(F.col("est").desc(), F.col("item"))
    ranked = estimates.withColumn("k", F.row_number().over(part)).withColumn("s", F.sum("est").over(part.rowsBetween(Window.unboundedPreceding, 0)))
    ranked = ranked.withColumn("shift", (F.col("s") - F.col("n")) / F.col("k"))
    whole = Window.partitionBy(*(by or []))
    ranked = ranked.withColumn("d", F.max_by(F.col("shift"), F.when(F.col("est") - F.col("shift") > 0, F.col("k"))).over(whole))
    return ranked.withColumn("clipped", F.greatest(F.col("est") - F.coalesce("d", F.lit(0.0)), F.lit(0.0))).drop("k", "s", "shift", "d")


def variance(n: float, eps: float, f: float = 0.0, exact: bool = False) -> float:
    """Variance of an estimate over n reports; exact adds the part that depends on the true count f."""
    if math.isinf(eps):
        return 0.0
    e = math.exp(-eps)
    return n * 4 * e / (1 - e) ** 2 + (f if exact else 0.0)


def variance_col(n: Column, eps: Column) -> Column:
    return n * 4 * F.exp(eps) / (F.exp(eps) - 1) / (F.exp(eps) - 1)


def _uniform_words(keys: np.ndarray, d: int) -> np.ndarray:
    """len(keys) x d keyed 32-bit numbers; one 64-bit hash makes two."""
    half = (d + 1) // 2
    salt = np.arange(1, half + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    bits = rng.mix(keys[:, None] + salt)
    return bits.view(np.uint32).reshape(len(keys), 2 * half)[:, :d]


def raised(keys: np.ndarray, items: np.ndarray, d: int, eps: float) -> np.ndarray:
    """len(items) x d bits: perturbed one-hot vectors; item -1 is the null report."""
    return raised_by(None if math.isinf(eps) else _uniform_words(keys, d), items, d, eps)


def raised_by(words: np.ndarray | None, items: np.ndarray, d: int, eps: float) -> np.ndarray:
    """The same from len(items) x d uniform 32-bit words; none are needed where eps is inf."""
    if math.isinf(eps):
        out = np.zeros((len(items), d), bool)
        ok = items >= 0
        out[np.flatnonzero(ok), items[ok]] = True
        return out
    out = words < np.uint32(min(0xFFFFFFFF, round(q_of(eps) * 2**32)))
    ok = np.flatnonzero(items >= 0)
    out[ok, items[ok]] = words[ok, items[ok]] < np.uint32(0x80000000)
    return out


#: Bits perturbed at once by the fused engine: few enough for a core's own cache.
BLOCK_BITS = 1 << 17


def column_sums(bits: np.ndarray) -> np.ndarray:
    """How many rows have each bit: sums of bytes over 255 rows at a time, which cannot overflow."""
    rows, d = bits.shape
    whole, total = rows // 255 * 255, np.zeros(d, np.int64)
    if whole:
        total += np.add.reduce(bits[:whole].view(np.uint8).reshape(-1, 255, d), axis=1, dtype=np.uint8).sum(0, dtype=np.int64)
    return total + np.add.reduce(bits[whole:].view(np.uint8), axis=0, dtype=np.uint8)


#: Bits of a trip from which a stream is drawn for it alone (below, starting one would take longer than the bits), and the most of them that may be taken back.
STREAM_BITS, TAKEN_BACK = 1 << 13, 1 / 32
#: Bits of several trips that are drawn at once.
STREAM_BLOCK = 1 << 18


def taken_back(eps: float) -> float:
    """The chance by which a false bit that a fair coin has raised is lowered again: 1 - 2 q, without the loss of digits."""
    return math.tanh(eps / 2)


def _places(words: np.ndarray, n: int, chance: float) -> np.ndarray:
    """Places that are hit, each by chance, in order: a row of them from each row of words, by the gaps between them. Those from n on are to be left out."""
    u = ((words >> np.uint64(11)).astype(np.float64) + 1) * 2.0**-53
    return np.cumsum(np.minimum(np.floor(np.log(u) / math.log1p(-chance)), n) + 1, axis=1).astype(np.int64) - 1


def streamed(keys: np.ndarray, items: np.ndarray, d: int, eps: float) -> np.ndarray:
    """Raised counts of d places: for each key its items.shape[1] reports, every bit of them drawn, from a stream that starts anew at the key.

    A fair coin raises each bit, and a false bit is then taken back by taken_back(): 1/2 for true bits, q for false ones.
    """
    n, total, source, chance = items.shape[1] * d, np.zeros(d, np.int64), rng.Stream(), taken_back(eps)
    width, gaps = (n + 63) // 64, int(n * chance + 5 * math.sqrt(n * chance)) + 8
    step = max(1, STREAM_BLOCK // n)
    for a in range(0, len(keys), step):
        own, starts = items[a : a + step].reshape(-1), rng.stream_starts(keys[a : a + step])
        drawn = np.stack([source.words(start, width + gaps) for start in starts])
        bits = np.unpackbits(drawn[:, :width].view(np.uint8), axis=1, count=n).reshape(-1)
        told = np.flatnonzero(own >= 0)
        true = told * d + own[told]
        coins = bits[true]
        if chance:
            at = _places(drawn[:, width:], n, chance)
            bits[(at + np.arange(len(at))[:, None] * n)[at < n]] = 0
            for row in np.flatnonzero(at[:, -1] < n):  # more gaps than foreseen
                last, used = int(at[row, -1]) + 1, width + gaps
                while last < n:
                    more = last + _places(source.words(starts[row], used + gaps)[None, used:], n, chance)[0]
                    bits[row * n + more[more < n]] = 0
                    last, used = int(more[-1]) + 1, used + gaps
        bits[true] = coins
        total += column_sums(bits.reshape(-1, d))
    return total


#: Reports of a trip from which their number that raises a place is drawn at once.
SUMMED = 8
#: Numbers of raised reports that are drawn at once, and trips that are added up in 16 bits: offsets are at most 127, so 255 trips fit.
SUMMED_BLOCK, SUMMED_ROWS = 1 << 17, 255
_OTHER = np.int16(0x7FFF)


def _cdf(n: int, p: float) -> np.ndarray:
    """P(X <= k) of the binomial, k = 0..n - 1: a uniform number gives X as how many of them it is not below."""
    if p <= 0.0:
        return np.ones(n)
    k = np.arange(1, n + 1)
    logs = np.concatenate([[0.0], np.cumsum(np.log((n - k + 1) / k))]) + np.arange(n + 1) * math.log(p) + np.arange(n, -1, -1) * math.log1p(-p)
    pmf = np.exp(logs - logs.max())
    return (np.cumsum(pmf) / pmf.sum())[:-1]


class Summed:
    """How many of a trip's reports raise each place: one draw of the binomial for each trip and place, in place of one for each report.

    The reports' bits are independent, a place's raised with q in the reports on other items and with 1/2 in those on its own, and
    only their sum over reports is handed on. Its law is that of the sum of the bits. Noise stays each trip's own, keyed by trip.
    """

    def __init__(self, each: int, d: int, eps: float):
        self.each, self.d, self.q, self.p = each, d, q_of(eps), p_of(eps)
        self.full, self.parts = _cdf(each, self.q), {}
        low = np.arange(1 << 16) / 65536
        value = np.searchsorted(self.full, low, "right")
        sure = value == np.searchsorted(self.full, low + 1 / 65536, "left")
        self.base = int(value[1 << 15])
        self.table = np.where(sure & (np.abs(value - self.base) < 128), value - self.base, _OTHER).astype(np.int16)
        self.salt = np.arange(1, (d + 3) // 4 + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)

    def part(self, n: int, p: float) -> np.ndarray:
        if (n, p) not in self.parts:
            self.parts[n, p] = _cdf(n, p)
        return self.parts[n, p]

    def add(self, keys: np.ndarray, items: np.ndarray) -> np.ndarray:
        """Raised counts of d places over trips of these keys, with items.shape[1] reports each (-1: the null report)."""
        row, at = np.nonzero(items >= 0)
        return self.add_at(keys, row, items[row, at])

    def add_at(self, keys: np.ndarray, row: np.ndarray, item: np.ndarray) -> np.ndarray:
        """The same from the reports that are not null: their trips (rows of keys) and items."""
        d, total, salt = self.d, np.zeros(self.d, np.int64), np.uint64(1 << 32)
        # places on which a trip has reports: their draws are their own
        place, count = np.unique(row * d + item, return_counts=True)
        step, wide = max(1, min(SUMMED_ROWS, SUMMED_BLOCK // d)), 4 * len(self.salt)
        got, flags, others, heads = np.empty(min(step, len(keys)) * wide + 8, np.int16), np.zeros(min(step, len(keys)) * wide + 8, bool), [], []
        cuts = np.searchsorted(place, np.arange(0, len(keys) + step, step) * d)
        for k, a in enumerate(range(0, len(keys), step)):
            own = keys[a : a + step]
            bits = rng.mix(own[:, None] + self.salt).view(np.uint16)
            size = bits.size
            part = np.take(self.table, bits.reshape(-1), out=got[:size], mode="wrap").reshape(len(own), wide)
            mine = place[cuts[k] : cuts[k + 1]] - a * d
            part[mine // d, mine % d] = 0
            np.equal(got[:size], _OTHER, out=flags[:size])
            flags[size:] = False
            hit = np.flatnonzero(flags[: (size + 7) // 8 * 8].view(np.uint64))
            if len(hit):
                other = (hit[:, None] * 8 + np.arange(8)).reshape(-1)
                other = other[flags[other]]
                got[other] = 0
                others.append(other + a * wide)
                heads.append(bits.reshape(-1)[other])
            total += np.add.reduce(part, axis=0, dtype=np.int16)[:d]
        total += self.base * len(keys)
        if others:
            row, at = np.divmod(np.concatenate(others), wide)
            more = rng.mix(keys[row] ^ rng.mix(at.astype(np.uint64) + salt))
            u, inside = (np.concatenate(heads) + rng.floats(more)) / 65536, at < d
            total += np.bincount(at[inside], np.searchsorted(self.full, u[inside], "right") - self.base, d).astype(np.int64)
        if len(place):
            row = place // d
            at = place - row * d
            key = keys[row] ^ rng.mix(at.astype(np.uint64) + salt + salt)
            u, v = rng.floats(rng.mix(key + np.uint64(1))), rng.floats(rng.mix(key + np.uint64(2)))
            for c in np.unique(count):
                k = np.flatnonzero(count == c)
                raised = np.searchsorted(self.part(self.each - int(c), self.q), u[k], "right") + np.searchsorted(self.part(int(c), self.p), v[k], "right")
                total += np.bincount(at[k], raised - self.base, d).astype(np.int64)
        return total


def _fused(features, seed, secret):
    """features: (name, column place, what makes the items of it or None, width in reports or 0 for one, domain, eps)."""

    def run(batches):
        total, summed = {name: np.zeros(d + 1, np.int64) for name, _, _, _, d, _ in features}, {}
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for salt, (name, at, made, width, d, eps) in enumerate(features):
                col = batch.column(at) if made is None else made(batch.column(at))
                if width:  # a list of items, filled up with null reports to width
                    offsets = col.offsets.to_numpy()
                    size = np.minimum(np.diff(offsets), width)
                    row = np.repeat(np.arange(len(ids)), size)
                    place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
                    own = col.values.to_numpy(zero_copy_only=False)[offsets[:-1][row] + place].astype(np.int64)
                    if secret is None and width >= SUMMED and not math.isinf(eps):
                        if name not in summed:
                            summed[name] = Summed(width, d, eps)
                        told = own >= 0
                        total[name][d] += len(ids) * width
                        total[name][:d] += summed[name].add_at(rng.keyed(seed, ids, salt), row[told], own[told])
                        continue
                    items = np.full((len(ids), width), -1, np.int64)
                    items[row, place] = own
                else:
                    items = col.fill_null(-1).to_numpy().astype(np.int64)[:, None]
                each = items.shape[1]
                total[name][d] += items.size
                if secret is None and each * d >= STREAM_BITS and taken_back(eps) <= TAKEN_BACK:
                    total[name][:d] += streamed(rng.keyed(seed, ids, salt), items, d, eps)
                    continue
                step = max(1, BLOCK_BITS // (d * each))
                for a in range(0, len(ids), step):
                    own = ids[a : a + step]
                    if math.isinf(eps):
                        words = None
                    elif secret is not None:
                        words = rng.secret_words(secret, own, salt, each * d).reshape(-1, d)
                    else:
                        keys = rng.keyed(seed, own, salt)
                        if width:
                            keys = rng.mix(keys[:, None] + np.arange(width, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93)).reshape(-1)
                        words = _uniform_words(keys, d)
                    total[name][:d] += column_sums(raised_by(words, items[a : a + step].reshape(-1), d, eps))
        names, item, ones, n = [], [], [], []
        for name, x in total.items():
            d = len(x) - 1
            names += [name] * d
            item += range(d)
            ones += x[:d].tolist()
            n += [int(x[d])] * d
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(item, pa.int32()), pa.array(ones, pa.int64()), pa.array(n, pa.int64())], ["feature", "item", "ones", "n"])

    return run


def fused(trips: DataFrame, features: list[tuple[str, Column, int, int, float]], seed: int | None = None, secret: bytes | None = None) -> DataFrame:
    """(feature, item, ones, n): perturbed and counted in one pass.

    features: (name, items, width, domain, eps). items is an INT column (width 0: one report per trip), or an
    ARRAY<INT>, or a pair (column, function) that makes one of the column's Arrow values, of which width reports are made, null reports filling up, so that their number tells nothing.
    Each task hands on one row per item; no id and no report leaves it. The noise is keyed by secret, or by a new
    one; a repeated run of the same DataFrame, or a retried task, raises the same bits. With a seed it is not private.
    """
    if seed is None and secret is None:
        secret = rng.new_secret()
    made = [c if isinstance(c, tuple) else (c, None) for _, c, _, _, _ in features]
    cols = [c.alias(f"f{k}") for k, (c, _) in enumerate(made)]
    spec = [(name, k + 1, made[k][1], width, d, eps) for k, (name, _, width, d, eps) in enumerate(features)]
    own = trips.select(F.col("traj_id").cast("bigint"), *cols)
    sums = own.mapInArrow(_fused(spec, seed, secret), "feature string, item int, ones long, n long")
    return sums.groupBy("feature", "item").agg(F.sum("ones").alias("ones"), F.sum("n").alias("n"))


def simulate(counts: dict[int, int], n: int, d: int, eps: float, seed: int = 0) -> np.ndarray:
    """Raised counts of d places drawn at once: the bits being independent, their sums are binomial. Sees true counts, so for experiments only."""
    draw = np.random.default_rng(seed)
    f = np.array([counts.get(k, 0) for k in range(d)])
    return draw.binomial(f, p_of(eps)) + draw.binomial(n - f, q_of(eps))


def worst_ratio(d: int, eps: float, null_report: bool = False) -> float:
    """The largest ratio of probabilities of one output under two inputs, over all 2^d outputs: e^eps, if the mechanism keeps its promise."""
    q, worst = q_of(eps), 0.0
    inputs = list(range(d)) + ([-1] if null_report else [])
    for out in range(1 << d):
        probs = []
        for x in inputs:
            p = 1.0
            for i in range(d):
                up = 0.5 if i == x else q
                p *= up if out >> i & 1 else 1 - up
            probs.append(p)
        worst = max(worst, max(probs) / min(probs))
    return worst
