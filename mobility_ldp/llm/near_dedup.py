"""Near-duplicate classes by ProbMinHash signatures, banding and exact verification.

Texts are sets of hashed runs of five lower-cased words (a text of fewer words
is one run). A signature has m registers. Each shingle sends a Poisson process
of arrivals, at a rate of its weight, to random registers; a register keeps its
first arrival. A shingle stops as soon as its next arrival comes after the
latest first arrival of all registers, so most shingles stop after one or two.
Registers of two texts agree with a probability that is their probability
Jaccard similarity. The bands give each distinct shingle the same weight, which
makes that the Jaccard similarity of the sets: how often a text repeats a
shingle does not count, as it does not for links.

Texts of equal word sequences are merged first (a hash aggregate). The rest
meets in bands of registers. A bucket of at most BLOCK texts is one block: a
product of its incidence matrix (texts by the shingles that two of them share)
has all its intersections, and a block gives the edges of a forest, not its
pairs. Blocks of the same texts in several bands are looked at once. The texts
of larger buckets that have the same first text, their pivot, are one group.
They are strewn over blocks at random, each block with the pivot in it, which
joins nearly all copies of one text. What is left outside the largest
component of its group is held against the whole group in tiles of up to
1,024 by 1,024 texts, if it is at most WIDE texts. If it is more, use is made
of this: two texts that are near to each other but not to the
pivot differ from it by shared shingles; so the texts of the group meet again
under (pivot, shingle by which they differ), in groups to which all the same is
done, until none is left. Links are exact: the Jaccard similarity of the whole shingle sets is at
least the threshold, as a fraction of integers. Classes are the connected
components, found by rounds of large and small stars.

Texts without words are alone in their class. Null ids stay null and are
ordered first; repeated rows fall into one class. Rows and word sequences are
known by two hashes of 64 bits each.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import shared, textops

SHINGLE, THRESHOLD = 5, 0.8
#: Bands and registers in a band. A pair at the threshold misses all with probability (1 - 0.8**5)**24 = 7e-5.
BANDS, ROWS = 24, 5
BASE = 0x9E6C63D0676A9A99
GOLDEN = 0x9E3779B97F4A7C15
MASK = (1 << 64) - 1
#: Texts, and shingles of them all, up to which a group is one block.
BLOCK, BLOCK_SHINGLES = 256, 1 << 20
#: Texts outside the largest component of a large group up to which each is held against all of the group.
WIDE = 1 << 14
#: Columns of an incidence matrix that are multiplied at once.
TILE = 4096
#: Pairs of a tile that share a shingle up to which they are counted one by one, and how many are at once.
RARE, PAIRS = 4096, 1 << 20
#: Rows of two or three 64-bit numbers up to which a join sends a table to all executors.
BROADCAST_KEYS = 1_000_000
WORD_PATTERN = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"


def shingles(data, offsets, ranges, n=SHINGLE):
    """Hashes of the runs of n words of each document (bounds by document), each document's number of words, and two hashes of its words."""
    starts, ends, per = textops.words(data, offsets)
    (wh,) = ranges(textops.LOWER[data], starts, ends) if len(starts) else (np.zeros(0, np.uint64),)
    total = np.zeros(len(wh), np.uint64)
    size = np.diff(per)
    doc = textops.owners(per)
    place = np.arange(len(wh)) - per[:-1][doc]
    short = (size < n)[doc]
    for j in range(n):
        factor = np.uint64(pow(0xD1342543DE82EF95, j + 1, 1 << 64))
        total[: len(wh) - j] += wh[j:] * factor if j else wh * factor
    keep = (place <= size[doc] - n) & ~short
    # a text of fewer words: its only run, over the words that it has
    if short.any():
        for j in range(n - 1, 0, -1):
            tail = short & (place == 0) & (size[doc] == j)
            at = np.flatnonzero(tail)
            value = np.full(len(at), np.uint64(j), np.uint64)
            for k in range(j):
                value += wh[at + k] * np.uint64(pow(0xD1342543DE82EF95, k + 1, 1 << 64))
            total[at] = value
            keep |= tail
    hashes = textops.mix(total[keep])
    counts = np.bincount(doc[keep], minlength=len(size))
    bounds = np.concatenate([[0], np.cumsum(counts)])
    # words in order: a chained sum that depends on the place
    stamp, whole = wh + (place.astype(np.uint64) + np.uint64(1)) * np.uint64(GOLDEN), []
    for _ in range(2):
        stamp = textops.mix(stamp)
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(stamp, dtype=np.uint64)])
        whole.append(textops.mix(sums[per[1:]] - sums[per[:-1]] + size.astype(np.uint64)))
    return hashes, bounds, size, whole


def weighted(hashes, bounds):
    """Distinct hashes of each document, sorted, with their counts, and the new bounds."""
    doc = textops.owners(bounds)
    order = np.lexsort((hashes, doc))
    h, d = hashes[order], doc[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    first = np.flatnonzero(new)
    counts = np.diff(np.append(first, len(h)))
    return h[first], counts, np.searchsorted(d[first], np.arange(len(bounds)))


def signatures(hashes, weights, bounds, m):
    """ProbMinHash registers (documents x m): the shingle whose arrival came first; 0 for documents without shingles."""
    n = len(bounds) - 1
    first, sig = np.full(n * m, np.inf), np.zeros(n * m, np.uint64)
    doc = textops.owners(bounds)
    live, time, turn, step = np.arange(len(hashes)), np.zeros(len(hashes)), 0, 1
    while len(live):
        # the more turns a text needs, the more arrivals are drawn at once
        step = 1 if turn < 2 else min(64, 2 * step)
        salt = np.array([(turn + k + 1) * GOLDEN & MASK for k in range(step)], np.uint64)
        turn += step
        x = textops.mix(hashes[live][:, None] + salt)
        gaps = -np.log(((x >> np.uint64(11)).astype(np.float64) + 1) * 2.0**-53) / weights[live][:, None]
        when = time[:, None] + np.cumsum(gaps, 1)
        y = textops.mix(x ^ np.uint64(0xA5A5A5A5A5A5A5A5))
        at = doc[live][:, None] * m + (y % np.uint64(m)).astype(np.int64)
        np.minimum.at(first, at.ravel(), when.ravel())
        won = first[at] == when
        sig[at[won]] = np.broadcast_to(hashes[live][:, None], at.shape)[won]
        own, back = np.unique(doc[live], return_inverse=True)
        time = when[:, -1]
        going = time < first.reshape(n, m)[own].max(1)[back]
        live, time = live[going], time[going]
    return sig.reshape(n, m)


def _signed(text_at, n, bands, rows, names):
    """Adds ka, kb (hashes of the words; null without words), size (distinct shingles) and a hash of each band; takes the text away."""

    def run(batches):
        ranges = textops.RangeHash(BASE)
        for batch in batches:
            data, offsets = textops.buffers(batch.column(text_at))
            cols = [c for k, c in enumerate(batch.columns) if k != text_at]
            for i, j in textops.chunks(offsets):
                h, b, size, whole = shingles(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], ranges, n)
                h, _, b = weighted(h, b)
                # equal weights: registers then agree with exactly the similarity that is verified
                sig = signatures(h, np.ones(len(h)), b, bands * rows).reshape(-1, bands, rows)
                band = np.zeros((j - i, bands), np.uint64)
                for k in range(rows):
                    band = textops.mix(band * np.uint64(GOLDEN) + sig[:, :, k] + np.uint64(k + 1))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (j - i + 1) * bands, bands), pa.int32()), pa.array(band.reshape(-1).view(np.int64)))
                keys = [pa.array(x.view(np.int64), mask=size == 0) for x in whole]
                yield pa.RecordBatch.from_arrays([*(c.slice(i, j - i) for c in cols), *keys, pa.array(np.diff(b), pa.int64()), lists], names)

    return run


def _sets(n):
    """(node, text) -> node and the sorted distinct shingles."""

    def run(batches):
        ranges = textops.RangeHash(BASE)
        for batch in batches:
            data, offsets = textops.buffers(batch.column(1))
            for i, j in textops.chunks(offsets):
                h, b, _, _ = shingles(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], ranges, n)
                h, _, b = weighted(h, b)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.ListArray.from_arrays(pa.array(b, pa.int32()), pa.array(h.view(np.int64)))], ["node", "sh"])

    return run


def near(both, a, b, threshold: Fraction):
    """Whether sets of a and b members with so many in both are near: integers only."""
    return both * (threshold.numerator + threshold.denominator) >= threshold.numerator * (a + b)


def forest(values: np.ndarray, bounds: np.ndarray, threshold: Fraction) -> np.ndarray:
    """For each set of a block (sorted distinct values within bounds) the place of the first set of its component."""
    n, size = len(bounds) - 1, np.diff(bounds)
    order = np.argsort(values, kind="stable")
    v, owner = values[order], np.repeat(np.arange(n), size)[order]
    new = np.ones(len(v), bool)
    new[1:] = v[1:] != v[:-1]
    column = np.cumsum(new) - 1
    # values of one set alone are in no intersection
    met = np.bincount(column, minlength=1)[column] > 1
    column, owner = column[met], owner[met]
    fresh = np.ones(len(column), bool)
    fresh[1:] = column[1:] != column[:-1]
    column = np.cumsum(fresh) - 1
    both = np.zeros((n, n), np.int64)
    for low in range(0, int(column[-1]) + 1 if len(column) else 0, TILE):
        a, b = np.searchsorted(column, [low, low + TILE])
        tile = np.zeros((n, min(TILE, int(column[b - 1]) + 1 - low)), np.float32)
        tile[owner[a:b], column[a:b] - low] = 1
        both += (tile @ tile.T).astype(np.int64)
    linked = near(both, size[:, None], size[None], threshold)
    np.fill_diagonal(linked, True)
    label = np.arange(n)
    while True:
        least = np.where(linked, label[None], n).min(1)
        if (least == label).all():
            return label
        label = least


def across(values: np.ndarray, bounds: np.ndarray, n: int, threshold: Fraction) -> np.ndarray:
    """The same as forest() where only pairs of one of the first n sets and one of the others count."""
    size, cut, m = np.diff(bounds), bounds[n], len(bounds) - 1 - n
    _, column = np.unique(values, return_inverse=True)
    owner = np.repeat(np.arange(n + m), size)
    own, other = column[:cut], column[cut:]
    n_own, n_other = (np.bincount(c, minlength=int(column.max(initial=0)) + 1) for c in (own, other))
    pairs = n_own * n_other
    both = np.zeros((n, m), np.int64)
    # what many pairs share: products of matrices
    dense = pairs > RARE
    place = np.cumsum(dense) - 1
    sides = [(owner[:cut][dense[own]], place[own[dense[own]]]), (owner[cut:][dense[other]] - n, place[other[dense[other]]])]
    for low in range(0, int(dense.sum()), TILE):
        tiles = []
        for (at, col), rows in zip(sides, (n, m), strict=True):
            on = (col >= low) & (col < low + TILE)
            tile = np.zeros((rows, min(TILE, int(dense.sum()) - low)), np.float32)
            tile[at[on], col[on] - low] = 1
            tiles.append(tile)
        both += (tiles[0] @ tiles[1].T).astype(np.int64)
    # what few pairs share: the pairs
    rare = (pairs > 0) & ~dense
    left, at = owner[:cut][rare[own]], own[rare[own]]
    order = np.argsort(other, kind="stable")
    start, met = (np.cumsum(n_other) - n_other)[at], n_other[at]
    ends = np.cumsum(met)
    i = 0
    while i < len(at):
        j = max(i + 1, int(np.searchsorted(ends, ends[i] - met[i] + PAIRS, "right")))
        k = met[i:j]
        right = order[np.repeat(start[i:j] - (np.cumsum(k) - k), k) + np.arange(k.sum())]
        both += np.bincount(np.repeat(left[i:j], k) * m + owner[cut:][right] - n, minlength=n * m).reshape(n, m)
        i = j
    a, b = np.nonzero(near(both, size[:n, None], size[None, n:], threshold))
    label, b = np.arange(n + m), b + n
    while True:
        before = label.copy()
        np.minimum.at(label, b, label[a])
        np.minimum.at(label, a, label[b])
        if (label == before).all():
            return label


def _blocks(links, threshold):
    """Rows (block, ...), sorted by block -> links (a, b): each text and the first of its component in the block."""

    def run(batches):
        left = None
        for batch in batches:
            if left is not None:
                batch = pa.Table.from_batches([left, batch]).combine_chunks().to_batches()[0]
            block = batch.column(0).to_numpy()
            if not len(block):
                continue
            # the last block may go on in the next batch
            stop = int(np.searchsorted(block, block[-1]))
            yield from links(batch.slice(0, stop), threshold)
            left = batch.slice(stop)
        if left is not None:
            yield from links(left, threshold)

    return run


def _joined(x, label):
    """Nodes with the least node that has the same label, those left out that have it themselves."""
    low = np.full(len(x), np.iinfo(np.int64).max)
    np.minimum.at(low, label, x)
    low = low[label]
    return x[low < x], low[low < x]


def _tile_links(batch, threshold):
    """Of rows (block, outside, node, sh), those outside first in each block: each of them against the others."""
    if not batch.num_rows:
        return
    block, outside, node, lists = batch.column(0).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False), batch.column(2).to_numpy(), batch.column(3)
    at, values = lists.offsets.to_numpy().astype(np.int64), lists.values.to_numpy()
    first = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
    for i, j in zip(first, np.append(first[1:], len(block)), strict=True):
        a, b = _joined(node[i:j], across(values[at[i] : at[j]], at[i : j + 1] - at[i], int(outside[i:j].sum()), threshold))
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])


def _links(batch, threshold):
    """Of rows (block, node, sh): all pairs of each block."""
    if not batch.num_rows:
        return
    block, node, lists = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2)
    at, values = lists.offsets.to_numpy().astype(np.int64), lists.values.to_numpy().view(np.uint64)
    first = np.flatnonzero(np.concatenate([[True], block[1:] != block[:-1]]))
    a, b = [], []
    for i, j in zip(first, np.append(first[1:], len(block)), strict=True):
        x = node[i:j]
        if j - i == 2:
            p, q = values[at[i] : at[i + 1]], values[at[i + 1] : at[j]]
            place = np.searchsorted(q, p)
            place[place == len(q)] = 0
            label = np.array([0, 0 if near(int((q[place] == p).sum()), len(p), len(q), threshold) else 1])
        else:
            label = forest(values[at[i] : at[j]], at[i : j + 1] - at[i], threshold)
        x, low = _joined(x, label)
        a.append(x)
        b.append(low)
    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], ["a", "b"])


def slots(size, threshold: Fraction):
    """How many of the shingles by which a text of so many shingles differs from its pivot must hold one that a text near to it differs by too.

    A text a with Jaccard(a, x) >= threshold differs from x by at most t = |x| (1 - threshold) / threshold
    shingles. If what a and x differ from the pivot by has nothing in common, both are linked to it. Else, in
    any order that both share, at most t shingles of x come before the first that is common.
    """
    return size * (threshold.denominator - threshold.numerator) // threshold.numerator + 1


#: Shingles of differences after which a batch is sent on.
FLUSH = 1 << 18


def _verify(threshold):
    """Rows (node, sh, pivot, psh) -> slots(), and the shingles that only one of both has."""
    names = ["node", "pivot", "slots", "delta"]

    def run(batches):
        for batch in batches:
            node, a, pivot, b = batch.columns
            ao, bo = a.offsets.to_numpy(), b.offsets.to_numpy()
            av, bv = a.values.to_numpy(), b.values.to_numpy()
            start, fits, deltas, ends = 0, [], [np.zeros(0, np.int64)], [0]
            for r in range(len(node)):
                x, y = av[ao[r] : ao[r + 1]], bv[bo[r] : bo[r + 1]]
                fits.append(slots(len(x), threshold))
                deltas.append(np.setxor1d(x, y, assume_unique=True))
                ends.append(ends[-1] + len(deltas[-1]))
                if r + 1 == len(node) or ends[-1] > FLUSH:
                    n = r + 1 - start
                    lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(deltas)))
                    yield pa.RecordBatch.from_arrays([node.slice(start, n), pivot.slice(start, n), pa.array(fits, pa.int64()), lists], names)
                    start, fits, deltas, ends = r + 1, [], [np.zeros(0, np.int64)], [0]

    return run


def attached(rows: DataFrame, table: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    """rows joined with a written table, which goes to all executors if it is small. If not, Spark can split the rows of a hot key, as the table is read for this join alone."""
    return rows.join(F.broadcast(table) if few(table) else table, on, how)


def few(table: DataFrame) -> bool:
    return table.count() <= BROADCAST_KEYS


def _settled(edges: DataFrame) -> bool:
    """Whether each u has one edge, to a v that has none of its own."""
    ends = edges.select(F.col("u").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(edges.select(F.col("v").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("into")))
    return ends.groupBy("x").agg(F.sum("out").alias("out"), F.max("into").alias("into")).where("out > 1 or out + into > 1").isEmpty()


def components(links: DataFrame, written: list[str] | None = None) -> DataFrame:
    """(node, root) for the nodes of the links (a, b): the least node of each connected component; a root itself has no row.

    Rounds of large-star and small-star, each written to the shared folder, until all components are stars. The
    path of the table that is returned is added to written.
    """
    spark = links.sparkSession
    edges = links.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    edges, path = shared.put(edges, "edges")
    while not _settled(edges):
        paths, small = [path], few(edges)

        def beside(df, small=small, paths=paths):
            """df to be joined: sent to all, or written first, so that Spark can split the rows of a hub."""
            if small:
                return F.broadcast(df)
            df, at = shared.put(df, "beside")
            paths.append(at)
            return df

        # large star: a node's greater neighbours go to its least neighbour (itself among them)
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(beside(least), "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # small star: a node and its lesser neighbours go to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        star = large.join(beside(low), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).where(F.col("u") != F.col("v")).distinct()
        edges, path = shared.put(star, "edges")
        shared.remove(spark, *paths)
    if written is not None:
        written.append(path)
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _differing(tried: DataFrame, members: DataFrame, keep) -> DataFrame:
    """(under, d, node, size, root): each text of tried under its pivot and the shingles d by which it can meet the texts near to it.

    tried: (node, pivot, slots, delta) with all the texts of each pivot. Shingles by which only one text, or only
    texts of one root, differ from the pivot come first in the order of slots(): nothing is to be found under them. Rarer ones are next.
    """
    each = attached(tried.select("node", "slots", F.size("delta").alias("n_delta"), "delta", F.col("pivot").alias("under")), members, ["node"])
    each = each.select("node", "slots", "n_delta", "under", "size", "root", F.explode("delta").alias("d"))
    shared_by = each.groupBy("under", "d").agg(F.count("*").alias("n"), F.min("root").alias("r1"), F.max("root").alias("r2")).where(F.col("r1") != F.col("r2")).select("under", "d", "n")
    met = attached(each, keep(shared_by, "shared-by"), ["under", "d"])
    own = Window.partitionBy("node", "under")
    placed = met.withColumn("place", F.row_number().over(own.orderBy("n", "d"))).withColumn("met", F.count("*").over(own))
    return placed.where(F.col("place") + F.col("n_delta") - F.col("met") <= F.col("slots")).select("under", "d", "node", "size", "root")


def _dealt(node: str, salt: int, parts) -> Column:
    return F.pmod(F.xxhash64(F.lit(salt), node), F.greatest(F.lit(1), F.ceil(parts)))


def _strewn(pairs: DataFrame, sized: DataFrame, salt: int) -> DataFrame:
    """(block, node): the texts (node, pivot) of each pivot strewn over blocks at random, and the pivot in each of its blocks."""
    parts = F.greatest(F.col("n") * 4 / (3 * BLOCK), F.col("s") / BLOCK_SHINGLES)
    own = attached(pairs.where(F.col("node") != F.col("pivot")), sized, ["pivot"]).select("pivot", _dealt("node", salt, parts).alias("t"), "node")
    heads = sized.select("pivot", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(1), F.ceil(parts)) - 1)).alias("t"), F.col("pivot").alias("node"))
    return own.unionByName(heads).select(F.xxhash64("pivot", "t").alias("block"), "node")


def _tiled(members: DataFrame, open_: DataFrame) -> DataFrame:
    """(block, outside, node): tiles in which each text of a pivot that is not of its largest component meets every text of the pivot.

    members: (node, pivot, root); open_: (pivot, top, n, s, u, us): texts and their shingles, all of them and those
    outside. A group has some 16 tiles at first, and more when a side would be over four blocks; their rows are 2 n u / side.
    """
    own, zero = attached(members, open_, ["pivot"]), F.lit(0).cast("long")
    side = F.greatest(F.lit(BLOCK / 2), F.least(F.lit(BLOCK * 4.0), F.sqrt(F.col("n") * F.col("u")) / 4))
    parts = lambda n, s: F.greatest(F.col(n) / side, F.col(s) / BLOCK_SHINGLES)
    count = lambda n, s: F.greatest(F.lit(1), F.ceil(parts(n, s)))
    every = own.select("pivot", "node", F.lit(False).alias("outside"), _dealt("node", 12, parts("n", "s")).alias("j"), F.explode(F.sequence(zero, count("u", "us") - 1)).alias("i"))
    outside = own.where(F.col("root") != F.col("top")).select("pivot", "node", F.lit(True).alias("outside"), _dealt("node", 11, parts("u", "us")).alias("i"), F.explode(F.sequence(zero, count("n", "s") - 1)).alias("j"))
    return every.unionByName(outside).select(F.xxhash64("pivot", "i", "j").alias("block"), "outside", "node")


def links(texts: DataFrame, keys: DataFrame, threshold: float = THRESHOLD, n: int = SHINGLE) -> DataFrame:
    """Verified links (a, b) between nodes: all pairs near to each other that share a bucket end in one component.

    texts: (ra, rb, text); keys: one row (node, ra, rb, size, bands) for each word sequence.
    A pivot comes before its texts in the order of nodes, and that of their groups after it, so the rounds end.
    """
    spark, exact = texts.sparkSession, Fraction(str(threshold))
    num, den = exact.numerator, exact.denominator
    groups = keys.select("node", "size", F.col("node").alias("root"), F.posexplode("bands").alias("band", "value")).select("node", "size", "root", F.xxhash64("band", "value").alias("bucket"))
    by, found, tried, sets, paths = ["bucket"], [], None, None, []

    def keep(df, name):
        df, at = shared.put(df, name)
        paths.append(at)
        return df

    def resolve(blocks):
        """Looks at all pairs of each block (block, node), or of each tile (block, outside, node)."""
        tiles = ["outside"] if "outside" in blocks.columns else []
        dealt = attached(sets, blocks, ["node"]).select("block", *tiles, "node", "sh").repartition("block").sortWithinPartitions("block", *[F.col(c).desc() for c in tiles])
        found.append(keep(dealt.mapInArrow(textops.tidy(_blocks(_tile_links if tiles else _links, exact)), "a long, b long").distinct(), "found"))

    def rooted(pairs):
        return attached(pairs, components(_union(found), paths), ["node"], "left").withColumn("root", F.coalesce("root", "node"))

    while True:
        ends = groups.groupBy(*by).agg(F.count("*").alias("n"), F.sum("size").alias("s"), F.min("size").alias("lo"), F.max("size").alias("hi"), F.min("node").alias("pivot"), F.min("root").alias("r1"), F.max("root").alias("r2"))
        # groups of one root are done, and so are two texts whose sizes rule out a link
        ends = keep(ends.where((F.col("r1") != F.col("r2")) & ((F.col("n") > 2) | (F.col("lo") * den >= F.col("hi") * num))).select(*by, "n", "s", "pivot"), "groups")
        held = attached(groups, ends, by)
        is_block = (F.col("n") <= BLOCK) & (F.col("s") <= BLOCK_SHINGLES)
        blocks = held.where(is_block).groupBy(*by).agg(F.sort_array(F.collect_list("node")).alias("nodes")).select("nodes").distinct()
        blocks = keep(blocks.select(F.xxhash64("nodes").alias("block"), F.explode("nodes").alias("node")), "blocks")
        pairs = None
        if not ends.where(~is_block).isEmpty():
            # the texts of all large groups of one pivot (itself among them) are one
            pairs = held.where(~is_block).select("node", "size", "pivot").distinct()
            if tried is not None:
                new = pairs.join(tried, ["node", "pivot"], "left_anti").select("pivot").distinct()
                pairs = attached(pairs, keep(new, "new"), ["pivot"], "left_semi")
            pairs = keep(pairs, "pairs")
            if pairs.isEmpty():
                pairs = None
        if sets is None:
            wanted = blocks.select("node") if pairs is None else blocks.select("node").unionByName(pairs.select("node"))
            wanted = keep(attached(keys.select("node", "ra", "rb"), keep(wanted.distinct(), "ends"), ["node"], "left_semi"), "wanted")
            chosen = attached(texts, wanted, ["ra", "rb"]).select("node", "text")
            sets = chosen.groupBy("node").agg(F.min("text").alias("text")).mapInArrow(textops.tidy(_sets(n)), "node long, sh array<long>")
            sets = sets if pairs is None else keep(sets, "sets")
        if pairs is None:
            resolve(blocks)
            break
        tried = pairs.select("node", "pivot") if tried is None else tried.unionByName(pairs.select("node", "pivot"))
        sized = keep(pairs.groupBy("pivot").agg(F.count("*").alias("n"), F.sum("size").alias("s")), "sized")
        for salt in (1, 2):
            strewn = keep(_strewn(pairs.select("node", "pivot"), sized, salt), "strewn")
            resolve(strewn.unionByName(blocks) if salt == 1 else strewn)
            members = keep(rooted(pairs), "members")
            tops = members.groupBy("pivot", "root").agg(F.count("*").alias("c"), F.sum("size").alias("s")).groupBy("pivot").agg(F.max(F.struct("c", "root", "s")).alias("x"), F.sum("c").alias("n"), F.sum("s").alias("s"), F.count("*").alias("roots"))
            open_ = keep(tops.where("roots > 1").select("pivot", F.col("x.root").alias("top"), "n", "s", (F.col("n") - F.col("x.c")).alias("u"), (F.col("s") - F.col("x.s")).alias("us")), "open")
            if open_.where(F.col("u") > WIDE).isEmpty():
                break
            pairs = attached(pairs, open_.select("pivot"), ["pivot"], "left_semi")
            sized = attached(sized, open_.select("pivot"), ["pivot"], "left_semi")
        resolve(keep(_tiled(members.select("node", "pivot", "root"), open_.where(F.col("u") <= WIDE)), "tiled"))
        wide = keep(open_.where(F.col("u") > WIDE).select("pivot"), "wide")
        if wide.isEmpty():
            break
        # too many texts far from each other: they meet by what they differ from the pivot by
        pairs = keep(attached(members, wide, ["pivot"], "left_semi"), "wide-pairs")
        # each side of the second join is dealt out for it alone, so that Spark can split the rows of a pivot that very many texts share
        both = pairs.where(F.col("node") != F.col("pivot")).select("node", "pivot").join(sets, "node").join(sets.select(F.col("node").alias("pivot"), F.col("sh").alias("psh")), "pivot").select("node", "sh", "pivot", "psh")
        delta = keep(both.mapInArrow(textops.tidy(_verify(exact)), "node long, pivot long, slots long, delta array<long>"), "delta")
        roots = keep(rooted(pairs.select("node", "size").distinct()), "members")
        groups, by = keep(_differing(delta, roots, keep), "differ"), ["under", "d"]
    out, _ = shared.put(_union(found).distinct(), "links")
    shared.remove(spark, *paths)
    return out


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _key(docs: DataFrame, text_col: str, id_col: str) -> DataFrame:
    own = F.col(f"`{id_col}`"), F.col(f"`{text_col}`")
    return docs.select(own[0].alias("id"), F.xxhash64(*own).alias("ra"), F.xxhash64(F.lit(1), *own).alias("rb"), F.coalesce(own[1], F.lit("")).alias("text"))


def classes(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", threshold: float = THRESHOLD, n: int = SHINGLE, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Rows (id, ra, rb, class_id, class_ra, class_rb): for each row of docs the least id of its class, and the hashes of the row that has it.

    ra and rb are two hashes of a row's id and text. Rows without words have their own id as class_id.
    """
    spark = docs.sparkSession
    texts = _key(docs, text_col, id_col)
    kind = docs.schema[id_col].dataType.simpleString()
    signed = texts.mapInArrow(textops.tidy(_signed(3, n, bands, rows, ["id", "ra", "rb", "ka", "kb", "size", "bands"])), f"id {kind}, ra long, rb long, ka long, kb long, size long, bands array<long>")
    signed, at = shared.put(signed, "signed")
    own = signed.where(F.col("ka").isNotNull())
    keys = own.groupBy("ka", "kb").agg(F.min(F.struct("id", "ra", "rb")).alias("x"), F.min("size").alias("size"), F.min("bands").alias("bands"))
    keys, at2 = shared.put(keys.select(F.monotonically_increasing_id().alias("node"), "x.*", "ka", "kb", "size", "bands"), "keys")
    paths = [at, at2]
    found = links(texts.select("ra", "rb", "text"), keys, threshold, n)
    roots = components(found, paths)
    several = roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
    least = attached(keys.select("node", "id", "ra", "rb"), several, ["node"]).groupBy("root").agg(F.min(F.struct("id", "ra", "rb")).alias("x"))
    least, at = shared.put(least, "least")
    paths.append(at)
    named = attached(several, least, ["root"]).select("node", "x")
    named = keys.join(F.broadcast(named) if few(named) else named, "node", "left").withColumn("x", F.coalesce("x", F.struct("id", "ra", "rb")))
    named, at = shared.put(named.select("ka", "kb", F.col("x.id").alias("class_id"), F.col("x.ra").alias("class_ra"), F.col("x.rb").alias("class_rb")), "named")
    paths.append(at)
    out = attached(own.select("id", "ra", "rb", "ka", "kb"), named, ["ka", "kb"]).drop("ka", "kb")
    lone = signed.where(F.col("ka").isNull()).select("id", "ra", "rb", F.col("id").alias("class_id"), F.col("ra").alias("class_ra"), F.col("rb").alias("class_rb"))
    out, _ = shared.put(out.unionByName(lone), "classes")
    shared.remove(spark, *paths)
    return out


def keep_first(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", **options) -> DataFrame:
    """docs with one row of each class: the one of the least id (of equal rows, any one). Rows without words all stay."""
    a = shared.spare(docs, "ra")
    b = shared.spare(docs.withColumn(a, F.lit(0)), "rb")
    found = classes(docs, text_col, id_col, **options)
    own = F.col(f"`{id_col}`"), F.col(f"`{text_col}`")
    keyed = docs.withColumns({a: F.xxhash64(*own), b: F.xxhash64(F.lit(1), *own)})
    first = (F.col("ra") == F.col("class_ra")) & (F.col("rb") == F.col("class_rb"))
    named = [F.col("ra").alias(a), F.col("rb").alias(b)]
    drop, _ = shared.put(found.where(~first).select(*named).distinct(), "dropped")
    kept = attached(keyed, drop, [a, b], "left_anti")
    again, _ = shared.put(found.where(first).groupBy("ra", "rb").agg(F.count("*").alias("n")).where(F.col("n") > 1).select(*named), "repeated")
    if not again.isEmpty():  # rows of the same id and text
        words = F.coalesce(F.col(f"`{text_col}`"), F.lit("")).rlike(WORD_PATTERN)
        twice = attached(kept, again, [a, b], "left_semi")
        kept = attached(kept, again, [a, b], "left_anti").unionByName(twice.where(words).dropDuplicates([a, b])).unionByName(twice.where(~words))
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns])


def op2(spark, sf_dir: str) -> DataFrame:
    """One row per document: doc_id and class_id, the least doc_id of its class of near duplicates."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text")
    return classes(docs).select(F.col("id").alias("doc_id"), "class_id")


#: All pairs by their shared shingles, and components by reach: exact, and for small tables only. Ids are distinct there.
SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[p:p + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(generate_series(1, greatest(1, len(ws) - 4))) AS p FROM d WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
e AS (SELECT x, y FROM (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2) p
      JOIN n i ON i.doc_id = x JOIN n j ON j.doc_id = y WHERE k >= CAST(0.8 AS DOUBLE) * (i.n + j.n - k)),
c AS (SELECT doc_id AS x, doc_id AS r FROM d UNION SELECT e.y, c.r FROM c JOIN e ON c.x = e.x)
SELECT x AS doc_id, min(r) AS class_id FROM c GROUP BY x
"""
