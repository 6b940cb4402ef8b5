"""Line dedup by a sharded minimal perfect hash.

1. Each document's distinct line keys are hashed to 128 bits and counted
   (combined per batch, then by a partial and a final hash aggregate).
2. The keys found in min_docs documents or more are dealt into shards by hash.
   Each shard gets a minimal perfect hash (levels of collision-free bits with
   ranks) that indexes a fingerprint array and a count array.
3. Documents probe the arrays; no line is shuffled. The index is sent in groups
   of shards of at most group_bytes. Where one group does not hold it all, the
   texts are read once for each group, and what is written is a bit per line of
   the distinct texts that lose some; the bits meet the rows by the text's key.

Null and empty texts are one empty line. Repeated rows are documents of their
own. A key shorter than min_chars code points is never dropped.
"""

from __future__ import annotations

import hashlib
import io

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import shared, textops

BASES = (0x5851F42D4C957F2D, 0xD6E8FEB86659FD93)
#: Keys in a shard, about; bits of a level for each key; levels before the rest is kept as it is.
SHARD_KEYS, GAMMA, LEVELS = 1 << 16, 2.0, 24
GROUP_BYTES = 64 << 20


def lines_of(data, offsets, ranges, min_chars=1):
    """For lines of the documents in data: bounds by document, two hashes, and whether the key is long enough."""
    newline = np.flatnonzero(data == 10)
    # a line starts at each document's start and after each newline
    n_docs = len(offsets) - 1
    per = np.searchsorted(newline, offsets)
    counts = np.diff(per) + 1
    bounds = np.concatenate([[0], np.cumsum(counts)])
    starts, ends = np.empty(bounds[-1], np.int64), np.empty(bounds[-1], np.int64)
    heads = np.zeros(bounds[-1], bool)
    heads[bounds[:-1]] = True
    starts[heads], starts[~heads] = offsets[:-1], newline + 1
    tails = np.zeros(bounds[-1], bool)
    tails[bounds[1:] - 1] = True
    ends[tails], ends[~tails] = offsets[1:], newline
    solid = np.flatnonzero(~textops.BLANK[data])
    a, b = np.searchsorted(solid, starts), np.searchsorted(solid, ends)
    full = b > a
    s, e = starts.copy(), starts.copy()
    s[full], e[full] = solid[a[full]], solid[b[full] - 1] + 1
    low = textops.LOWER[data]
    h1, h2 = ranges(low, s, e)
    points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    return bounds, n_docs, h1, h2, points[e] - points[s] >= max(1, min_chars)


def _counts(min_chars):
    def run(batches):
        ranges = textops.RangeHash(*BASES)
        for batch in batches:
            data, offsets = textops.buffers(batch.column(0))
            for i, j in textops.chunks(offsets):
                at = offsets[i : j + 1] - offsets[i]
                bounds, _, h1, h2, ok = lines_of(data[offsets[i] : offsets[j]], at, ranges, min_chars)
                doc = textops.owners(bounds)[ok]
                order = np.lexsort((doc, h2[ok], h1[ok]))
                k1, k2, doc = h1[ok][order], h2[ok][order], doc[order]
                if not len(k1):
                    continue
                new_key = np.concatenate([[True], (k1[1:] != k1[:-1]) | (k2[1:] != k2[:-1])])
                new = new_key.copy()
                new[1:] |= doc[1:] != doc[:-1]
                first = np.flatnonzero(new_key)
                n = np.add.reduceat(new.astype(np.int64), first)
                yield pa.RecordBatch.from_arrays([pa.array(k1[first].view(np.int64)), pa.array(k2[first].view(np.int64)), pa.array(n)], ["h1", "h2", "n"])

    return run


def line_counts(docs: DataFrame, text_col: str = "text", min_chars: int = 1) -> DataFrame:
    """Rows (h1, h2, n): in how many documents each line key is found."""
    found = docs.select(F.col(text_col).alias("t")).mapInArrow(textops.tidy(_counts(min_chars)), "h1 long, h2 long, n long")
    return found.groupBy("h1", "h2").agg(F.sum("n").alias("n"))


def build(h1: np.ndarray, h2: np.ndarray, counts: np.ndarray) -> dict[str, np.ndarray]:
    """A minimal perfect hash over distinct (h1, h2), with its fingerprint and count arrays."""
    h1, h2 = h1.view(np.uint64), h2.view(np.uint64)
    left, bits, sizes, slot, base = np.arange(len(h1)), [], [], np.zeros(len(h1), np.int64), 0
    for level in range(LEVELS):
        if not len(left):
            break
        size = max(64, int(len(left) * GAMMA))
        at = textops.mix(h1[left] + np.uint64((level + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) % np.uint64(size)
        hits = np.bincount(at.astype(np.int64), minlength=size)
        alone = hits[at.astype(np.int64)] == 1
        bit = hits == 1
        rank = np.cumsum(bit) - 1
        slot[left[alone]] = base + rank[at[alone].astype(np.int64)]
        base += int(bit.sum())
        bits.append(np.packbits(bit))
        sizes.append(size)
        left = left[~alone]
    slot[left] = base + np.arange(len(left))
    fp, n = np.empty(len(h1), np.uint64), np.empty(len(h1), np.int64)
    fp[slot], n[slot] = h2, counts
    return {"sizes": np.array(sizes, np.int64), "bits": np.concatenate(bits) if bits else np.zeros(0, np.uint8), "fp": fp, "n": n, "rest": h1[left]}


class Shard:
    """The arrays of build(), ready for probing."""

    def __init__(self, arrays):
        self.fp, self.n, self.rest, self.levels = arrays["fp"], arrays["n"], arrays["rest"], []
        at = base = 0
        for size in arrays["sizes"]:
            wide = (int(size) + 7) // 8
            bit = np.unpackbits(arrays["bits"][at : at + wide])[: int(size)].view(bool)
            rank = np.cumsum(bit, dtype=np.int32) + (base - 1)
            self.levels.append((np.uint64(size), bit, rank))
            at, base = at + wide, int(rank[-1]) + 1 if len(rank) else base
        self.base = base

    def counts(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        """The counts of keys; 0 for keys that are not in the index."""
        slot = np.full(len(h1), -1, np.int64)
        left = np.arange(len(h1))
        for level, (size, bit, rank) in enumerate(self.levels):
            at = (textops.mix(h1[left] + np.uint64((level + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) % size).astype(np.int64)
            hit = bit[at]
            slot[left[hit]] = rank[at[hit]]
            left = left[~hit]
        for k, x in enumerate(self.rest):
            slot[left[h1[left] == x]] = self.base + k
        out, seen = np.zeros(len(h1), np.int64), slot >= 0
        ok = np.zeros(len(h1), bool)
        ok[seen] = self.fp[slot[seen]] == h2[seen]
        out[ok] = self.n[slot[ok]]
        return out


def _build_shard(group: pa.Table) -> pa.Table:
    arrays = build(*(group.column(c).to_numpy() for c in ("h1", "h2", "n")))
    out = io.BytesIO()
    np.savez(out, **arrays)
    return pa.table({"shard": pa.array([group.column("shard")[0].as_py()], pa.int64()), "arrays": pa.array([out.getvalue()], pa.binary())})


def index(keys: DataFrame) -> tuple[DataFrame, int]:
    """Shards (shard, arrays) of the index over keys (h1, h2, n), and how many shards there are."""
    shards = max(1, -(-keys.count() // SHARD_KEYS))
    dealt = keys.withColumn("shard", F.pmod(F.col("h1"), F.lit(shards)).cast("long"))
    return dealt.groupBy("shard").applyInArrow(_build_shard, "shard long, arrays binary"), shards


def _drops(index, shards, min_docs, h1, h2, ok):
    """Which lines have a key in the index that is in min_docs documents or more."""
    drop = np.zeros(len(h1), bool)
    home = (h1.view(np.int64) % shards) if shards > 1 else np.zeros(len(h1), np.int64)
    for k, shard in index.items():
        mine = np.flatnonzero(ok & (home == k))
        drop[mine] = shard.counts(h1[mine], h2[mine]) >= min_docs
    return drop


def _flag(sent, shards, min_docs, min_chars):
    """For each text with lines to drop by this part of the index: its key, and a bit per line."""

    def run(batches):
        ranges = textops.RangeHash(*BASES)
        index = {k: Shard(np.load(io.BytesIO(v))) for k, v in sent.value}
        for batch in batches:
            data, offsets = textops.buffers(batch.column(0))
            for i, j in textops.chunks(offsets):
                at = offsets[i : j + 1] - offsets[i]
                part = data[offsets[i] : offsets[j]]
                bounds, _, h1, h2, ok = lines_of(part, at, ranges, min_chars)
                drop = _drops(index, shards, min_docs, h1, h2, ok)
                hit = np.flatnonzero(np.add.reduceat(drop.astype(np.int64), bounds[:-1]))
                keys = [hashlib.md5(part[at[d] : at[d + 1]].tobytes(), usedforsecurity=False).digest() for d in hit]
                bits = [np.packbits(drop[bounds[d] : bounds[d + 1]]).tobytes() for d in hit]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(bits, pa.binary())], ["key", "drop"])

    return run


def _cut(sent, shards, min_docs, min_chars, text_at, drop_at, names):
    """The columns in names and the text without the lines that the index drops, or, at drop_at, lists of bits per line."""

    def run(batches):
        ranges = textops.RangeHash(*BASES)
        index = {k: Shard(np.load(io.BytesIO(v))) for k, v in sent.value} if sent is not None else {}
        for batch in batches:
            text = batch.column(text_at)
            data, offsets = textops.buffers(text)
            kept, n_lines, n_dropped = [], [], []
            for i, j in textops.chunks(offsets):
                at = offsets[i : j + 1] - offsets[i]
                bounds, _, h1, h2, ok = lines_of(data[offsets[i] : offsets[j]], at, ranges, min_chars)
                drop = _drops(index, shards, min_docs, h1, h2, ok)
                if drop_at is not None:
                    for d, flags in enumerate(batch.column(drop_at).slice(i, j - i).to_pylist()):
                        for bits in flags or ():
                            drop[bounds[d] : bounds[d + 1]] |= np.unpackbits(np.frombuffer(bits, np.uint8))[: bounds[d + 1] - bounds[d]].view(bool)
                gone = np.add.reduceat(drop.astype(np.int64), bounds[:-1])
                n_lines.append(np.diff(bounds))
                n_dropped.append(gone)
                own = text.slice(i, j - i)
                if gone.any():
                    hit = np.flatnonzero(gone)
                    lists = pc.split_pattern(pc.fill_null(own, "").take(pa.array(hit)), "\n")
                    keep = np.concatenate([~drop[bounds[d] : bounds[d + 1]] for d in hit])
                    per = np.diff(bounds)[hit] - gone[hit]
                    joined = pc.binary_join(pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(per)]), pa.int32()), lists.flatten().filter(pa.array(keep))), "\n")
                    own = pc.replace_with_mask(own, pa.array(gone > 0), joined)
                kept.append(own)
            whole = pa.concat_arrays(kept) if kept else text.slice(0, 0)
            counts = [pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64()) for x in (n_lines, n_dropped)]
            yield pa.RecordBatch.from_arrays([*(c for k, c in enumerate(batch.columns) if k != drop_at), whole, *counts], [*names, "kept", "n_lines", "n_dropped"])

    return run


def drop_common_lines(docs: DataFrame, text_col: str = "text", min_docs: int = 10, min_chars: int = 1, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """docs with the columns kept_text, n_lines and n_dropped more (suffixed by _ where docs has such a name).

    A null text stays null and counts as one empty line. Other columns pass unchanged, whatever their names.
    """
    spark = docs.sparkSession
    frequent, path = shared.put(line_counts(docs, text_col, min_chars).where(F.col("n") >= min_docs), "lines")
    built, shards = index(frequent)
    stored, at = shared.put(built, "line-index")
    names = [f"c{k}" for k in range(len(docs.columns))]
    text_at = docs.columns.index(text_col)
    now, drop_at = docs.toDF(*names), None
    sizes = [(r[0], r[1]) for r in stored.select("shard", F.octet_length("arrays")).orderBy("shard").collect()]
    groups: list[list[int]] = [[]]
    total = 0
    for shard, size in sizes:
        if total + size > group_bytes and groups[-1]:
            groups, total = [*groups, []], 0
        groups[-1].append(shard)
        total += size

    def send(group):
        rows = stored.where(F.col("shard").isin(group)).collect() if group else []
        return spark.sparkContext.broadcast([(r["shard"], bytes(r["arrays"])) for r in rows])

    if len(groups) == 1:
        sent = send(groups[0])
    else:  # one group at a time on the driver and in the tasks
        parts = []
        for group in groups:
            sent = send(group)
            found = now.select(names[text_at]).mapInArrow(textops.tidy(_flag(sent, shards, min_docs, min_chars)), "key binary, drop binary")
            parts.append(shared.put(found.groupBy("key").agg(F.max("drop").alias("drop")), "line-flags"))
            sent.destroy()
        flags = spark.read.schema("key binary, drop binary").parquet(*[p for _, p in parts])
        flags, _ = shared.put(flags.groupBy("key").agg(F.collect_list("drop").alias("drop")), "line-flags")
        shared.remove(spark, *[p for _, p in parts])
        text_key = F.unhex(F.md5(F.coalesce(names[text_at], F.lit(""))))
        now = now.withColumn("key", text_key).join(flags, "key", "left").select(*names, "drop")
        sent, drop_at = None, len(names)
    fields = [T.StructField(n, f.dataType, True) for n, f in zip(names, docs.schema.fields, strict=True)]
    fields += [T.StructField("kept", T.StringType()), T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType())]
    now = now.mapInArrow(textops.tidy(_cut(sent, shards, min_docs, min_chars, text_at, drop_at, names)), T.StructType(fields))
    shared.remove(spark, path, at)
    return now.toDF(*shared.beside(docs.columns, ["kept_text", "n_lines", "n_dropped"]))


def op7(spark, sf_dir: str) -> DataFrame:
    """The contract's digest of each document."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = drop_common_lines(docs, min_docs=10, min_chars=1)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("kept_text", F.lit("")), 256).alias("kept_sha256"))


SQL = """
WITH l AS (
  SELECT rowid_ AS r, doc_id, u.i AS i, u.line AS line,
         translate(trim(u.line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM (SELECT row_number() OVER () AS rowid_, doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents) d,
       LATERAL (SELECT unnest(ls) AS line, generate_subscripts(ls, 1) AS i) u
), c AS (
  SELECT k FROM l WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT r) >= 10
)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(c.k) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE c.k IS NULL), '')) AS kept_sha256
FROM l LEFT JOIN c ON l.k = c.k GROUP BY r, doc_id
"""
