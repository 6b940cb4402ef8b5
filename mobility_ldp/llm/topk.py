"""Exact top-k search by tiled matrix products.

Queries are taken in blocks of at most block_rows rows (by a hash of their id),
each sent to all executors as one matrix. A task runs through its shard of the
vectors in tiles: a matrix product, a partial selection of each query's best,
and a merge with the best so far. The lists of all tasks are then merged as a
tree: in groups of tasks first, then over the groups.

Scores are whole numbers and computed exactly: in 64-bit floats while no sum
can pass 2**53, else in Python's integers, held within 64 bits. Vectors that
are null, or hold a null or a number that is not finite, take no part, and
vectors of another length than the query's are no candidates for it. Rows of
the query's own id are not candidates either; repeated ids are candidates
each, and a repeated query id gets its list once for each distinct vector.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import shared

K, SCALE = 20, 64
BLOCK_ROWS, TILE_ROWS, QUERY_ROWS = 16_384, 2_048, 512
#: Tasks whose lists are merged together first.
FAN_IN = 64


def _valid(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    v = F.col(f"`{vec_col}`")
    ok = v.isNotNull() & F.col(f"`{id_col}`").isNotNull() & F.coalesce(F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))), F.lit(False))
    return df.where(ok).select(F.col(f"`{id_col}`").alias("vec_id"), v.cast("array<double>").alias("v"))


def quantise(flat: np.ndarray, scale: int) -> np.ndarray:
    return np.floor(flat * scale)


def scores(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of the rows of a and b (whole numbers), as 64-bit integers."""
    if a.shape[1] == 0:
        return np.zeros((len(a), len(b)), np.int64)
    top = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * a.shape[1]  # may be infinite
    if top < 2.0**53:
        return (a @ b.T).astype(np.int64)
    exact = np.array([[int(x) for x in r] for r in a], object) @ np.array([[int(x) for x in r] for r in b], object).T
    return np.clip(exact, -(2**63) + 2, 2**63 - 1).astype(np.int64)


def best(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Column places of each row's k best: highest score, ties to the smaller id. ids is a row, or as wide as score."""
    n = score.shape[1]
    wide = np.broadcast_to(ids, score.shape)
    if n <= 4 * k:
        return np.lexsort((wide, -score), axis=1)[:, :k]
    # candidates above the k-th score are in; those equal to it compete by id
    limit = -np.partition(-score, k - 1, axis=1)[:, k - 1]
    out = np.empty((len(score), k), np.int64)
    for r in range(len(score)):
        at = np.flatnonzero(score[r] >= limit[r])
        out[r] = at[np.lexsort((wide[r, at], -score[r, at]))[:k]]
    return out


def _search(sent, k, scale, tile_rows, query_rows):
    def run(batches):
        qid, qm, qno = sent.value  # ids, quantised matrices by length, places
        state = {d: [np.full((len(qid[d]), 0), 0, np.int64), np.full((len(qid[d]), 0), 0, np.int64)] for d in qid}
        lowest = np.iinfo(np.int64).min + 1

        def tile(ids, m):
            d = m.shape[1]
            if d not in qid:
                return
            order = np.argsort(ids, kind="stable")
            ids, m = ids[order], m[order]
            top_s, top_i = state[d]
            new_s, new_i = [], []
            for a in range(0, len(qid[d]), query_rows):
                s = scores(qm[d][a : a + query_rows], m)
                q = qid[d][a : a + query_rows]
                own = np.searchsorted(ids, q), np.searchsorted(ids, q, "right")
                gone = own[1] > own[0]
                i = np.broadcast_to(ids, s.shape)
                mark = np.zeros(s.shape, bool)
                for r in np.flatnonzero(gone):
                    mark[r, own[0][r] : own[1][r]] = True
                s = np.where(mark, lowest, s)
                at = best(s, ids, k)
                take = np.arange(len(s))[:, None]
                s, i, hidden = s[take, at], i[take, at], mark[take, at]
                s = np.concatenate([top_s[a : a + query_rows], s], 1)
                i = np.concatenate([top_i[a : a + query_rows], np.where(hidden, -1, i)], 1)
                at = best(s, i, k)
                new_s.append(s[take, at])
                new_i.append(i[take, at])
            state[d] = [np.concatenate(new_s), np.concatenate(new_i)]

        for batch in batches:
            ids, v = batch.column(0).to_numpy(), batch.column(1)
            size = np.diff(v.offsets.to_numpy())
            flat, at = v.values.to_numpy(), v.offsets.to_numpy()
            for d in np.unique(size):
                rows = np.flatnonzero(size == d)
                for a in range(0, len(rows), tile_rows):
                    own = rows[a : a + tile_rows]
                    m = flat[(at[own][:, None] + np.arange(d))] if d else np.zeros((len(own), 0))
                    tile(ids[own], quantise(m, scale))
        for d, (s, i) in state.items():
            if s.shape[1]:
                # hidden places (the query's own rows) have the lowest score and sort last
                r, c = np.nonzero((i >= 0) | (s > lowest))
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qno[d], s.shape[1]).reshape(s.shape)[r, c]), pa.array(qid[d][r]), pa.array(i[r, c]), pa.array(s[r, c])], ["query_no", "query_id", "vec_id", "score"])

    return run


def search(vectors: DataFrame, queries: DataFrame, k: int = K, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = SCALE, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best vectors."""
    spark = vectors.sparkSession
    base = _valid(vectors, id_col, vec_col)
    asked, path = shared.put(_valid(queries, id_col, vec_col).distinct(), "queries")
    n = asked.count()
    # hashed blocks of block_rows on average; a block more for every two, so that few are larger
    blocks = 1 if n <= block_rows else -(-3 * n // (2 * block_rows))
    order = [F.col("score").desc(), F.col("vec_id")]
    lists, sent = [], None
    for k_block in range(blocks):
        own = asked.where(F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks)) == k_block) if blocks > 1 else asked
        rows = own.toPandas()
        qid, qm, qno = {}, {}, {}
        size = rows["v"].map(len).to_numpy() if len(rows) else np.zeros(0, int)
        for d in np.unique(size):
            mine = np.flatnonzero(size == d)
            qid[int(d)] = rows["vec_id"].to_numpy()[mine].astype(np.int64)
            qm[int(d)] = quantise(np.array(rows["v"].iloc[mine].tolist(), float).reshape(len(mine), int(d)), scale)
            qno[int(d)] = mine.astype(np.int64)
        sent = spark.sparkContext.broadcast((qid, qm, qno))
        found = base.mapInArrow(_search(sent, k, scale, TILE_ROWS, QUERY_ROWS), "query_no long, query_id long, vec_id long, score long").withColumn("group", (F.spark_partition_id() / FAN_IN).cast("int"))
        first = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_no", "group").orderBy(*order))).where(F.col("rank") <= k)
        last = first.withColumn("rank", F.row_number().over(Window.partitionBy("query_no").orderBy(*order))).where(F.col("rank") <= k)
        lists.append(last.select("query_id", "rank", "vec_id", "score"))
        if blocks > 1:  # one block after the other: the driver and the executors hold the queries of one
            lists[-1], _ = shared.put(lists[-1], "top-lists")
            sent.destroy()
    shared.remove(spark, path)
    out = lists[0]
    for x in lists[1:]:
        out = out.unionByName(x)
    return out


def op6(spark, sf_dir: str) -> DataFrame:
    """The contract's top lists: queries are the rows whose vec_id is divisible by 20."""
    rows = shared.table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return search(rows, rows.where(F.col("vec_id") % 20 == 0))


SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS q
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT a.vec_id AS query_id, b.vec_id AS vec_id, CAST(list_dot_product(CAST(a.q AS DOUBLE[]), CAST(b.q AS DOUBLE[])) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 20
"""
