"""Each stage of the pipeline against a plain version of it, and the queries against their SQL."""

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import DOCS, brute_classes, brute_hits, brute_lines, odd_texts

import corpus_pipeline as cp
from mobility_ldp.llm import entries, packing, shared

SF = "/root/testdata/sf0.01"


def norm(v):
    return "null" if v is None else str(int(v) if isinstance(v, bool) else v)


@pytest.mark.parametrize("name", list(entries.oracle_sql()))
def test_against_sql(spark, duck, name):
    df = entries.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(norm(r[c]) for c in cols) for r in df.collect())
    names, rows = duck(entries.oracle_sql()[name])
    at = [names.index(c) for c in cols]
    assert got == sorted(tuple(norm(r[i]) for i in at) for r in rows)


def rows_of(df):
    return {r["doc_id"]: r.asDict() for r in df.collect()}


def test_stages(spark, tmp_path):
    docs = shared.table(spark, SF, "documents").where("doc_id < 400").select(*cp.COLUMNS)
    bench = [(r["item_id"], r["text"]) for r in shared.table(spark, SF, "benchmark").collect()]
    before = rows_of(docs)
    for name, stage in cp.STAGES[:-1]:
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        after = rows_of(docs)
        assert docs.columns == list(cp.COLUMNS)
        ids = sorted(before)
        texts = [before[k]["text"] for k in ids]
        if name == "language_id":
            assert set(before) - set(after) == {k for k, t in zip(ids, texts) if not any(c.isalpha() for c in t or "")}
        elif name == "line_dedup":
            want = brute_lines(texts, 10)
            assert {k: v["text"] for k, v in after.items()} == {k: w[2] for k, w in zip(ids, want)}
            assert all(v["n_chars"] == len(v["text"]) for v in after.values())
        elif name == "near_dedup":
            classes = brute_classes(texts)
            assert sorted(after) == sorted({ids[c] for c in classes})
        else:
            hits = [brute_hits(t, bench) for t in texts]
            assert sorted(after) == [k for k, (n, h, _) in zip(ids, hits) if not (h and 20 * h >= n)]
        before = after
    pieces = cp.STAGES[-1][1](spark, docs, SF).collect()
    encode = packing.encoder("byte_bpe_50k.json")
    by = collections.defaultdict(list)
    for p in pieces:
        by[p["doc_id"]].append(p)
    assert set(by) == set(before)
    for k, v in before.items():
        ids = np.concatenate([np.frombuffer(p["ids"], "<u4") for p in sorted(by[k], key=lambda p: p["start"])])
        assert ids.tolist() == [*encode(v["text"] or "").tolist(), 0]


def test_odd_rows(spark):
    texts = odd_texts()
    docs = spark.createDataFrame([(None if k == 9 else k, t, None, None, None) for k, t in enumerate(texts)], DOCS)
    for _, stage in cp.STAGES:
        empty = stage(spark, docs.limit(0), SF)
        assert empty.count() == 0
        docs2 = stage(spark, docs, SF)
        assert docs2.count() > 0
        if docs2.columns == list(cp.COLUMNS):
            path = f"{shared.shared_dir(spark)}/odd-{id(docs2)}"
            docs2.write.mode("overwrite").parquet(path)
            docs = spark.read.parquet(path)


def test_run(spark, sf):
    out = cp.run(spark, sf)
    assert out.where(F.col("length") > 0).count() == out.count() > 0
