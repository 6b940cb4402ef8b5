"""Packing by power-of-two decomposition.

A document's token ids (with the closing id) are cut into pieces of max_len
and, for the rest, of falling powers of two. Each piece is a sequence of its
own; sequences of one length form a bucket, so a batch is a rectangle without
padding and no sequence crosses documents. Nothing is shuffled.

Null and empty texts are the closing id alone. Repeated rows are packed again.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import shared, textops

#: Longest run without white space, and of white space, that goes to the quick encoder.
RUN = 1000


def encoder(name: str):
    """text -> ids (numpy uint32) as the file's own library gives them.

    For the byte-level BPE with ranks beside it, ordinary texts go to the
    quicker of two libraries that hold the same vocabulary; texts with a
    special token's string or very long runs go to the other.
    """
    import base64
    import os
    import re

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    whole = Tokenizer.from_file(public_tokenizers.path(name))
    ranks_file = public_tokenizers.path(name.replace(".json", ".tiktoken"))

    def slow(text):
        return np.array(whole.encode(text, add_special_tokens=False).ids, np.uint32)

    if not os.path.exists(ranks_file):
        return slow
    with open(ranks_file, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f)}
    quick = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    special = [t.content for t in whole.get_added_tokens_decoder().values()]
    blank = re.compile(r"\s{%d}" % RUN)

    def encode(text):
        if any(x in text for x in special) or max(map(len, text.split()), default=0) > RUN or blank.search(text):
            return slow(text)
        return np.array(quick.encode_ordinary(text), np.uint32)

    return encode


def pieces(n: int, max_len: int) -> list[int]:
    """Lengths of the pieces of n ids."""
    rest = n % max_len
    return [max_len] * (n // max_len) + [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]


#: Ids after which a batch of pieces is handed on.
FLUSH = 1 << 20


def _pack(text_at, tokenizer, end_id, max_len, names):
    def run(batches):
        encode = encoder(tokenizer)
        for batch in batches:
            cols = [c for k, c in enumerate(batch.columns) if k != text_at]
            rows, start, length, total, raw, size = [], [], [], [], [], 0

            def out():
                take = pa.array(rows, pa.int64())
                arrays = [pc.take(c, take) for c in cols] + [pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(total, pa.int64()), pa.array(raw, pa.binary())]
                return pa.RecordBatch.from_arrays(arrays, names)

            for row, text in enumerate(batch.column(text_at)):
                ids = np.append(encode(text.as_py() or ""), np.uint32(end_id)).astype("<u4")
                at = 0
                for k in pieces(len(ids), max_len):
                    rows.append(row)
                    start.append(at)
                    length.append(k)
                    total.append(len(ids))
                    raw.append(ids[at : at + k].tobytes())
                    at += k
                size += len(ids)
                if size >= FLUSH:
                    yield out()
                    rows, start, length, total, raw, size = [], [], [], [], [], 0
            yield out()

    return run


def pack(docs: DataFrame, text_col: str = "text", tokenizer: str = "byte_bpe_50k.json", end_id: int = 0, max_len: int = 1024) -> DataFrame:
    """One row per piece: docs' columns but the text, then start, length, doc_tokens, ids (little-endian
    unsigned 32-bit), sequence_id, offset and bucket (log2 of the length).

    max_len is a power of two. New names that docs has too are suffixed by _.
    """
    if max_len < 1 or max_len & (max_len - 1):
        raise ValueError("max_len must be a power of two")
    new = ["start", "length", "doc_tokens", "ids", "sequence_id", "offset", "bucket"]
    keep = [c for c in docs.columns if c != text_col]
    now = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`")).toDF(*[f"c{k}" for k in range(len(keep))], "text__")
    names = [f"c{k}" for k in range(len(keep))] + new[:4]
    fields = [T.StructField(n, f.dataType) for n, f in zip(names, now.schema.fields[:-1], strict=False)]
    fields += [T.StructField(n, T.LongType()) for n in new[:3]] + [T.StructField("ids", T.BinaryType())]
    out = now.mapInArrow(textops.tidy(_pack(len(keep), tokenizer, end_id, max_len, names)), T.StructType(fields))
    return out.withColumns({"sequence_id": F.monotonically_increasing_id(), "offset": F.lit(0).cast("long"), "bucket": F.log2(F.col("length")).cast("int")}).toDF(*shared.beside(keep, new))


def write_buckets(packed: DataFrame, path: str) -> None:
    """One folder per length, so that a reader makes batches without padding."""
    packed.write.partitionBy("bucket").parquet(path)


def padding(packed: DataFrame) -> DataFrame:
    """Per bucket: sequences, ids, and padded places (none, as each sequence is as long as its bucket)."""
    return packed.groupBy("bucket").agg(F.count("*").alias("sequences"), F.sum("length").alias("ids"), F.sum(F.pow(F.lit(2.0), F.col("bucket")).cast("long") - F.col("length")).alias("padded"))


def op8(spark, sf_dir: str) -> DataFrame:
    """The contract's digest of each piece."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = pack(docs)
    return out.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
