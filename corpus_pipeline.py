"""Five stages from raw documents to packed sequences.

Each stage reads what its predecessor kept, written as Parquet. All but the
last return the columns of documents: rows go, or their texts lose lines.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mobility_ldp.llm import decontaminate, langid, line_dedup, near_dedup, packing, shared

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Documents whose language is less sure than this go, as do those without letters.
MIN_SCORE = 0.25


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents go that have no letters, or no language with a score of MIN_SCORE; the others stay as they are."""
    model = langid.fit_contract(docs)
    out = langid.identify(docs, model)
    pred, score = out.columns[len(docs.columns) :]
    # without any labelled row there is nothing to judge by
    sure = (F.col(pred) != langid.UNKNOWN) & (F.col(score) >= MIN_SCORE) if model.langs else F.col("text").rlike(r"\p{L}")
    return out.where(sure).select(*docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten documents or more go; n_chars follows the text."""
    out = line_dedup.drop_common_lines(docs)
    kept, _, dropped = out.columns[len(docs.columns) :]
    return out.select(*[F.col(kept).alias("text") if c == "text" else F.when(F.col(dropped) > 0, F.length(kept)).otherwise(F.col("n_chars")).cast("long").alias("n_chars") if c == "n_chars" else F.col(c) for c in docs.columns])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates stays, the one of the least id."""
    return near_dedup.keep_first(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents go of whose words a twentieth or more lies in windows of the benchmark."""
    return decontaminate.decontaminate(docs, shared.table(spark, sf_dir, "benchmark").select("item_id", "text"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents, each a sequence of a power of two of ids."""
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", drop_lines),
    ("near_dedup", drop_near_copies),
    ("decontaminate", drop_contaminated),
    ("packing", pack_sequences),
]
#: Language identification, signatures and token ids are not expressible in SQL; tests hold each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on the documents of sf_dir; each but the last is written to the shared folder and read again."""
    docs = shared.table(spark, sf_dir, "documents").select(*COLUMNS)
    base = f"{shared.shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{name}")
        docs = spark.read.parquet(f"{base}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
