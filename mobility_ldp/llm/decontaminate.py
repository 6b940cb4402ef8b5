"""Benchmark decontamination by winnowing, in DataFrame functions alone.

Both sides keep the least k-gram hash of each run of w hashes, with
k + w - 1 = window, so every shared span of window words shares a fingerprint.
Fingerprints are joined and each hit is extended word by word, so hashes only
propose and words decide. An extension reaches at most window - k words to
either side: all windows that hold the fingerprint lie in that reach.
A benchmark item shorter than a window is anchored at its longest word.

Null and empty texts have no words and no hits. Repeated rows are judged one
by one. Benchmark rows with a null id mark words, but count as no item.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shared

WINDOW = 13
#: Low bits of a packed fingerprint that hold its position.
PLACE = 30
#: Bytes of benchmark fingerprints, with their contexts, up to which they are broadcast.
BROADCAST_BYTES = 64 << 20
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    """Lower-cased words (A-Z only) of a text; none for null."""
    return F.array_remove(F.split(shared.ascii_lower(F.coalesce(text, F.lit(""))), SEPARATORS), "")


def gram_length(window: int) -> int:
    return max(1, (2 * window) // 3)


def _packed(ws: Column, i: Column, k: int) -> Column:
    return F.xxhash64(F.slice(ws, i + 1, k)).bitwiseAND(F.lit(-(1 << PLACE))).bitwiseOR(i.cast("long"))


def hashes(ws: Column, window: int) -> Column:
    """Packed k-gram hashes at all places of a text that has a whole window."""
    k = gram_length(window)
    return F.when(F.size(ws) >= window, F.transform(F.sequence(F.lit(0), F.size(ws) - k), lambda i: _packed(ws, i, k)))


def winnowed(hs: Column, window: int) -> Column:
    """The distinct least hashes (leftmost of equals) of all runs."""
    w = window - gram_length(window) + 1
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.size(hs) - (w - 1)), lambda j: F.array_min(F.slice(hs, j, w))))


def benchmark_prints(bench: DataFrame, text_col: str, id_col: str, window: int) -> DataFrame:
    """Rows (fp, before, after, need, items): before is read leftwards from the fingerprint."""
    k, reach = gram_length(window), window - gram_length(window)
    items = bench.select(F.col(id_col).cast("string").alias("item"), words(F.col(text_col)).alias("ws")).where(F.size("ws") > 0)
    items = items.withColumn("hs", hashes(F.col("ws"), window))
    longest = F.array_position(F.transform("ws", lambda x: F.char_length(x)), F.array_max(F.transform("ws", lambda x: F.char_length(x)))).cast("int") - 1
    prints = F.when(F.size("ws") >= window, winnowed(F.col("hs"), window)).otherwise(F.array(_packed(F.col("ws"), longest, 1)))
    rows = items.select("item", "ws", F.explode(prints).alias("x")).withColumn("q", F.col("x").bitwiseAND(F.lit((1 << PLACE) - 1)).cast("int"))
    whole = F.size("ws") < window
    back = F.when(whole, F.col("q")).otherwise(F.least(F.col("q"), F.lit(reach)))
    ahead = F.when(whole, F.size("ws")).otherwise(F.lit(k + reach))
    rows = rows.select(
        F.shiftright("x", PLACE).alias("fp"),
        F.reverse(F.slice("ws", F.col("q") - back + 1, back)).alias("before"),
        F.slice("ws", F.col("q") + 1, ahead).alias("after"),
        F.least(F.size("ws"), F.lit(window)).alias("need"),
        "item",
    )
    return rows.groupBy("fp", "before", "after", "need").agg(F.array_sort(F.collect_set("item")).alias("items"))


def _run(a: Column, b: Column) -> Column:
    """How many leading elements of two arrays agree."""
    same = F.zip_with(a, b, lambda x, y: F.coalesce(x == y, F.lit(False)))
    miss = F.array_position(same, False).cast("int")
    return F.when(miss == 0, F.size(same)).otherwise(miss - 1)


def _marks(ws: Column, hs: Column, window: int, short: bool) -> Column:
    """Packed fingerprints of a text: its winnowed ones and, where the benchmark has items under a window, each single word."""
    nothing = F.array().cast("array<bigint>")
    marks = F.when(F.size(ws) >= window, F.coalesce(winnowed(hs, window), nothing)).otherwise(nothing)
    return F.concat(marks, F.transform(ws, lambda x, i: _packed(ws, i, 1))) if short else marks


def _place(x: Column) -> Column:
    return x.bitwiseAND(F.lit((1 << PLACE) - 1)).cast("int")


def _extended() -> tuple[Column, Column]:
    """Start and end, in words, of the agreement around a fingerprint at place p of ws."""
    left = F.slice("ws", F.greatest(F.col("p") - F.size("before"), F.lit(0)) + 1, F.least(F.col("p"), F.size("before")))
    return F.col("p") - _run(F.reverse(left), F.col("before")), F.col("p") + _run(F.slice("ws", F.col("p") + 1, F.size("after")), F.col("after"))


def _gathered(ok: Column) -> list[Column]:
    """Aggregates spans and items of the hits (s, e, need, items) that are ok."""
    return [
        F.array_sort(F.collect_set(F.when(ok, F.struct("s", "e")))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set(F.when(ok, F.col("items")))))).alias("items"),
    ]


def _beside_sent(docs: DataFrame, prints: DataFrame, text: Column, own: Column, window: int, short: bool) -> DataFrame:
    """(own__, n_words, spans, items) per row of docs; the fingerprints are sent to all tasks and the words never leave theirs."""
    ws = docs.select(F.monotonically_increasing_id().alias("row__"), own, words(text).alias("ws"))
    ws = ws.withColumn("hs", hashes(F.col("ws"), window))
    ws = ws.select("row__", "own__", "ws", F.concat(F.array(F.lit(None).cast("long")), _marks(F.col("ws"), F.col("hs"), window, short)).alias("marks"))
    # outer, though no list is empty: else the optimiser tests each list's size by computing it once more
    rows = ws.select("row__", "own__", "ws", F.explode_outer("marks").alias("x"))
    rows = rows.select("row__", "own__", "ws", _place(F.col("x")).alias("p"), F.shiftright("x", PLACE).alias("fp"))
    base = F.col("p").isNull()
    hit = rows.join(F.broadcast(prints), "fp", "left").where(base | F.col("need").isNotNull())
    start, end = _extended()
    found = hit.select(
        "row__",
        F.when(base, F.col("own__")).alias("own__"),
        F.when(base, F.size("ws")).alias("n"),
        F.when(~base, start).alias("s"),
        F.when(~base, end).alias("e"),
        "need",
        "items",
    )
    # no filter on ok: it would run outside generated code, and each fingerprint would copy the words
    ok = F.col("e") - F.col("s") >= F.col("need")
    return found.groupBy("row__").agg(F.max("own__").alias("own__"), F.coalesce(F.max("n"), F.lit(0)).cast("long").alias("n_words"), *_gathered(ok)).drop("row__")


def _beside_shuffled(docs: DataFrame, prints: DataFrame, text: Column, own: Column, window: int, short: bool) -> DataFrame:
    """The same where the fingerprints are too many to send.

    Only (text key, place, fingerprint) is shuffled by fingerprint. The words come in afterwards, once for each
    distinct text that shares a fingerprint with the benchmark, and the verdict goes back to the rows by the text's key.
    """
    keyed = docs.select(own, F.coalesce(text, F.lit("")).alias("t")).withColumn("key", F.md5("t"))
    ws = keyed.select("key", words(F.col("t")).alias("ws")).withColumn("hs", hashes(F.col("ws"), window))
    rows = ws.select("key", F.explode_outer(_marks(F.col("ws"), F.col("hs"), window, short)).alias("x"))
    rows = rows.select("key", _place(F.col("x")).alias("p"), F.shiftright("x", PLACE).alias("fp"))
    met, _ = shared.put(rows.join(prints.select("fp").distinct(), "fp", "left_semi").distinct(), "met")
    texts = keyed.join(met.select("key").distinct(), "key", "left_semi").groupBy("key").agg(F.first("t").alias("t")).select("key", words(F.col("t")).alias("ws"))
    start, end = _extended()
    found = met.join(prints, "fp").join(texts, "key").select("key", start.alias("s"), end.alias("e"), "need", "items")
    out = found.groupBy("key").agg(*_gathered(F.col("e") - F.col("s") >= F.col("need")))
    rows = keyed.select("own__", "key", F.size(words(F.col("t"))).cast("long").alias("n_words")).join(out, "key", "left")
    return rows.select("own__", "n_words", *[F.coalesce(c, F.array().cast(out.schema[c].dataType)).alias(c) for c in ("spans", "items")])


def contamination(docs: DataFrame, bench: DataFrame, text_col: str = "text", bench_text: str = "text", bench_id: str = "item_id", window: int = WINDOW, keep: list[str] | None = None) -> DataFrame:
    """Per row of docs: the columns in keep, then n_words, n_hit, spans (start, end in words) and items."""
    keep = keep or []
    prints, _ = shared.put(benchmark_prints(bench, bench_text, bench_id, window), "prints")
    size = prints.agg(F.sum(F.octet_length(F.concat_ws(" ", "before", "after", "items")) + 64).alias("b"), F.max((F.col("need") < window).cast("int")).alias("short")).first()
    own = F.struct(F.lit(1).alias("one__"), *[F.col(f"`{c}`") for c in keep]).alias("own__")
    way = _beside_sent if (size["b"] or 0) <= BROADCAST_BYTES else _beside_shuffled
    out = way(docs, prints, F.col(f"`{text_col}`"), own, window, bool(size["short"]))
    start = F.struct(F.lit(0).alias("upto"), F.lit(0).cast("long").alias("n"))
    covered = F.aggregate("spans", start, lambda a, x: F.struct(F.greatest(a["upto"], x["e"]).alias("upto"), (a["n"] + F.greatest(F.lit(0), x["e"] - F.greatest(a["upto"], x["s"]))).alias("n")))
    return out.select(*[F.col("own__")[c].alias(c) for c in keep], "n_words", covered["n"].alias("n_hit"), "spans", "items")


def judged(out: DataFrame) -> Column:
    """A twentieth of the words or more is hit."""
    return (out["n_hit"] > 0) & (20 * out["n_hit"] >= out["n_words"])


def decontaminate(docs: DataFrame, bench: DataFrame, text_col: str = "text", bench_text: str = "text", bench_id: str = "item_id", window: int = WINDOW) -> DataFrame:
    """The rows of docs that are not contaminated. The verdict depends on the text alone, so it is carried by a digest of it."""
    key = shared.spare(docs, "text_key")
    keyed = docs.withColumn(key, F.md5(F.col(f"`{text_col}`")))
    out = contamination(keyed.select(key, F.col(f"`{text_col}`").alias("t")), bench, "t", bench_text, bench_id, window, keep=[key])
    bad, _ = shared.put(out.where(judged(out)).select(key).distinct(), "contaminated")
    return keyed.join(bad, key, "left_anti").drop(key).select(*[F.col(f"`{c}`") for c in docs.columns])


def op1(spark, sf_dir: str) -> DataFrame:
    """The contract's digest of each document."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = contamination(docs, shared.table(spark, sf_dir, "benchmark").select("item_id", "text"), keep=["doc_id"])
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), judged(out).alias("contaminated"))


_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
SQL = rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS ws FROM documents),
i AS (SELECT item_id, {_WORDS} AS ws FROM benchmark),
iw AS (SELECT DISTINCT item_id, n, array_to_string(ws[p:p + n - 1], ' ') AS g
       FROM (SELECT item_id, ws, least(len(ws), 13) AS n, unnest(generate_series(1, len(ws) - least(len(ws), 13) + 1)) AS p FROM i WHERE len(ws) > 0)),
ns AS (SELECT DISTINCT n FROM iw),
dw AS (SELECT r, n, p, array_to_string(ws[p:p + n - 1], ' ') AS g
       FROM (SELECT r, ws, n, unnest(generate_series(1, len(ws) - n + 1)) AS p FROM d, ns WHERE len(ws) >= n)),
h AS (SELECT r, p, dw.n AS n, item_id FROM dw JOIN iw ON dw.n = iw.n AND dw.g = iw.g),
hit AS (SELECT r, count(DISTINCT x) AS n_hit FROM (SELECT r, unnest(generate_series(p, p + n - 1)) AS x FROM (SELECT DISTINCT r, p, n FROM h)) GROUP BY r),
its AS (SELECT r, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS s FROM (SELECT DISTINCT r, CAST(item_id AS VARCHAR) AS s FROM h) GROUP BY r)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN hit USING (r) LEFT JOIN its USING (r)
"""
