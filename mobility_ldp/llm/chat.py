"""Chat formatting with offset-aligned loss masks.

A conversation is rendered whole: each turn is <|role|>, its role, <|text|>,
its text, <|end|>. In roles and texts a backslash is put behind the first
character of every control string (those three, and the usual ones of other
templates), or one more where backslashes stand there; taking one away again
gives the text back. The rendered conversation is encoded once with offsets;
the markers are tokens of their own, so no token crosses a turn's border. The
sorted spans of the turns to learn from are intersected with the sorted token
spans by binary search.

Rows of a conversation are ordered by turn, then role, then text (nulls
first). Null roles and texts are empty. Rows with a null id are one
conversation. Conversations are streamed out of a sort, and one of more than
max_chars characters comes out in segments of whole turns: encoding turns
apart gives the same tokens, since markers split the text.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import shared

#: The template's markers.
ROLE, TEXT, END = "<|role|>", "<|text|>", "<|end|>"
#: Control strings start with < or [ and go on like this.
CONTROL = r"(?=\||/?s>|/?INST\]|</?SYS>>)"
LEARN = ("assistant",)
MAX_CHARS = 16_000_000
OUT = "conv_id {id}, segment long, formatted string, tokens array<int>, starts array<int>, ends array<int>, mask array<boolean>, n_turns long, last boolean"


def escape(text: str) -> str:
    return re.sub(rf"([<\[])(\\*){CONTROL}", r"\1\\\2", text)


def unescape(text: str) -> str:
    return re.sub(rf"([<\[])\\(\\*){CONTROL}", r"\1\2", text)


def render(turns: list[tuple[str, str]], learn=LEARN) -> tuple[str, list[tuple[int, int]]]:
    """The formatted text, and the spans in it of the texts to learn from."""
    parts, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{ROLE}{escape(role)}{TEXT}", escape(text)
        if role in learn:
            spans.append((at + len(head), at + len(head) + len(body)))
        parts += [head, body, END]
        at += len(head) + len(body) + len(END)
    return "".join(parts), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted text."""
    out = []
    for turn in formatted.split(END)[:-1]:
        head, _, body = turn.partition(TEXT)
        out.append((unescape(head[len(ROLE) :]), unescape(body)))
    return out


def mask(starts: np.ndarray, ends: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """Which tokens lie in the spans; tokens and spans are sorted."""
    out = np.zeros(len(starts), bool)
    if not spans or not len(starts):
        return out
    s = np.array(spans)
    k = np.searchsorted(s[:, 1], starts, "right")  # the first span that ends after the token's start
    ok = k < len(s)
    out[ok] = (ends[ok] > s[k[ok], 0]) & (ends[ok] > starts[ok])
    return out


def masked_runs(starts, ends, on) -> list[tuple[int, int]]:
    """Character runs under a mask; tokens that share a character (parts of its bytes) cover it once."""
    a, b = np.asarray(starts)[on], np.asarray(ends)[on]
    if not len(a):
        return []
    first = np.ones(len(a), bool)
    first[1:] = a[1:] > np.maximum.accumulate(b)[:-1]
    at = np.flatnonzero(first)
    return list(zip(a[at].tolist(), np.maximum.reduceat(b, at).tolist(), strict=True))


def loss_texts(formatted: str, starts, ends, on) -> list[str]:
    """The texts under the mask, unescaped."""
    return [unescape(formatted[a:b]) for a, b in masked_runs(starts, ends, np.asarray(on, bool))]


def tokenizer(name: str):
    """The file's tokenizer with the markers added as tokens; offsets keep blanks."""
    import os

    import public_tokenizers
    from tokenizers import AddedToken, Tokenizer, processors

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    tok = Tokenizer.from_file(public_tokenizers.path(name))
    tok.post_processor = processors.ByteLevel(trim_offsets=False)
    old = [t.content for t in tok.get_added_tokens_decoder().values()]
    tok.add_tokens([AddedToken(x, normalized=False, special=False) for x in (ROLE, TEXT, END)])
    # special strings of the file's own in a text are ordinary text
    tok.encode_special_tokens = bool(old)
    return tok


def _format(name, learn, max_chars, id_type):
    def run(batches):
        tok = tokenizer(name)
        now, turns, size, segment, rows, waiting = None, [], 0, 0, [], 0

        def close(last):
            formatted, spans = render(turns, learn)
            enc = tok.encode(formatted, add_special_tokens=False)
            offsets = np.array(enc.offsets, np.int64).reshape(-1, 2)
            on = mask(offsets[:, 0], offsets[:, 1], spans)
            return (now[0], segment, formatted, np.array(enc.ids, np.int32), offsets[:, 0].astype(np.int32), offsets[:, 1].astype(np.int32), on, len(turns), last)

        def lists(k, kind):
            size = np.cumsum([0, *(len(r[k]) for r in rows)])
            return pa.ListArray.from_arrays(pa.array(size, pa.int32()), pa.array(np.concatenate([np.zeros(0, kind), *(r[k] for r in rows)]).astype(kind)))

        def out():
            plain = [pa.array([r[k] for r in rows], kind) for k, kind in ((0, id_type), (1, pa.int64()), (2, pa.string()), (7, pa.int64()), (8, pa.bool_()))]
            arrays = [*plain[:3], lists(3, np.int32), lists(4, np.int32), lists(5, np.int32), lists(6, bool), *plain[3:]]
            return pa.RecordBatch.from_arrays(arrays, ["conv_id", "segment", "formatted", "tokens", "starts", "ends", "mask", "n_turns", "last"])

        for batch in batches:
            for conv, role, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if now is not None and now[0] != conv:
                    rows.append(close(True))
                    turns, size, segment, now = [], 0, 0, None
                elif size > max_chars:
                    rows.append(close(False))
                    turns, size, segment = [], 0, segment + 1
                now = (conv,)
                turns.append((role or "", text or ""))
                size += len(role or "") + len(text or "")
                waiting += len(text or "")
                if waiting > 1 << 20:
                    yield out()
                    rows.clear()
                    waiting = 0
        if now is not None:
            rows.append(close(True))
        yield out()

    return run


def format_chats(rows: DataFrame, tokenizer_name: str = "byte_bpe_50k.json", learn=LEARN, max_chars: int = MAX_CHARS) -> DataFrame:
    """One row per conversation (or segment of a huge one) of rows (conv_id, turn, role, text)."""
    kind = rows.schema["conv_id"].dataType.simpleString()
    from pyspark.sql.pandas.types import to_arrow_type

    dealt = rows.select("conv_id", "turn", "role", "text").repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")
    return dealt.mapInArrow(_format(tokenizer_name, tuple(learn), max_chars, to_arrow_type(rows.schema["conv_id"].dataType)), OUT.format(id=kind))


def _digest(batches):
    """What can be read back from formatted conversations."""
    turns, loss, n, chars, length = hashlib.sha256(), hashlib.sha256(), 0, 0, 0
    for batch in batches:
        out = []
        bounds = batch.column(2).offsets.to_numpy()
        starts, ends, on = (batch.column(k).values.to_numpy(zero_copy_only=False) for k in (2, 3, 4))
        for k, (conv, formatted, last) in enumerate(zip(*(batch.column(c).to_pylist() for c in (0, 1, 5)), strict=True)):
            own = slice(bounds[k], bounds[k + 1])
            for role, text in parse(formatted):
                turns.update(f"{role}\n{text}\n".encode())
                n += 1
            for text in loss_texts(formatted, starts[own], ends[own], on[own]):
                loss.update(text.encode())
                chars += len(text)
            length += len(formatted)
            if last:
                out.append((conv, n, turns.hexdigest(), chars, loss.hexdigest(), length))
                turns, loss, n, chars, length = hashlib.sha256(), hashlib.sha256(), 0, 0, 0
        cols = list(zip(*out, strict=True)) or [[]] * 6
        kinds = [batch.schema.field(0).type, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])


def digests(formatted: DataFrame) -> DataFrame:
    """Counts and digests per conversation, read back from the output of format_chats (whose segments stand in order)."""
    kind = formatted.schema["conv_id"].dataType.simpleString()
    return formatted.select("conv_id", "formatted", "starts", "ends", "mask", "last").mapInArrow(_digest, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op3(spark, sf_dir: str) -> DataFrame:
    """The contract's digest of each conversation, and of conversation -1, whose texts hold control strings."""
    rows = shared.table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    schema = T.StructType([T.StructField("conv_id", T.LongType()), T.StructField("turn", T.LongType()), T.StructField("role", T.StringType()), T.StructField("text", T.StringType())])
    own = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], schema)
    return digests(format_chats(rows.unionByName(own)))


SQL_TURNS = """
SELECT conv_id, CAST(count(*) AS BIGINT) AS n_turns,
       sha256(string_agg(coalesce(role, '') || chr(10) || coalesce(text, '') || chr(10), '' ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST)) AS turns_sha256,
       CAST(coalesce(sum(length(coalesce(text, ''))) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(coalesce(text, ''), '' ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(length(ESC(coalesce(role, ''))) + length(ESC(coalesce(text, ''))) + 23) AS BIGINT) AS formatted_chars
FROM (SELECT conv_id, turn, role, text FROM conversations
      UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
      UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]')
GROUP BY conv_id
"""
#: RE2 has no look-ahead; what follows is put back instead.
SQL = re.sub(r"ESC\((coalesce\(\w+, ''\))\)", r"regexp_replace(\1, '([<\\[])(\\\\*)(\\||/?s>|/?INST\\]|</?SYS>>)', '\\1\\\\\\2\\3', 'g')", SQL_TURNS)
