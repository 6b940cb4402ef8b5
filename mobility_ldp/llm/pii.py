"""Personal data by fixed patterns and a linear-chain conditional random field.

The base patterns are found first and stay. The field labels every token of
every text with one of the kinds or none. Tokens are runs of digits, runs of
letters (bytes beyond ASCII are letters), or single marks; their features are
word shapes: class, length, case, the mark itself, a few words, and the same of
their neighbours. It is fitted to the small table of pii_labels and decoded
by Viterbi over whole batches in numpy: all texts of a chunk are one chain
with resets, cut into equal pieces, whose best-score matrices are first
combined and then traced back, so texts of any length cost linear time.
The field alone decides what is added: of its spans only those go that touch a
base span, or whose number of digits or checksum is not that of their kind.

Null and empty texts have no spans. Repeated rows are looked at one by one.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import pii_labels, shared, textops

KINDS = pii_labels.KINDS
LABELS = ("none", *KINDS)
PIECE = 128

LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
#: A match starts at the first digit of a run, as no later digit does better.
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    """Leftmost, non-overlapping matches of each kind that pass its test."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    at, done = text.find("@"), 0
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL_CHARS:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            out["email"].append((start, m.end()))
            done = m.end()
        else:
            done = max(done, at + 1)
        at = text.find("@", at + 1)
    if DIGIT.search(text):
        out["ip"] = [m.span() for m in IP.finditer(text) if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split("."))]
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 16:
                d = m[0].replace(" ", "").replace("-", "")
                if 16 <= len(d) <= 19 and luhn(d):
                    out["card"].append(m.span())
        out["phone"] = [m.span() for m in PHONE.finditer(text) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]
    return out


DIGIT = re.compile(r"[0-9]")

# ---- tokens and features -------------------------------------------------

#: Byte classes: 0 blank, 1 digit, 2 letter, 3 mark.
CLASS = np.full(256, 3, np.uint8)
CLASS[[32, *range(9, 14)]] = 0
CLASS[48:58] = 1
CLASS[65:91] = CLASS[97:123] = CLASS[128:] = 2
MARKS = {c: k for k, c in enumerate("+-().@[]/:,%=#_\"'|*")}
WORDS = ("at", "dot", "com", "org", "net", "card", "call", "phone", "tel", "ip")
#: Shapes: 1..20 digits by length; letters by case and length; words of the list; marks.
DIGITS, LETTERS, WORD0, MARK0 = 0, 24, 40, 50
SHAPES = 72
#: Each token sees shapes at these distances, and whether a blank stands before it and after it.
REACH = (-3, -2, -1, 0, 1, 2, 3)
WIDTH = SHAPES * len(REACH) + 4 * SHAPES
MARK_SHAPE = np.full(256, MARK0 + 20, np.int64)
for _c, _k in MARKS.items():
    MARK_SHAPE[ord(_c)] = MARK0 + _k


def tokens(data: np.ndarray, offsets: np.ndarray):
    """Starts and ends (bytes) of the tokens, and the bounds by document."""
    kind = CLASS[data]
    new = np.ones(len(data), bool)
    new[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == 3)
    first = offsets[:-1][offsets[:-1] < len(data)]
    new[first] = True
    at = np.flatnonzero(new)
    end = np.append(at[1:], len(data))
    solid = kind[at] != 0
    at, end = at[solid], end[solid]
    return at, end, np.searchsorted(at, offsets)


def shapes(data: np.ndarray, at: np.ndarray, end: np.ndarray, ranges) -> np.ndarray:
    kind, size = CLASS[data[at]] if len(at) else np.zeros(0, np.uint8), end - at
    out = np.zeros(len(at), np.int64)
    d = kind == 1
    out[d] = DIGITS + np.minimum(size[d], 20)
    w = kind == 2
    if w.any():
        upper = (data >= 65) & (data < 91)
        n_upper = np.concatenate([[0], np.cumsum(upper)])
        ups = n_upper[end[w]] - n_upper[at[w]]
        case = np.where(ups == 0, 0, np.where(ups == size[w], 2, np.where((ups == 1) & upper[at[w]], 1, 3)))
        out[w] = LETTERS + 4 * case + np.minimum((size[w] + 1) // 3, 3)
        (h,) = ranges(textops.LOWER[data], at[w], end[w])
        for k, word in enumerate(WORDS):
            raw = np.frombuffer(word.encode(), np.uint8)
            (own,) = ranges(raw, np.array([0]), np.array([len(raw)]))
            out[np.flatnonzero(w)[h == own[0]]] = WORD0 + k
    m = kind == 3
    out[m] = MARK_SHAPE[data[at[m]]]
    return out


def emissions(shape: np.ndarray, at, end, bounds, weights: np.ndarray) -> np.ndarray:
    """Score of each label at each token: the sum of the weights of its features."""
    n = len(shape)
    out = np.zeros((n, len(LABELS)))
    if not n:
        return out
    doc = textops.owners(bounds)
    for k, r in enumerate(REACH):
        there = np.zeros(n, np.int64)  # shape 0: no token there
        if r < 0:
            there[-r:] = np.where(doc[-r:] == doc[:r], shape[:r], 0)
        elif r > 0:
            there[:-r] = np.where(doc[:-r] == doc[r:], shape[r:], 0) if r < n else there[:-r]
        else:
            there = shape
        out += weights[k * SHAPES + there]
    before, after = glued(at, end, doc)
    out += weights[len(REACH) * SHAPES + (before + 2 * after) * SHAPES + shape]
    return out


def glued(at, end, doc):
    """Whether each token touches the one before it, and the one after it."""
    n = len(at)
    before, after = np.zeros(n, np.int64), np.zeros(n, np.int64)
    if n > 1:
        touch = (end[:-1] == at[1:]) & (doc[:-1] == doc[1:])
        before[1:] = after[:-1] = touch
    return before, after


def feature_rows(shape, at, end, bounds):
    """For fitting: the places in the weights of each token's features."""
    n = len(shape)
    doc = textops.owners(bounds)
    cols = []
    for k, r in enumerate(REACH):
        there = np.zeros(n, np.int64)
        for i in range(n):
            if 0 <= i + r < n and doc[i] == doc[i + r]:
                there[i] = shape[i + r]
        cols.append(k * SHAPES + there)
    before, after = glued(at, end, doc)
    cols.append(len(REACH) * SHAPES + (before + 2 * after) * SHAPES + shape)
    return np.stack(cols, 1)


# ---- the field -------------------------------------------------------------


def fit(rounds: int = 120, penalty: float = 2e-3) -> dict[str, np.ndarray]:
    """Weights (features x labels), transitions and starts, by gradient steps on the likelihood of the labelled table."""
    ranges = textops.RangeHash(0x5851F42D4C957F2D)
    table = pii_labels.labelled()
    raw = [t.encode() for t, _ in table]
    data = np.frombuffer(b"".join(raw), np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])])
    at, end, bounds = tokens(data, offsets)
    x = feature_rows(shapes(data, at, end, ranges), at, end, bounds)
    y = np.zeros(len(at), np.int64)
    doc = textops.owners(bounds)
    for d, (text, spans) in enumerate(table):
        for a, b, kind in spans:
            lo, hi = offsets[d] + len(text[:a].encode()), offsets[d] + len(text[:b].encode())
            y[(doc == d) & (at >= lo) & (end <= hi)] = LABELS.index(kind)
    n, s = len(table), len(LABELS)
    length = np.diff(bounds)
    longest = int(length.max())
    place = np.full((n, longest), -1)
    for d in range(n):
        place[d, : length[d]] = np.arange(bounds[d], bounds[d + 1])
    there = place >= 0
    p = {"w": np.zeros((WIDTH, s)), "t": np.zeros((s, s)), "s": np.zeros(s)}
    m, v = {k: np.zeros_like(a) for k, a in p.items()}, {k: np.zeros_like(a) for k, a in p.items()}

    def total(z, axis):
        top = z.max(axis, keepdims=True)
        return (top + np.log(np.exp(z - top).sum(axis, keepdims=True))).squeeze(axis)

    for step in range(1, rounds + 1):
        e = np.zeros((n, longest, s))
        e[there] = p["w"][x].sum(1)[place[there]]
        alpha, beta = np.zeros((n, longest, s)), np.zeros((n, longest, s))
        alpha[:, 0] = p["s"] + e[:, 0]
        for k in range(1, longest):
            alpha[:, k] = np.where(there[:, k, None], total(alpha[:, k - 1, :, None] + p["t"], 1) + e[:, k], alpha[:, k - 1])
        for k in range(longest - 2, -1, -1):
            beta[:, k] = np.where(there[:, k + 1, None], total(p["t"] + (e[:, k + 1] + beta[:, k + 1])[:, None, :], 2), 0)
        z = total(alpha[:, -1], 1)
        node = np.exp(alpha + beta - z[:, None, None])
        g = {k: penalty * n * a for k, a in p.items()}
        diff = node[there]
        order = place[there]
        gap = np.zeros((len(y), s))
        gap[order] = diff
        gap[np.arange(len(y)), y] -= 1
        for c in range(x.shape[1]):
            np.add.at(g["w"], x[:, c], gap)
        for k in range(1, longest):
            on = there[:, k]
            pair = np.exp(alpha[on, k - 1, :, None] + p["t"] + (e[on, k] + beta[on, k])[:, None, :] - z[on, None, None])
            g["t"] += pair.sum(0)
            np.add.at(g["t"], (y[place[on, k - 1]], y[place[on, k]]), -1)
        g["s"] += node[:, 0].sum(0)
        np.add.at(g["s"], y[place[:, 0]], -1)
        for k in p:
            m[k] = 0.9 * m[k] + 0.1 * g[k]
            v[k] = 0.99 * v[k] + 0.01 * g[k] ** 2
            p[k] = p[k] - 0.15 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
    return p


def viterbi(e: np.ndarray, starts: np.ndarray, trans: np.ndarray, first: np.ndarray, piece: int = PIECE) -> np.ndarray:
    """Best labels of chains laid end to end; starts marks the first token of each chain."""
    n, s = e.shape
    if not n:
        return np.zeros(0, np.int64)
    n_pieces = -(-n // piece)
    pad = n_pieces * piece - n
    e = np.concatenate([e, np.zeros((pad, s))]).reshape(n_pieces, piece, s)
    fresh = np.concatenate([starts, np.ones(pad, bool)]).reshape(n_pieces, piece)

    def step(score, l):
        """score: pieces x ... x labels before; the best over them for each label after, and where it came from."""
        way = np.where(fresh[:, l, None, None], first[None, None, :], trans[None])
        if score.ndim == 3:
            way = way[:, None]
        z = score[..., :, None] + way
        came = z.argmax(-2)
        return np.take_along_axis(z, came[..., None, :], -2)[..., 0, :] + (e[:, l, None] if score.ndim == 3 else e[:, l]), came

    # scores of each piece from each label before it
    through = np.broadcast_to(np.where(np.eye(s, dtype=bool), 0.0, -np.inf), (n_pieces, s, s))
    for l in range(piece):
        through, _ = step(through, l)
    enter = np.zeros((n_pieces, s))
    now = np.zeros(s)
    for c in range(n_pieces):
        enter[c] = now
        now = (now[:, None] + through[c]).max(0)
        now = now - now.max()
    back = np.empty((piece, n_pieces, s), np.int8)
    score = enter
    for l in range(piece):
        score, back[l] = step(score, l)
    # for each label at a piece's end, the label before the piece
    origin = np.broadcast_to(np.arange(s), (n_pieces, s)).copy()
    for l in range(piece - 1, -1, -1):
        origin = np.take_along_axis(back[l].astype(np.int64), origin, 1)
    last = np.empty(n_pieces, np.int64)
    label = int(score[-1].argmax())
    for c in range(n_pieces - 1, -1, -1):
        last[c] = label
        label = int(origin[c, label])
    out = np.empty((n_pieces, piece), np.int64)
    label = last
    rows = np.arange(n_pieces)
    for l in range(piece - 1, -1, -1):
        out[:, l] = label
        label = back[l][rows, label].astype(np.int64)
    return out.reshape(-1)[:n]


def field_spans(data: np.ndarray, offsets: np.ndarray, model, ranges) -> list[tuple[int, int, int, str]]:
    """(document, start, end, kind) in bytes from the start of data."""
    at, end, bounds = tokens(data, offsets)
    if not len(at):
        return []
    shape = shapes(data, at, end, ranges)
    heads = np.zeros(len(at), bool)
    heads[bounds[:-1][np.diff(bounds) > 0]] = True
    label = viterbi(emissions(shape, at, end, bounds, model["w"]), heads, model["t"], model["s"])
    hit = np.flatnonzero(label)
    if not len(hit):
        return []
    doc = textops.owners(bounds)
    cut = np.ones(len(hit), bool)
    cut[1:] = (np.diff(hit) > 1) | (label[hit[1:]] != label[hit[:-1]]) | (doc[hit[1:]] != doc[hit[:-1]])
    first = np.flatnonzero(cut)
    stop = np.append(first[1:], len(hit)) - 1
    return [(int(doc[hit[a]]), int(at[hit[a]]), int(end[hit[b]]), LABELS[label[hit[a]]]) for a, b in zip(first, stop, strict=True)]


#: Digits that a span of the field must have, by kind, least and most.
DIGITS_OF = {"email": (0, 99), "ip": (4, 12), "card": (13, 19), "phone": (7, 15)}


def counted(text: str, kind: str) -> bool:
    """Whether a span of the field has as many digits as its kind, and passes the card's checksum. Nothing else is asked of it."""
    digits = "".join(c for c in text if "0" <= c <= "9")
    least, most = DIGITS_OF[kind]
    return least <= len(digits) <= most and (kind != "card" or luhn(digits))


def find(text_column: pa.Array, model, ranges):
    """Per text the base spans by kind, and all spans by kind (code points)."""
    data, offsets = textops.buffers(text_column)
    for i, j in textops.chunks(offsets):
        part, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        extra: dict[int, list] = {}
        for d, a, b, kind in field_spans(part, at, model, ranges):
            extra.setdefault(d, []).append((a, b, kind))
        for d in range(j - i):
            raw = part[at[d] : at[d + 1]].tobytes()
            text = raw.decode()
            base = base_spans(text) if b"@" in raw or DIGIT.search(text) else {k: [] for k in KINDS}
            every = {k: list(v) for k, v in base.items()}
            taken = [x for v in base.values() for x in v]
            for a, b, kind in extra.get(d, []):
                s = len(raw[: a - at[d]].decode())
                e = s + len(raw[a - at[d] : b - at[d]].decode())
                if counted(text[s:e], kind) and not any(s < y and x < e for x, y in taken):
                    every[kind].append((s, e))
            yield base, {k: sorted(v) for k, v in every.items()}


def written(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in spans[k])


def _scan(model, text_at, names):
    def run(batches):
        ranges = textops.RangeHash(0x5851F42D4C957F2D)
        for batch in batches:
            counts, base, spans = [[] for _ in KINDS], [], []
            for own, every in find(batch.column(text_at), model, ranges):
                for k, kind in enumerate(KINDS):
                    counts[k].append(len(own[kind]))
                base.append(written(own))
                spans.append(written(every))
            cols = [c for k, c in enumerate(batch.columns) if k != text_at]
            yield pa.RecordBatch.from_arrays([*cols, *(pa.array(c, pa.int64()) for c in counts), pa.array(base, pa.string()), pa.array(spans, pa.string())], names)

    return run


def scan(docs: DataFrame, text_col: str = "text", model=None) -> DataFrame:
    """docs without the text, with n_email, n_ip, n_card, n_phone (base), base_spans and spans (kind:start:end, comma-joined) more, suffixed by _ where docs has such a name."""
    new = [*(f"n_{k}" for k in KINDS), "base_spans", "spans"]
    keep = [c for c in docs.columns if c != text_col]
    now = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`"))
    names = [f"c{k}" for k in range(len(keep))] + new
    fields = [T.StructField(n, f.dataType) for n, f in zip(names, now.schema.fields[:-1], strict=False)]
    fields += [T.StructField(n, T.LongType()) for n in new[:4]] + [T.StructField(n, T.StringType()) for n in new[4:]]
    out = now.toDF(*names[: len(keep)], "text__").mapInArrow(textops.tidy(_scan(model or fit(), len(keep), names)), T.StructType(fields))
    return out.toDF(*shared.beside(keep, new))


def op9(spark, sf_dir: str) -> DataFrame:
    """The contract's digest of each document."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text")
    out = scan(docs)
    return out.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", F.sha2("base_spans", 256).alias("base_sha256"), "spans")
