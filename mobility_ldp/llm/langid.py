"""Language identification in two steps.

Texts become averages of hashed features: byte n-grams of the lower-cased text
and whole words. A linear support vector machine of one-versus-rest kind picks
the language family, then one-versus-one machines vote among the languages of
that family. As features are averaged, the score of a text is the mean of the
weights of its features, so a text of any length needs one pass and no vector.

Fitting takes at most sample_rows labelled rows, chosen by a hash of id and
spread over the languages; features of whole texts are made on the executors.
Prediction covers every row. Null texts and texts without letters are "und"
with score 0; without any labelled row, every text is "und".
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import shared, textops

#: The family of common languages; any other language is a family of its own.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af lb fy yi",
    "romance": "fr es it pt ro ca gl oc la",
    "slavic": "ru uk pl cs sk sl hr sr bs bg mk be",
    "baltic": "lt lv",
    "uralic": "fi et hu",
    "turkic": "tr az kk uz ky tk tt",
    "indo-aryan": "hi ur bn mr gu pa ne si",
    "semitic": "ar he am mt",
}
DIM, GRAMS = 4096, (1, 2, 3, 4)
SAMPLE_ROWS = 3000
UNKNOWN = "und"


def family(lang: str) -> str:
    code = lang.lower().split("-")[0].split("_")[0]
    return next((f for f, codes in FAMILIES.items() if code in codes.split()), f"only {lang}")


def features(data: np.ndarray, offsets: np.ndarray, ranges) -> tuple[list[np.ndarray], np.ndarray]:
    """Hashed features at each byte (one array for each kind) and how many each document has."""
    low = textops.LOWER[data].astype(np.uint32)
    low[low < 48] = 32  # blanks and punctuation are alike
    n, kinds = len(low), []
    total = np.zeros(n, np.uint32)
    for k in range(max(GRAMS)):
        shifted = np.zeros(n, np.uint32)
        shifted[: max(0, n - k)] = low[k:]
        total = total * np.uint32(0x01000193) + (shifted + np.uint32(1)) * np.uint32(0x9E3779B1)
        if k + 1 in GRAMS:
            kinds.append(((total * np.uint32(0x85EBCA6B)) >> np.uint32(16)) % np.uint32(DIM))
    return kinds, np.diff(offsets)


def letters(column) -> np.ndarray:
    """Whether each text has a letter."""
    import pyarrow.compute as pc

    return pc.fill_null(pc.match_substring_regex(column, r"\pL"), False).to_numpy(zero_copy_only=False)


def _sums(kinds, offsets, table):
    """Per document the sum of table's rows over all features; a feature near a document's end may reach into the next one's bytes, so those are left out."""
    n_docs, width = len(offsets) - 1, table.shape[1]
    out = np.zeros((n_docs, width))
    filled = np.flatnonzero(np.diff(offsets) > 0)
    if not len(filled):
        return out
    left = np.repeat(offsets[1:], np.diff(offsets)) - np.arange(offsets[-1])  # bytes to the end of the document
    for k, kind in zip(GRAMS, kinds, strict=True):
        value = table[kind]
        value[left < k] = 0
        out[filled] += np.add.reduceat(value, offsets[:-1][filled], 0)
    return out


def _vectors(batches):
    """(lang, text) -> (lang, averaged features as 32-bit floats)."""
    for batch in batches:
        data, offsets = textops.buffers(batch.column(1))
        ok = letters(batch.column(1))
        rows, langs = [], []
        for d in np.flatnonzero(ok):
            part = data[offsets[d] : offsets[d + 1]]
            kinds, size = features(part, np.array([0, len(part)]), None)
            x = np.zeros(DIM)
            for k, kind in zip(GRAMS, kinds, strict=True):
                x += np.bincount(kind[: max(0, len(part) - k + 1)], minlength=DIM)
            rows.append((x / max(1, len(part))).astype(np.float32).tobytes())
            langs.append(batch.column(0)[int(d)].as_py())
        yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(rows, pa.binary())], ["lang", "x"])


def svm(x: np.ndarray, y: np.ndarray, rounds: int = 300, penalty: float = 1e-5) -> tuple[np.ndarray, float]:
    """Weights and bias of a linear machine with squared hinge loss, y in {-1, 1}; both classes weigh alike."""
    w, b = np.zeros(x.shape[1], x.dtype), x.dtype.type(0)
    y = y.astype(x.dtype)
    weight = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum())).astype(x.dtype)
    m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    for t in range(1, rounds + 1):
        slack = np.maximum(0, 1 - y * (x @ w + b))
        pull = -2 * weight * slack * y
        g = np.append(x.T @ pull + penalty * w, pull.sum())
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        step = 0.3 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9) * min(1, 2 - 2 * t / (rounds + 1))
        w, b = w - step[:-1].astype(x.dtype), b - x.dtype.type(step[-1])
    return w, float(b)


class Model:
    """Families, languages and machines."""

    def __init__(self, x: np.ndarray, langs: list[str]):
        """x (32-bit rows of averaged features) is overwritten, so that one copy of it is held."""
        self.langs = sorted(set(langs))
        self.families = sorted({family(v) for v in self.langs})
        self.mean = x.mean(0) if len(x) else np.zeros(DIM)
        self.scale = 1 / (x.std(0) + 1e-4) if len(x) else np.ones(DIM)
        self.mean, self.scale = self.mean.astype(np.float32), self.scale.astype(np.float32)
        z = x
        z -= self.mean
        z *= self.scale / np.float32(np.sqrt(DIM))
        y = np.array(langs)
        of = np.array([family(v) for v in langs])
        self.machines = []  # (kind, a, b, weights on raw averages, bias)
        for f in self.families if len(self.families) > 1 else []:
            self._add("family", f, None, z, np.where(of == f, 1.0, -1.0))
        for f in self.families:
            own = [v for v in self.langs if family(v) == f]
            for k, a in enumerate(own):
                for b in own[k + 1 :]:
                    sel = (y == a) | (y == b)
                    self._add("pair", a, b, z[sel], np.where(y[sel] == a, 1.0, -1.0))
        self.table = np.array([m[3] for m in self.machines]).T if self.machines else np.zeros((DIM, 0))
        self.bias = np.array([m[4] for m in self.machines])
        self.machines = [m[:3] for m in self.machines]

    def _add(self, kind, a, b, z, y):
        w, bias = svm(z, y)
        raw = w.astype(np.float64) * self.scale / np.sqrt(DIM)
        self.machines.append((kind, a, b, raw, bias - float(self.mean @ raw)))

    def predict(self, data, offsets):
        """Languages and scores of the documents."""
        kinds, size = features(data, offsets, None)
        margin = _sums(kinds, offsets, self.table) / np.maximum(1, size)[:, None] + self.bias
        sure = 1 / (1 + np.exp(-np.clip(4 * margin, -50, 50)))
        n = len(size)
        fam = [k for k, m in enumerate(self.machines) if m[0] == "family"]
        if fam:
            best = margin[:, fam].argmax(1)
            names, p = np.array([self.machines[k][1] for k in fam], object)[best], sure[:, fam][np.arange(n), best]
        else:
            names, p = np.array(self.families * n, object), np.ones(n)
        out, score = np.empty(n, object), np.zeros(n)
        for f in self.families:
            rows = np.flatnonzero(names == f)
            own = [v for v in self.langs if family(v) == f]
            votes = np.zeros((len(rows), len(own)))
            soft = np.zeros((len(rows), len(own)))
            for k, (kind, a, b) in enumerate(self.machines):
                if kind == "pair" and a in own:
                    s, i, j = sure[rows, k], own.index(a), own.index(b)
                    votes[np.arange(len(rows)), np.where(s >= 0.5, i, j)] += 1
                    soft[:, i] += s
                    soft[:, j] += 1 - s
            if len(own) == 1:
                pick, q = np.zeros(len(rows), int), np.ones(len(rows))
            else:
                pick = (votes + soft / (len(own) + 1)).argmax(1)
                q = soft[np.arange(len(rows)), pick] / (len(own) - 1)
            out[rows] = np.array(own, object)[pick]
            score[rows] = p[rows] * q
        return out, score


def fit(labelled: DataFrame, text_col: str, lang_col: str, id_col: str, sample_rows: int = SAMPLE_ROWS) -> Model:
    """A model from at most sample_rows rows with a language, about as many of each language."""
    rows = labelled.where(F.col(lang_col).isNotNull())
    per = {r[0]: r[1] for r in rows.groupBy(lang_col).count().collect()}
    if not per:
        return Model(np.zeros((0, DIM), np.float32), [])
    each = max(1, sample_rows // len(per))
    share = F.lit(0.0)
    for lang, n in per.items():
        share = F.when(F.col(lang_col) == lang, min(1.0, 0.9 * each / n if n > each else 1.0)).otherwise(share)
    chance = F.pmod(F.xxhash64(F.lit("sample"), F.col(id_col)), F.lit(1 << 30)) / float(1 << 30)
    chosen = rows.where(chance < share).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text")).mapInArrow(textops.tidy(_vectors), "lang string, x binary")
    found = chosen.limit(2 * sample_rows).collect()
    langs, x = [r["lang"] for r in found], np.empty((len(found), DIM), np.float32)
    for k, r in enumerate(found):
        x[k] = np.frombuffer(r["x"], np.float32)
    del found
    return Model(x, langs)


def _predict(sent, text_at, names):
    def run(batches):
        model = sent.value
        for batch in batches:
            data, offsets = textops.buffers(batch.column(text_at))
            ok = letters(batch.column(text_at))
            langs, scores = [], []
            for i, j in textops.chunks(offsets):
                out, score = model.predict(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]) if model.langs else (np.full(j - i, UNKNOWN, object), np.zeros(j - i))
                langs.append(out)
                scores.append(score)
            lang = np.concatenate([np.zeros(0, object), *langs])
            score = np.concatenate([np.zeros(0), *scores])
            lang[~ok], score[~ok] = UNKNOWN, 0.0
            cols = [c for k, c in enumerate(batch.columns)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names)

    return run


def identify(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """docs with lang_pred and score more (suffixed by _ where docs has such a name)."""
    names = [f"c{k}" for k in range(len(docs.columns))]
    fields = [T.StructField(n, f.dataType) for n, f in zip(names, docs.schema.fields, strict=True)] + [T.StructField("p", T.StringType()), T.StructField("s", T.DoubleType())]
    sent = docs.sparkSession.sparkContext.broadcast(model)
    out = docs.toDF(*names).mapInArrow(textops.tidy(_predict(sent, docs.columns.index(text_col), [*names, "p", "s"])), T.StructType(fields))
    pred = shared.spare(docs, "lang_pred")
    return out.toDF(*docs.columns, pred, shared.spare(docs, "score"))


def held_out(doc_id: Column) -> Column:
    """The fold that fitting never sees."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit_contract(docs: DataFrame) -> Model:
    return fit(docs.where(~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull()), "text", "lang", "doc_id")


def op10(spark, sf_dir: str) -> DataFrame:
    """The contract's prediction for each document."""
    docs = shared.table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    out = identify(docs.select("doc_id", "text"), fit_contract(docs))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
