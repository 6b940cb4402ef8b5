import collections
import hashlib
import json
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from mobility_ldp.llm import chat, decontaminate, langid, licences, line_dedup, near_dedup, packing, pii, textops, topk, urlrules

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
AZ = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
CLASH = "n_lines bigint, kept_text string, score double, lang_pred string, start bigint, row_key bigint, text_key string, id bigint, key string"


def words(t):
    return WORD.findall((t or "").translate(AZ))


def prose(seed, n):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefgé") for _ in range(r.randrange(2, 7))) for _ in range(n))


def odd_texts():
    long = prose(1, 60_000)
    return [None, "", " \n\t", "...", "A", "É x", long, long, prose(2, 40), prose(2, 40), "a\n" * 30, "\u0000\U0001F600 <|endoftext|> end"]


def frame(spark, texts, ids=None, extra=True):
    rows = [((k if ids is None else ids[k]), t, None, None, None) for k, t in enumerate(texts)]
    df = spark.createDataFrame(rows, DOCS)
    return df.select("*", *[F.lit(7).cast(c.split()[1]).alias(c.split()[0]) for c in CLASH.split(", ")]) if extra else df


# ---- decontamination ---------------------------------------------------------------


def brute_hits(text, items, window=13):
    w, hit, found = words(text), set(), set()
    for item, t in items:
        x = words(t)
        n = min(window, len(x))
        grams = {tuple(x[k : k + n]) for k in range(len(x) - n + 1)} if n else set()
        for k in range(len(w) - n + 1 if n else 0):
            if tuple(w[k : k + n]) in grams:
                hit |= set(range(k, k + n))
                if item is not None:
                    found.add(str(item))
    return len(w), len(hit), sorted(found)


@pytest.mark.parametrize("limit", [64 << 20, -1])
def test_decontamination_is_exact(spark, limit, monkeypatch):
    monkeypatch.setattr(decontaminate, "BROADCAST_BYTES", limit)
    r = random.Random(4)
    vocab = ["a", "b", "c", "dd", "é"]
    item = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    items = [(k, item(n)) for k, n in enumerate([1, 3, 5, 8, 12, 13, 14, 20, 30])] + [(9, None), (10, "..."), (None, item(15)), (6, item(13))]
    texts = odd_texts()[:6] + [" ".join([item(20), items[k][1] or "", item(9).upper(), items[7][1]]) for k in range(9)] + [item(300), items[8][1] * 2]
    docs, bench = frame(spark, texts), spark.createDataFrame(items, "item_id bigint, text string")
    got = decontaminate.contamination(docs, bench, keep=["doc_id", "score"]).collect()
    assert len(got) == len(texts)
    for x in got:
        assert (x["n_words"], x["n_hit"], x["items"]) == brute_hits(texts[x["doc_id"]], items), x["doc_id"]
    kept = {x["doc_id"] for x in decontaminate.decontaminate(docs, bench).collect()}
    assert kept == {k for k, t in enumerate(texts) for n, h, _ in [brute_hits(t, items)] if not (h and 20 * h >= n)}


@pytest.mark.parametrize("window", [1, 2, 5, 13])
def test_windows_and_both_joins(spark, window, monkeypatch):
    r = random.Random(window)
    text = lambda n: " ".join(r.choice("abc") for _ in range(n))
    items = [(k, text(n)) for k, n in enumerate((4, 9, 20))]
    texts = [text(60) for _ in range(8)] + [None]
    docs, bench = frame(spark, texts, extra=False), spark.createDataFrame(items, "item_id bigint, text string")
    for limit in (1 << 30, -1):
        monkeypatch.setattr(decontaminate, "BROADCAST_BYTES", limit)
        for x in decontaminate.contamination(docs, bench, window=window, keep=["doc_id"]).collect():
            assert (x["n_words"], x["n_hit"], x["items"]) == brute_hits(texts[x["doc_id"]], items, window)


def test_no_words_are_shuffled_with_fingerprints(spark, monkeypatch):
    monkeypatch.setattr(decontaminate, "BROADCAST_BYTES", -1)
    text = prose(8, 400)
    docs, bench = frame(spark, [text] * 30 + [prose(9, 50), None], extra=False), spark.createDataFrame([(1, " ".join(text.split()[100:130]))], "item_id bigint, text string")
    out = decontaminate.contamination(docs, bench, keep=["doc_id"])
    plan = out._jdf.queryExecution().explainString(out._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    moved = re.findall(r"\) Exchange\nInput \[\d+\]: \[(.*?)\]", plan)
    assert moved and not any("ws#" in x for x in moved)
    assert sorted(x["n_hit"] for x in out.collect()) == [0, 0] + [30] * 30


def test_decontamination_of_nothing(spark):
    bench = spark.createDataFrame([], "item_id bigint, text string")
    docs = frame(spark, ["a b c", None])
    assert [x["n_hit"] for x in decontaminate.contamination(docs, bench).collect()] == [0, 0]
    assert decontaminate.contamination(docs.limit(0), bench, keep=["doc_id"]).count() == 0
    assert decontaminate.decontaminate(docs, bench).count() == 2


# ---- near duplicates ---------------------------------------------------------------


def shingle_set(t):
    w = words(t)
    return frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()


def brute_classes(texts):
    s, root = [shingle_set(t) for t in texts], list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(texts)):
        for b in range(a):
            if s[a] and s[b] and len(s[a] & s[b]) >= 0.8 * len(s[a] | s[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return [find(k) for k in range(len(texts))]


def near_texts():
    r, out = random.Random(9), []
    for base in range(4):
        w = prose(100 + base, 150).split()
        for k in range(25):  # copies with ever more edits, near and far
            v = list(w)
            for _ in range(k // 3):
                v[r.randrange(len(v))] = f"new{r.randrange(10**6)}"
            out.append(" ".join(v))
        out += [" ".join(w[:120]), " ".join(w[:118]), " ".join(w + w)]
    return out + odd_texts()[:6] + odd_texts()[8:]


def test_classes_equal_brute_force(spark):
    texts = near_texts()
    got = {x["id"]: x["class_id"] for x in near_dedup.classes(frame(spark, texts)).collect()}
    assert [got[k] for k in range(len(texts))] == brute_classes(texts)


def test_one_of_each_class_stays(spark):
    texts = near_texts()
    docs = frame(spark, texts)
    kept = [x["doc_id"] for x in near_dedup.keep_first(docs).collect()]
    assert sorted(kept) == sorted(set(brute_classes(texts)))
    # equal rows, null ids
    twice = frame(spark, ["a b c d e f", "a b c d e f", "", "", "other words here now yes"], ids=[3, 3, 4, 4, None])
    rows = near_dedup.keep_first(twice).collect()
    assert collections.Counter(x["doc_id"] for x in rows) == {3: 1, 4: 2, None: 1}
    assert near_dedup.keep_first(docs.limit(0)).count() == 0
    assert near_dedup.keep_first(docs).columns == docs.columns


def test_repeats_inside_a_text_do_not_part_copies(spark):
    texts = []
    for k in range(12):
        w = prose(300 + k, 200).split()
        line = " ".join(w[60:74])
        texts += [" ".join(w), " ".join([*w, *[line] * 100])]
    got = {x["id"]: x["class_id"] for x in near_dedup.classes(frame(spark, texts)).collect()}
    assert [got[k] for k in range(24)] == brute_classes(texts) == [k - k % 2 for k in range(24)]


def passage_sets(n, seed=3):
    """Sets of shingles of 12 passages out of 30, half of them with a near copy that has one other passage."""
    r, own = random.Random(seed), random.Random(seed + 1)
    pool = [[own.randrange(1, 1 << 62) for _ in range(4)] for _ in range(30)]
    picks = []
    for _ in range(n // 2):
        p = r.sample(range(30), 12)
        picks += [frozenset(p), frozenset(p[1:] + [r.choice([k for k in range(30) if k not in p])])]
    return [sorted(x for k in p for x in pool[k]) for p in dict.fromkeys(picks)]


@pytest.mark.parametrize(("n", "block", "wide"), [(240, 256, 1024), (240, 16, 1024), (40, 8, 4)])
def test_links_of_one_crowded_bucket(spark, monkeypatch, n, block, wide):
    """As one block, strewn and in tiles, and by what the texts differ from their pivot by."""
    sets = passage_sets(n)
    monkeypatch.setattr(near_dedup, "_sets", lambda n: fixed_sets)
    monkeypatch.setattr(near_dedup, "BLOCK", block)
    monkeypatch.setattr(near_dedup, "WIDE", wide)

    def fixed_sets(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([sets[int(x)] for x in b.column(1).to_pylist()], pa.list_(pa.int64()))], ["node", "sh"])

    texts = spark.createDataFrame([(k, 0, str(k)) for k in range(len(sets))], "ra long, rb long, text string")
    keys = spark.createDataFrame([(k, k, 0, len(x), [1]) for k, x in enumerate(sets)], "node long, ra long, rb long, size long, bands array<long>")
    near = {(a, b) for a in range(len(sets)) for b in range(a) if len(set(sets[a]) & set(sets[b])) >= 0.8 * len(set(sets[a]) | set(sets[b]))}
    found = near_dedup.links(texts, keys)
    root = {x["node"]: x["root"] for x in near_dedup.components(found).collect()}
    assert [p for p in sorted(near) if root.get(p[0], p[0]) != root.get(p[1], p[1])] == [] and len(near) > 10
    # nothing is linked that no chain of near pairs joins
    brute = list(range(len(sets)))
    for _ in range(len(sets)):
        for a, b in near:
            brute[a] = brute[b] = min(brute[a], brute[b])
    assert all(brute[x["a"]] == brute[x["b"]] for x in found.collect())


def test_forest_at_the_exact_threshold():
    third = near_dedup.Fraction("0.8")
    for size in range(4, 60, 4):
        x = np.arange(size)
        y = np.arange(size + size // 4)  # Jaccard of exactly 0.8
        z = np.arange(size + size // 4 + 1)
        for other, same in ((y, True), (z, False)):
            values = np.concatenate([x, other, [10**6]])
            bounds = np.array([0, len(x), len(x) + len(other), len(values)])
            assert near_dedup.forest(values, bounds, third).tolist() == [0, 0 if same else 1, 2]
        assert near_dedup.slots(size, third) == size // 4 + 1
    values = np.concatenate([np.sort(np.random.default_rng(k).choice(30_000, 9_000, False)) for k in range(3)])
    assert near_dedup.forest(np.concatenate([values, values[:9_000]]), np.arange(5) * 9_000, third).tolist() == [0, 1, 2, 0]


@pytest.mark.parametrize("rare", [0, 4096])
def test_tiles_equal_all_pairs(monkeypatch, rare):
    monkeypatch.setattr(near_dedup, "RARE", rare)
    monkeypatch.setattr(near_dedup, "PAIRS", 50)
    third, sets, n = near_dedup.Fraction("0.8"), passage_sets(120), 45
    label, old = list(range(len(sets))), None
    near = [(i, j) for i in range(n) for j in range(n, len(sets)) if len(set(sets[i]) & set(sets[j])) >= 0.8 * len(set(sets[i]) | set(sets[j]))]
    while label != old:
        old = list(label)
        for i, j in near:
            label[i] = label[j] = min(label[i], label[j])
    assert near_dedup.across(np.concatenate([np.array(x) for x in sets]), np.cumsum([0, *map(len, sets)]), n, third).tolist() == label and near
    assert near_dedup.across(np.arange(3), np.array([0, 3]), 0, third).tolist() == near_dedup.across(np.arange(3), np.array([0, 3]), 1, third).tolist() == [0]


def test_many_texts_outside_are_held_against_their_group_at_once(spark, monkeypatch):
    """Over 1,024 texts of one bucket that are near to few others: no rounds by what they differ by."""
    sets = passage_sets(1500)
    monkeypatch.setattr(near_dedup, "_differing", None)

    def fixed_sets(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([sets[int(x)] for x in b.column(1).to_pylist()], pa.list_(pa.int64()))], ["node", "sh"])

    monkeypatch.setattr(near_dedup, "_sets", lambda n: fixed_sets)
    texts = spark.createDataFrame([(k, 0, str(k)) for k in range(len(sets))], "ra long, rb long, text string")
    keys = spark.createDataFrame([(k, k, 0, len(x), [1]) for k, x in enumerate(sets)], "node long, ra long, rb long, size long, bands array<long>")
    root = {x["node"]: x["root"] for x in near_dedup.components(near_dedup.links(texts, keys)).collect()}
    columns = {v: k for k, v in enumerate(sorted({v for x in sets for v in x}))}
    inc = np.zeros((len(sets), len(columns)), np.float32)
    for k, x in enumerate(sets):
        inc[k, [columns[v] for v in x]] = 1
    both, size = (inc @ inc.T).astype(int), inc.sum(1).astype(int)
    linked, label = 9 * both >= 4 * (size[:, None] + size[None]), np.arange(len(sets))
    for _ in range(50):
        label = np.where(linked, label[None], len(sets)).min(1)
    assert [root.get(k, k) for k in range(len(sets))] == label.tolist() and len(set(label)) < len(sets) - 10


def test_one_large_group_of_near_copies(spark):
    """2,000 copies with more and less edits: the classes of all pairs."""
    r, w, texts = random.Random(4), prose(77, 140).split(), []
    for k in range(2000):
        v = list(w)
        for _ in range(r.randrange(0, 7)):
            v[r.randrange(len(v))] = r.choice(w) if k % 3 else f"new{r.randrange(40)}"
        texts.append(" ".join(v))
    ids, rows, cols, sizes = {}, [], [], []
    for k, t in enumerate(texts):
        own = shingle_set(t)
        rows += [k] * len(own)
        cols += [ids.setdefault(x, len(ids)) for x in own]
        sizes.append(len(own))
    m = np.zeros((len(texts), len(ids)), np.float32)
    m[rows, cols] = 1
    both, size = (m @ m.T).astype(np.int64), np.array(sizes)
    linked = 9 * both >= 4 * (size[:, None] + size[None])
    label = np.arange(len(texts))
    while True:
        least = np.where(linked, label[None], len(texts)).min(1)
        if (least == label).all():
            break
        label = least
    got = {x["id"]: x["class_id"] for x in near_dedup.classes(frame(spark, texts, extra=False)).collect()}
    assert [got[k] for k in range(len(texts))] == label.tolist()
    assert len(set(label.tolist())) > 50


def test_signatures_estimate_probability_jaccard():
    r = np.random.default_rng(0)
    pool = r.integers(1, 1 << 63, 300).astype(np.uint64)
    a, b = np.sort(pool[:200]), np.sort(pool[100:300])
    wa, wb = dict(zip(a.tolist(), r.integers(1, 4, 200).tolist())), dict(zip(b.tolist(), r.integers(1, 4, 200).tolist()))
    m = 4096
    sig = near_dedup.signatures(np.concatenate([a, b]), np.array([wa[x] for x in a.tolist()] + [wb[x] for x in b.tolist()], float), np.array([0, 200, 400]), m)
    same = (sig[0] == sig[1]).mean()
    both = set(wa) | set(wb)
    want = sum(1 / sum(max(wa.get(y, 0) / wa[x], wb.get(y, 0) / wb[x]) for y in both) for x in set(wa) & set(wb))
    assert abs(same - want) < 4 * (want * (1 - want) / m) ** 0.5
    assert (near_dedup.signatures(np.array([5], np.uint64), np.ones(1), np.array([0, 1, 1]), 8) == [[5] * 8, [0] * 8]).all()


def test_components_of_a_chain(spark):
    e = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "a long, b long")
    got = {x["node"]: x["root"] for x in near_dedup.components(e).collect()}
    assert got == {**{k: 0 for k in range(1, 41)}, 101: 100}


def test_shingles_by_bytes():
    texts = ["A b-c", "", "é É x", "one two three four five six"]
    raw = [t.encode() for t in texts]
    data, offsets = np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)])
    s, e, per = textops.words(data, offsets)
    assert [data[a:b].tobytes().decode() for a, b in zip(s, e)] == ["A", "b", "c", "é", "É", "x", *texts[3].split()]
    h, b, size, whole = near_dedup.shingles(data, offsets, textops.RangeHash(near_dedup.BASE))
    assert np.diff(b).tolist() == [1, 0, 1, 2] and size.tolist() == [3, 0, 3, 6] and all(len(set(x.tolist())) == 4 for x in whole)


# ---- chat ---------------------------------------------------------------------------


@pytest.mark.parametrize("text", ["</s>[INST] ok [/INST]", "<|end|>", "<\\|x", "<", "[", "<<SYS>>", "<\\\\/s>", "\\", "[\\INST]<|role|>", "é\U0001F600<|", "|end|>"])
def test_escaping_is_reversible(text):
    assert chat.unescape(chat.escape(text)) == text
    formatted, _ = chat.render([("user", text), (text, "<"), ("assistant", text)])
    assert chat.parse(formatted) == [("user", text), (text, "<"), ("assistant", text)]
    assert not re.search(r"</s>|\[/?INST\]", formatted)


def test_chat_digests(spark):
    draw, pieces = random.Random(1), ["<|end|>", "</s>", "[INST]", "\\", " ", "\n", "é", "\U0001F600", "a", "<", "|", ">", "\t\t", "  x"]
    rows = [(c, t, draw.choice(["user", "assistant", "system", None]), draw.choice([None, "", "".join(draw.choice(pieces) for _ in range(draw.randrange(30)))])) for c in [*range(20), None] for t in range(draw.randrange(1, 6))]
    rows += [(3, 0, "assistant", "tie"), (3, 0, "assistant", "tie")]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    for limit in (10**6, 20):  # whole, and in segments
        got = {x["conv_id"]: x for x in chat.digests(chat.format_chats(df, max_chars=limit)).collect()}
        assert len(got) == 21
        for c in got:
            own = sorted(((t, r or "", x or "", r is not None, x is not None) for k, t, r, x in rows if k == c), key=lambda v: (v[0], v[3], v[1], v[4], v[2]))
            turns = "".join(f"{r}\n{x}\n" for _, r, x, _, _ in own)
            loss = "".join(x for _, r, x, _, _ in own if r == "assistant")
            assert got[c]["n_turns"] == len(own)
            assert got[c]["turns_sha256"] == hashlib.sha256(turns.encode()).hexdigest()
            assert got[c]["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest() and got[c]["loss_chars"] == len(loss)
    assert chat.digests(chat.format_chats(df.limit(0))).count() == 0


# ---- URL rules ------------------------------------------------------------------------


def test_given_rules(spark):
    cases = [
        ("http://a.example.com/en/70?x", "a.example.com", "/en/70", "example.com/en/7", "allow"),
        ("HTTP://EXAMPLE.COM/en/8#t", "example.com", "/en/8", "com/en/", "block"),
        ("https://net/de/", "net", "/de/", "net/de/", "allow"),
        ("x://notexample.net/de/8", "notexample.net", "/de/8", "net/de/", "allow"),
        ("x://example.net/de/81", "example.net", "/de/81", "example.net/de/8", "block"),
        ("x://a.org/es/1", "a.org", "/es/1", "org/es/", "block"),
        ("x://a.org/EN/", "a.org", "/EN/", None, "allow"),
        ("example.com/en/", "", "", None, "allow"),
        (None, "", "", None, "allow"),
        ("", "", "", None, "allow"),
        ("x://a.com?q=/en/", "a.com", "", None, "allow"),
        ("x://a.com", "a.com", "", None, "allow"),
    ]
    pages = spark.createDataFrame([(k, c[0], 1, 1) for k, c in enumerate(cases)], "page_id bigint, url string, row int, token int")
    none = spark.createDataFrame([], "token string, antecedent array<string>, confidence double, support double, lift double")
    got = {x["page_id"]: x for x in urlrules.judge(pages, none).collect()}
    for k, (_, host, path, rule, verdict) in enumerate(cases):
        assert (got[k]["host"], got[k]["path"], got[k]["rule"], got[k]["verdict"]) == (host, path, rule, verdict), cases[k]


def test_rules_are_those_of_the_contract(spark):
    contract = "block com/en/, allow example.com/en/7, allow net/de/, block example.net/de/8, block org/es/"
    assert ", ".join(f"{v} {h}{p}" for v, h, p in urlrules.RULES) == contract
    # the SQL and the operator give each rule its word, also where the method would say the other
    mined = spark.createDataFrame([("h:net", ["h:net"], 1.0, 1.0, 2.0)], "token string, antecedent array<string>, confidence double, support double, lift double")
    pages = spark.createDataFrame([(1, "x://a.net/de/7"), (2, "x://a.net/fr/7"), (3, "x://b.example.net/de/8")], "page_id bigint, url string")
    assert {x["page_id"]: x["verdict"] for x in urlrules.judge(pages, mined).collect()} == {1: "allow", 2: "block", 3: "block"}
    words = dict(re.findall(r"starts_with\(path, '([^']*)'\) THEN '(allow|block)'", urlrules.sql()))
    assert words == {"/en/": "block", "/en/7": "allow", "/de/": "allow", "/de/8": "block", "/es/": "block"}


def test_mined_rules(spark, monkeypatch):
    r = random.Random(2)
    rows = []
    for k in range(400):
        spam = r.random() < 0.3
        host = "farm.example.org" if spam else r.choice(["a.example.com", "b.example.net", "farm.example.net"])
        rows.append((k, f"http://{host}/{r.choice(['en', 'fr'])}/{k}" + ("?ref=x" if r.random() < 0.5 else ""), spam if r.random() < 0.95 else not spam))
    pages = spark.createDataFrame([x[:2] for x in rows], "page_id bigint, url string")
    labels = spark.createDataFrame([(k, int(not bad), 0) for k, _, bad in rows] + [(None, 0, 0)], "doc_id bigint, quality int, toxic int")
    rules = urlrules.mine(urlrules.labelled_pages(pages, labels))
    assert rules.count() > 0
    toks = {x["page_id"]: set(x["t"]) for x in pages.select("page_id", urlrules.tokens(F.col("url")).alias("t")).collect()}
    bad = {k for k, _, b in rows if b}
    for x in rules.collect():  # supports and confidences by counting
        own = {k for k, t in toks.items() if set(x["antecedent"]) <= t}
        assert abs(x["confidence"] - len(own & bad) / len(own)) < 1e-9 and len(own & bad) >= 20 and x["confidence"] >= 0.6
        assert x["token"] in x["antecedent"]
    want = {k for k, t in toks.items() if any(set(x["antecedent"]) <= t for x in rules.collect())}
    for limit in (10**6, -1):
        monkeypatch.setattr(urlrules, "BROADCAST_RULES", limit)
        got = urlrules.judge(pages, rules, fixed=()).collect()
        assert len(got) == 400 and {x["page_id"] for x in got if x["verdict"] == "block"} == want
    assert urlrules.mine(urlrules.labelled_pages(pages, labels.limit(0))).count() == 0
    assert urlrules.judge(pages.limit(0), rules).count() == 0


def test_a_small_bad_host_among_many_pages(spark):
    n = 14_000
    host = F.when(F.col("id") < 50, "farm.example.org").otherwise(F.concat(F.lit("h"), (F.col("id") % 40).cast("string"), F.lit(".example.com")))
    pages = spark.range(n).select(F.col("id").alias("page_id"), F.concat(F.lit("http://"), host, F.lit("/p")).alias("url"))
    labels = spark.range(n).select(F.col("id").alias("doc_id"), (F.col("id") >= 50).cast("int").alias("quality"), F.lit(0).alias("toxic"))
    rules = urlrules.mine(urlrules.labelled_pages(pages, labels))
    got = {x["page_id"] for x in urlrules.judge(pages, rules, fixed=()).collect() if x["verdict"] == "block"}
    assert got == set(range(50))


# ---- licences ---------------------------------------------------------------------------


def test_licences(spark):
    mit = licences.TEXTS["MIT"]
    texts = [
        mit,
        mit.upper().replace("copyright (c) <year>", "Copyright (C) 2020").replace("\n", "\r\n"),
        re.sub("(?i)license", "licence", mit).replace("NONINFRINGEMENT", "NON-INFRINGEMENT").replace("Copyright (c) <year> <copyright holders>", "Copyright (c) 1999 Some One\n(c) 2001 Another"),
        mit + " and more",
        "x\nLicensed under CC BY-NC 4.0.\nReleased under the MIT Licence\n",
        None,
        "",
        "---",
        prose(3, 30_000),
    ]
    got = {x["doc_id"]: x for x in licences.scan(frame(spark, texts)).collect()}
    assert [got[k]["licence"] for k in range(9)] == ["MIT"] * 3 + [None] * 6
    assert got[4]["notices"] == "CC-BY-NC-4.0,MIT"
    assert got[5]["text_digest"] is None and got[7]["text_digest"] is None and got[8]["text_digest"]
    assert licences.scan(frame(spark, []).limit(0)).count() == 0


def test_given_licence_texts(spark):
    own = [("Own-1.0", "Own License\n\nCopyright (c) <year> X\n\n" + prose(8, 2_000) + " organisation"), ("MIT", licences.TEXTS["MIT"]), ("BSD-2-Clause", licences.TEXTS["BSD-2-Clause"]), ("None", None)]
    texts = [own[0][1], own[0][1].split("\n\n", 1)[1].replace("organisation", "organization"), own[1][1].split("\n\n", 1)[1], own[2][1], own[0][1] + " more", None]
    table = spark.createDataFrame(own, "licence string, text string")
    got = {x["doc_id"]: x["licence"] for x in licences.scan(frame(spark, texts), texts=table).collect()}
    assert [got[k] for k in range(6)] == ["Own-1.0", "Own-1.0", "MIT", "BSD-2-Clause", None, None]


# ---- top-k --------------------------------------------------------------------------------


def brute_top(rows, k):
    ok = [(i, [int(np.floor(64 * float(x))) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    out = []
    for i, v in ok:
        if i % 20 == 0:
            c = sorted((-sum(a * b for a, b in zip(v, w)), j) for j, w in ok if j != i and len(w) == len(v))[:k]
            out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(c)]
    return sorted(out)


def test_topk(spark, monkeypatch):
    r = np.random.default_rng(3)
    rows = [(int(i), [float(np.float32(x)) for x in r.normal(size=4).round(1)]) for i in range(150)]  # few values: many ties
    rows += [(200, None), (220, [1.0, None, 0.0, 0.0]), (240, [float("nan")] * 4), (260, [float("inf")] * 4), (280, [1.0, 2.0]), (281, [3.0, 4.0]), (None, [0.0] * 4), (300, []), (301, [])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").repartition(5)
    for block in (16_384, 3):
        got = topk.search(df, df.where("vec_id % 20 = 0"), k=7, block_rows=block)
        assert sorted((x["query_id"], x["rank"], x["vec_id"], x["score"]) for x in got.collect()) == brute_top(rows, 7)
    assert topk.search(df.limit(0), df.limit(0)).count() == 0


def test_topk_beyond_floats():
    a, b = np.array([[2.0**40, 3.0]]), np.array([[2.0**20 + 1, 1.0], [1.0, 1.0]])
    assert topk.scores(a, b).tolist() == [[2**40 * (2**20 + 1) + 3, 2**40 + 3]]
    assert topk.scores(np.array([[1e300]]), np.array([[1e300]])).tolist() == [[2**63 - 1]]


# ---- lines ------------------------------------------------------------------------------------


def brute_lines(texts, min_docs, min_chars=1):
    strip = " \t\n\x0b\x0c\r"
    key = lambda x: x.strip(strip).translate(AZ)
    lines = [(t or "").split("\n") for t in texts]
    n = collections.Counter(k for ls in lines for k in {key(x) for x in ls} if len(k) >= min_chars)
    return [(len(ls), sum(len(key(x)) >= min_chars and n[key(x)] >= min_docs for x in ls), "\n".join(x for x in ls if not (len(key(x)) >= min_chars and n[key(x)] >= min_docs))) for ls in lines]


def test_line_dedup(spark, monkeypatch):
    r = random.Random(5)
    pool = ["Alpha", " alpha\t", "ALPHA\r", "É", "é", "x", "", " ", "beta\x0b", "gamma delta"] + [f"line {k}" for k in range(40)]
    texts = ["\n".join(r.choice(pool) for _ in range(r.randrange(1, 9))) for _ in range(120)] + odd_texts()
    docs = frame(spark, texts)
    for keys, group in ((1 << 16, 1 << 26), (4, 400)):  # one shard in one pass; many shards in many passes
        monkeypatch.setattr(line_dedup, "SHARD_KEYS", keys)
        out = line_dedup.drop_common_lines(docs, min_docs=10, group_bytes=group)
        kept, n, d = out.columns[-3:]
        got = {x["doc_id"]: (x[n], x[d], x[kept] or "") for x in out.collect()}
        assert [got[k] for k in range(len(texts))] == brute_lines(texts, 10)
    assert len(set(c.lower() for c in out.columns)) == len(out.columns)
    assert line_dedup.drop_common_lines(docs.limit(0)).count() == 0
    short = line_dedup.drop_common_lines(frame(spark, texts, extra=False), min_docs=5, min_chars=3)
    assert {x["doc_id"]: (x["n_lines"], x["n_dropped"], x["kept_text"] or "") for x in short.collect()} == dict(enumerate(brute_lines(texts, 5, 3)))


def test_perfect_hash():
    r = np.random.default_rng(1)
    h1, h2 = r.integers(-(2**63), 2**63 - 1, 5000), r.integers(-(2**63), 2**63 - 1, 5000)
    h1[:3] = 77  # equal first halves end up in the rest
    a = line_dedup.build(h1, h2, np.arange(5000) + 1)
    s = line_dedup.Shard(a)
    assert len(a["fp"]) == 5000 and sorted(a["n"]) == list(range(1, 5001))
    own = s.counts(h1.view(np.uint64), h2.view(np.uint64))
    assert (own[3:] == np.arange(5000)[3:] + 1).all()
    assert not s.counts(h2.view(np.uint64), h1.view(np.uint64)).any()


# ---- packing ---------------------------------------------------------------------------------------


def test_packing(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = odd_texts() + ["x" * 5000, " " * 3000 + "y", "don't  stop\n\n\n now " * 700]
    rows = packing.pack(frame(spark, texts)).collect()
    assert len({x["sequence_id"] for x in rows}) == len(rows)
    by = collections.defaultdict(list)
    for x in rows:
        by[x["doc_id"]].append(x)
        assert x["offset"] == 0 and x["length"] == 1 << x["bucket"] <= 1024 and len(x["ids"]) == 4 * x["length"]
    for k, t in enumerate(texts):
        want = tok.encode(t or "", add_special_tokens=False).ids + [0]
        own = sorted(by[k], key=lambda x: x["start_"])
        got = np.concatenate([np.frombuffer(x["ids"], "<u4") for x in own])
        assert got.tolist() == want and own[0]["doc_tokens"] == len(want)
        assert [x["length"] for x in own] == packing.pieces(len(want), 1024)
        assert [x["start_"] for x in own] == np.cumsum([0, *[x["length"] for x in own]])[:-1].tolist()
    assert packing.padding(packing.pack(frame(spark, texts))).where("padded > 0").count() == 0
    assert packing.pack(frame(spark, []).limit(0)).count() == 0
    with pytest.raises(ValueError):
        packing.pack(frame(spark, texts), max_len=1000)


def test_op8_crc(spark, sf):
    from mobility_ldp.llm import shared

    x = packing.op8(spark, sf).orderBy("doc_id", "start").first()
    y = packing.pack(shared.table(spark, sf, "documents").select("doc_id", "text")).orderBy("doc_id", "start").first()
    assert x["ids_crc32"] == zlib.crc32(bytes(y["ids"]))


# ---- personal data -----------------------------------------------------------------------------------

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def plain_base(t):
    out = {}
    for kind, p in PATTERNS.items():
        out[kind] = []
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": lambda: True, "ip": lambda: all(int(x) <= 255 for x in m[0].split(".")), "card": lambda: 16 <= len(d) <= 19 and pii.luhn(d), "phone": lambda: 8 <= len(d) <= 15}[kind]():
                out[kind].append(m.span())
    return out


def test_base_patterns():
    r = random.Random(3)
    for _ in range(5000):
        t = "".join(r.choice("ab1.23@@+-% ()45..é") for _ in range(r.randrange(40)))
        assert pii.base_spans(t) == plain_base(t), t
    card = "4111111111111111"
    for t in (card, f"x{card}y {card[:4]} {card[4:8]}-{card[8:12]} {card[12:]}", f"1 {card}", "256.1.1.1 1.2.3.4.5.6.7.8", "a@b.c@d.e", "1" * 3000 + "." + "2" * 3000):
        assert pii.base_spans(t) == plain_base(t), t


def test_viterbi_over_pieces():
    r = np.random.default_rng(0)
    for n in (1, 5, 31, 32, 33, 300):
        e, trans, first, starts = r.normal(size=(n, 5)), r.normal(size=(5, 5)), r.normal(size=5), r.random(n) < 0.1
        starts[0] = True
        want, heads = [], [*np.flatnonzero(starts), n]
        for a, b in zip(heads[:-1], heads[1:]):
            d, came = first + e[a], []
            for i in range(a + 1, b):
                z = d[:, None] + trans
                came.append(z.argmax(0))
                d = z.max(0) + e[i]
            path = [int(d.argmax())]
            for c in came[::-1]:
                path.append(int(c[path[-1]]))
            want += path[::-1]
        assert pii.viterbi(e, starts, trans, first, piece=32).tolist() == want


def test_scan(spark):
    texts = odd_texts() + ["é mail a.b@x.org or +1 (212) 555-0147, card 4111 1111 1111 1111 from 10.0.0.1", "call (212) 555-0147 now", "write bob at example dot com please", "on 2021-03-14 at noon. Dot by dot."]
    got = {x["doc_id"]: x for x in pii.scan(frame(spark, texts)).collect()}
    for k, t in enumerate(texts):
        want = plain_base(t or "")
        assert got[k]["base_spans"] == pii.written(want)
        assert [got[k][f"n_{x}"] for x in pii.KINDS] == [len(want[x]) for x in pii.KINDS]
        assert set(filter(None, got[k]["base_spans"].split(","))) <= set(got[k]["spans"].split(","))
    n = len(odd_texts())
    assert got[n]["base_spans"] == got[n]["spans"] != ""
    assert got[n + 1]["spans"] == "phone:5:19" and got[n + 2]["spans"] == "email:6:28" and got[n + 3]["spans"] == ""
    assert pii.scan(frame(spark, []).limit(0)).count() == 0


def test_the_field_learns_its_table():
    ranges, model = textops.RangeHash(0x5851F42D4C957F2D), pii.fit()
    good = total = 0
    for text, spans in pii.pii_labels.labelled(copies=2, seed=99):  # other words and digits than it was fitted to
        raw = text.encode()
        got = {(a, b, k) for _, a, b, k in pii.field_spans(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), model, ranges)}
        want = {(len(text[:a].encode()), len(text[:b].encode()), k) for a, b, k in spans}
        total += len(want | got)
        good += len(want & got)
    assert good / total > 0.9


HELD = """
ask [[email|nina_k (at) web (dot) fr]] about it
contact [[email|support [at] shop [dot] net]] soon
my number is [[phone|(646) 555-0187]] ok
ring [[phone|07 55 51 20 14]] later
the host [[ip|172 . 16 . 4 . 12]] was down
paid with card [[card|4242.4242.4242.4242]] today
she sat at the dot of the map, at noon
| left | right | 12 | 2031 | 4.5 |
from 1811-1820 to 2.5.7 of 100 000 000 in 12:30:45
go go go go go go go go go go go go
digest 0bb3fce0c31ad44167de7d05e47a1227f75a4816
""".strip().splitlines()


def test_shapes_that_no_training_line_has():
    ranges, model = textops.RangeHash(0x5851F42D4C957F2D), pii.fit()
    good = wrong = wanted = 0
    for line in HELD:
        text, want = "", set()
        for part in re.split(r"(\[\[\w+\|.*?\]\](?!\]))", line):
            m = re.fullmatch(r"\[\[(\w+)\|(.*)\]\]", part)
            if m:
                want.add((m[1], len(text), len(text) + len(m[2])))
            text += m[2] if m else part
        base, every = next(pii.find(pa.array([text]), model, ranges))
        got = {(k, *x) for k, v in every.items() for x in v}
        assert not any(base.values())  # the base patterns know none of them
        good, wrong, wanted = good + len(got & want), wrong + len(got - want), wanted + len(want)
    assert wanted == 6 and good >= 5 and wrong == 0


# ---- languages ---------------------------------------------------------------------------------------------


def test_language_held_out(spark):
    from mobility_ldp.llm import shared

    docs = shared.table(spark, "/root/testdata/sf0.01", "documents")
    out = langid.op10(spark, "/root/testdata/sf0.01").join(docs.select("doc_id", "lang"), "doc_id")
    row = out.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")).alias("a"), F.min("score").alias("lo"), F.max("score").alias("hi")).first()
    assert row["a"] >= 0.97 and row["lo"] >= 0 and row["hi"] <= 1
    assert out.count() == docs.count()


def test_language_edges(spark):
    rows = [(k, prose(k, 30) if k % 2 else "und der die " * 9, "en" if k % 2 else "de", None, None) for k in range(40)]
    docs = spark.createDataFrame(rows, DOCS)
    model = langid.fit(docs, "text", "lang", "doc_id")
    odd = frame(spark, odd_texts())
    out = langid.identify(odd, model)
    pred, score = out.columns[-2:]
    got = {x["doc_id"]: (x[pred], x[score]) for x in out.collect()}
    assert len(got) == len(odd_texts())
    for k in (0, 1, 2, 3):
        assert got[k] == ("und", 0.0)
    assert all(got[k][0] in ("en", "de") and 0 <= got[k][1] <= 1 for k in (4, 5, 6, 8))
    none = langid.fit(docs.limit(0), "text", "lang", "doc_id")
    assert {x["lang_pred"] for x in langid.identify(docs.select("doc_id", "text"), none).collect()} == {"und"}
    only = langid.fit(docs.where("lang = 'de'"), "text", "lang", "doc_id")
    assert {x["lang_pred"] for x in langid.identify(docs.select("doc_id", "text"), only).collect()} == {"de"}


def test_prediction_does_not_see_other_columns(spark):
    docs = spark.createDataFrame([(k, prose(k % 7, 20), "en" if k % 7 < 4 else "fr", "s", 1) for k in range(60)], DOCS)
    model = langid.fit_contract(docs)
    a = langid.identify(docs.select("doc_id", "text"), model).collect()
    b = langid.identify(docs.select((F.col("doc_id") + 9).alias("doc_id"), "text"), model).collect()
    assert [(x["lang_pred"], x["score"]) for x in a] == [(x["lang_pred"], x["score"]) for x in b]


def test_native_plans(spark, sf):
    """The operators of built-in functions run no Python."""
    from mobility_ldp.llm import entries

    for name in ("op1_decontaminate", "op4_url", "op5_licence"):
        plan = entries.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|Arrow", plan), name
    assert json.dumps(list(entries.oracle_sql()))
