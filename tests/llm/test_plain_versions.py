"""Operators and the pipeline against slow plain versions, on small tables and on hard rows."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from test_contracts import HARD, fingerprint, groups, ids, texts
from tokenizers import Tokenizer

import corpus_pipeline
from waypath.llm import html_extract, id_output, mixing, packing, quality, queries, simhash, token_counts, toxicity, winnowing

MASK = (1 << 64) - 1


@pytest.fixture(scope="module")
def tok():
    return Tokenizer.from_file(str(public_tokenizers.path("word_bpe_49k.json")))


def gram_hash(gram):
    h = 0
    for c in gram:
        h = (h * 0x100000001B3 + ord(c) + 1) & MASK
    h ^= h >> 29
    return (h * 0x9E3779B97F4A7C15 & MASK) >> 32


def kept_grams(text, k=12, w=16):
    """(position, hash) of the rightmost smallest hash of every window."""
    grams = [text[i:i + k] for i in range(max(1, len(text) - k + 1))] if text else []
    h = [gram_hash(g) for g in grams]
    out = set()
    for lo in range(max(1, len(h) - w + 1) if h else 0):
        window = range(lo, min(lo + w, len(h)))
        out.add(max((i for i in window if h[i] == min(h[j] for j in window))))
    return sorted((i, h[i]) for i in out)


def alike(a, b):
    x, y = {h for _, h in a}, {h for _, h in b}
    return len(x & y) / len(x | y) if x and y else float(x == y)


def shown(grams):
    return " ".join(f"{i:x}:{h:08x}" for i, h in grams)


def check_winnowing(rows, text):
    order = sorted(text, reverse=True)
    got = {r.doc_id: r for r in rows}
    assert sorted(got) == sorted(text) and len(rows) == len(text)
    for n, i in enumerate(order):
        nxt = text[order[(n + 1) % len(order)]]
        half = len(text[i]) // 2
        edited = text[i][:len(text[i]) - half] + nxt[:half]
        a, e, b = kept_grams(text[i]), kept_grams(edited), kept_grams(nxt)
        r = got[i]
        assert (r.n_chars, r.fingerprint, r.edited_fingerprint) == (len(text[i]), shown(a), shown(e))
        assert r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert r.near_edited == pytest.approx(alike(a, e)) and r.near_next == pytest.approx(alike(a, b))


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", f"s{i % 2}", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")


def test_fingerprints_of_hard_rows(spark):
    rows = [(i, t[:900] if t else t) for i, t in HARD] + [(40, "ab" * 60), (41, "x" * 27), (42, "x" * 28), (-3, "é中" * 50)]
    check_winnowing(winnowing.edited_fingerprints(frame(spark, rows)).collect(), {i: t or "" for i, t in rows})


def test_fingerprints_of_the_small_table(spark, sf):
    some = {i: (t or "")[:1500] for i, t in texts(spark, sf).items()}
    docs = spark.createDataFrame(list(some.items()), "doc_id long, text string")
    check_winnowing(winnowing.edited_fingerprints(docs, buckets=5).collect(), some)


def test_one_row_follows_itself_and_null_ids_come_last(spark):
    one = winnowing.edited_fingerprints(frame(spark, [(7, "abcdef")])).collect()
    assert [(r.doc_id, r.near_next) for r in one] == [(7, 1.0)]
    docs = spark.createDataFrame([(None, "zz"), (2, "aa"), (9, "bb")], "doc_id long, text string")
    sha = {r.doc_id: r.edited_sha256 for r in winnowing.edited_fingerprints(docs).collect()}
    assert sha == {9: hashlib.sha256(b"ba").hexdigest(), 2: hashlib.sha256(b"az").hexdigest(), None: hashlib.sha256(b"zb").hexdigest()}


# ---------------------------------------------------------------- pages

HOSTILE = {
    "deep": "<div>" * 20000 + "<p>text</p>",
    "deep inline": "<article><p>" + "<b>" * 20000 + "text" + "</i>" * 20000,
    "open quotes": "<a x=\"1\" y='" * 8000 + "<p>text</p>",
    "named": "<div class=sidebar>" * 20000 + "text",
    "cells": "<table><tr><td>" + "<ul><li>" * 5000 + "<td></td>" * 5000 + "text",
}


@pytest.mark.parametrize("name", HOSTILE)
def test_hostile_pages_end(name):
    import time

    began = time.time()
    assert "text" in html_extract.extract_one(HOSTILE[name])
    html_extract.best_path(html_extract.parse(HOSTILE[name]))
    assert time.time() - began < 20


def test_pages_of_hosts_with_two_templates(spark):
    """Most pages of a host vote for one path; a page with another layout falls back to its own best."""
    p = "This is a sentence of the article that goes on for a while, as sentences of articles do. "
    a = lambda i: f"<html><body><nav><a href=x>Menu</a></nav><article><h1>T{i}</h1><p>{p * 3}</p><div class='notice'>Cookies</div><p>{p}{i}</p></article><div class=comments><p>{p * 9}</p></div></body></html>"
    b = lambda i: f"<html><body><header>Site</header><div class='content main-{i}'><h2>U{i}</h2><p>{p * 3}</p></div><form><p>{p}</p></form><aside>More</aside></body></html>"
    rows = [(i, "http://one.test/%d" % i, a(i)) for i in range(4)] + [(10, "http://one.test/x", b(1))] + [(20 + i, "https://two.test:80/%d" % i, b(i)) for i in range(3)] + [(30, None, None), (31, "x", "")]
    df = spark.createDataFrame([(*r, "extra") for r in rows], "page_id long, url string, html string, host string")
    got = {r.page_id: r.text for r in html_extract.main_text(df).collect()}
    line = p.strip()
    for i in range(4):
        assert got[i] == "\n".join([f"T{i}", " ".join([line] * 3), f"{p}{i}"])
    assert got[10] == "\n".join(["U1", " ".join([line] * 3)])
    assert all(got[20 + i] == "\n".join([f"U{i}", " ".join([line] * 3)]) for i in range(3)) and got[30] == got[31] == ""


# ---------------------------------------------------------------- scores

def slow_quality_features(text):
    """The same counts, each from its own loop."""
    words = text.split()
    if not words:
        return [0.0] * len(quality.NAMES)
    n, chars, low = len(words), len(text), [w.lower() for w in words]
    upper = lambda s: sum(c.isascii() and c.isupper() or "À" <= c <= "Þ" and c != "×" for c in s)
    runs = lambda s: len(re.findall(r"([^\w\s])\1\1", s))
    letters = max(1, sum(bool(re.match(r"[^\W\d_]", c)) for c in text))
    marks = sum(c in "#$%&*^~_=<>\\|@{}[]" for c in text)
    lines = [x for x in text.split("\n") if x.strip()]
    share = lambda test: sum(len(x) for x in lines if test(x)) / chars
    caps, pipes, mark = lambda x: upper(x) > len(x) / 2, lambda x: x.count("|") * 12 > len(x), lambda x: runs(x) * 14 > len(x)
    longest = max(len(m) for m in re.findall("1+", "1" + "".join("1" if a == b else "01" for a, b in zip(low, low[1:]))))
    return [
        math.log1p(n), sum(map(len, words)) / n, len(set(low)) / n**0.8, max(Counter(low).values()) / n, sum(a == b for a, b in zip(low, low[1:])) / n, 1 - len(set(lines)) / len(lines),
        upper(text) / letters, share(caps), sum(len(w) > 1 and w.isupper() for w in words) / n, math.log1p(100 * marks / chars), share(mark), min(1, runs(text) / n),
        min(1, text.count("|") / n), share(pipes), min(1, text.count("!!") / n), math.log1p(100 * text.count("!!") / n), sum(c.isdecimal() for c in text) / chars,
        letters / chars, sum(len(x) < 40 for x in lines) / len(lines), sum(len(w) <= 3 for w in low) / n, math.log(len(lines) / len(set(lines))), math.log1p(len(lines)),
        share(lambda x: x.rstrip()[-1] not in ".!?:;\"'”»)"), math.log1p(longest - 1), share(lambda x: caps(x) or pipes(x) or mark(x)),
    ]


TEXTS = ["", "One two  three.", "ÀÉ ÞING x² ١٢ 7", "BUY NOW!!! BUY | NOW | *** ### $$$\n\nBUY NOW!!!\n" * 30, "word " * 300, "É" * 250 + "\nok.", "a_b {x} [y] " * 500]


@pytest.mark.parametrize("text", TEXTS)
def test_quality_features(text):
    assert quality.features(text) == pytest.approx(slow_quality_features(text))


def test_quality_features_do_not_change_with_length():
    line = "Ω é ٣ X" + "x" * 180
    a, b = quality.features(line), quality.features("\n".join([line] * 100))
    at = quality.NAMES.index
    assert all(a[at(f)] == pytest.approx(b[at(f)], abs=0.01) for f in ("digits", "caps", "caps_lines", "letters"))


def scored_plainly(docs, labels, label, cut):
    """{row number: kept} of a model fitted without Spark on the labelled rows outside the held-out fold."""
    train = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 != 0
    by_id = {}
    for i, t in docs:
        if train(i) and labels.get(i) in (0, 1):
            by_id[i] = min(t or "", by_id.get(i, t or ""))
    if label == "quality":
        x = sorted(((i, labels[i], quality.features(t)) for i, t in by_id.items()))
        model = quality.QualityModel().fit(np.array([r[2] for r in x]).reshape(-1, len(quality.NAMES)), np.array([r[1] for r in x], int))
        return model.score(np.array([quality.features(t or "") for _, t in docs]).reshape(-1, len(quality.NAMES)))
    lexicons = []
    counts = defaultdict(lambda: [0] * 6)
    for i, t in by_id.items():
        for e in toxicity.entries_of(set(toxicity._WORD.findall(t.lower()))):
            counts[e][2 * toxicity.fold_of(i) + labels[i]] += 1
    have = Counter((toxicity.fold_of(i), labels[i]) for i in by_id)
    for left in (0, 1, 2, None):
        use, lex = [f for f in range(3) if f != left], {}
        p, q = (sum(have[f, y] for f in use) for y in (1, 0))
        for e, c in counts.items():
            tall, call = c[1] + c[3] + c[5], c[0] + c[2] + c[4]
            t, n = sum(c[2 * f + 1] for f in use), sum(c[2 * f] for f in use)
            odds = math.log((t + 0.5) / (p + 1)) - math.log((n + 0.5) / (q + 1))
            if tall >= 3 and call <= tall and t >= (3 if left is None else 2) and odds >= 2.2:
                lex[e] = odds
        lexicons.append(lex)
    x = sorted((i, labels[i], toxicity.features(t, lexicons[toxicity.fold_of(i)])) for i, t in by_id.items())
    model = toxicity.ToxicityModel().fit(np.array([r[2] for r in x]).reshape(-1, len(toxicity.NAMES)), np.array([r[1] for r in x], int), np.array([toxicity.fold_of(r[0]) for r in x], int), lexicons[-1])
    return model.score(np.array([toxicity.features(t or "", model.lexicon) for _, t in docs]).reshape(-1, len(toxicity.NAMES)))


@pytest.mark.parametrize("name,label,cut", [("op6_quality", "quality", 0.3), ("op1_toxicity", "toxic", 0.5)])
def test_scores_equal_a_model_fitted_without_spark(spark, sf, name, label, cut):
    labels = {r.doc_id: r[label] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    docs = sorted(texts(spark, sf).items())
    want = dict(zip([i for i, _ in docs], scored_plainly(docs, labels, label, cut)))
    got = {r.doc_id: r.score for r in queries.queries()[name](spark, sf).collect()}
    assert got == pytest.approx(want, abs=1e-9)


ODD = [(None, "null id", "en", None, 0, "x"), (1, None, "en", "a", 0, "x"), (1, None, "en", "a", 0, "x"), (2, "", None, "b", 0, None), (5, "same words here now", "en", "a", 9, "y"), (6, "same words here now", "en", "b", 9, "y"), (6, "other", "en", "b", 9, "y"), (8, "word " * 30000, "en", "a", 1, "z")]
ODD_COLS = "doc_id long, text string, lang string, source string, n_chars long, extra string"
LABELS = [(1, 1, 0), (2, 0, 1), (5, 1, 0), (6, 0, 1), (8, 1, None), (None, 1, 1), (5, 1, 0)]
CLASH = ["score", "source_size", "target", "fp", "rep", "start", "seq", "y", "id", "size", "part", "node", "text2", "held_out", "component_id"]


def test_stages_keep_odd_rows_and_clashing_columns(spark):
    docs = spark.createDataFrame(ODD, ODD_COLS)
    for c in CLASH:
        docs = docs.withColumn(c, F.lit("clash"))
    labels = spark.createDataFrame(LABELS, "doc_id long, quality int, toxic int")
    for f in (lambda d: quality.keep_good(d, labels), lambda d: toxicity.keep_clean(d, labels), simhash.keep_one, mixing.mix):
        out = f(docs)
        assert out.columns == docs.columns and all(r.score == r.target == "clash" for r in out.collect())
        assert f(docs.limit(0)).count() == 0


def test_reports_keep_odd_rows(spark):
    docs = spark.createDataFrame(ODD, ODD_COLS)
    labels = spark.createDataFrame(LABELS, "doc_id long, quality int, toxic int")
    none = docs.limit(0)
    n = len(ODD)
    for f in (lambda d: quality.scored(d, quality.trained(docs, labels)), lambda d: toxicity.scored(d, toxicity.trained(docs, labels)), token_counts.token_counts, simhash.near_duplicates, mixing.mix_report, winnowing.edited_fingerprints, id_output.id_report):
        rows = f(docs).collect()
        assert len(rows) == n and Counter(r.doc_id for r in rows) == Counter(r[0] for r in ODD)
        assert f(none).count() == 0
    assert Counter(r.doc_id for r in packing.pack(docs).where("start = 0").collect()) == Counter(r[0] for r in ODD)
    empty = labels.limit(0)
    assert quality.scored(docs, quality.trained(docs, empty)).count() == toxicity.scored(docs, toxicity.trained(docs, empty)).count() == n


def test_a_repeated_id_counts_once_in_the_sample(spark):
    docs = spark.createDataFrame([(1, f"text {i % 7}") for i in range(500)] + [(2, "b")], "doc_id long, text string")
    labels = spark.createDataFrame(LABELS, "doc_id long, quality int, toxic int")
    from waypath.llm.common import labelled_sample

    assert sorted(map(tuple, labelled_sample(docs, labels, "quality", 100).collect())) == [(i, t, y) for i, t, y in ((1, "text 0", 1), (2, "b", 0)) if zlib.crc32(str(i).encode()) % 5]


# ---------------------------------------------------------------- mixing and the pipeline

def taken_plainly(rows, weights=(5, 2, 1), share=1.5, most=2, seed=7):
    """(source_size, target, copies) per row of (doc_id, source, size)."""
    names = sorted({s for _, s, _ in rows}, key=lambda s: (s is None, s or ""))
    total = {s: sum(n for _, t, n in rows if t == s) for s in names}
    goal, left, open_ = {}, share * sum(total.values()), {s: weights[i % 3] for i, s in enumerate(names)}
    while open_:
        level = left / sum(open_.values())
        over = [s for s in open_ if level * open_[s] > most * total[s]]
        if not over:
            goal |= {s: level * w for s, w in open_.items()}
            break
        for s in over:
            goal[s] = float(most * total[s])
            left -= goal[s]
            del open_[s]
    out = [None] * len(rows)
    digest = lambda t: int(hashlib.md5(t.encode()).hexdigest()[:8], 16)
    for s in names:
        u = digest(f"{seed}:" + ("null" if s is None else "s" + s)) / 2**32
        rate = goal[s] / total[s] if total[s] else 0.0
        own = sorted((math.floor(math.log2(n + 1) * 4), digest("null" if i is None else str(i)), i is None, i or 0, n, k) for k, (i, t, n) in enumerate(rows) if t == s)
        for r, (*_, k) in enumerate(own):
            out[k] = (total[s], goal[s], math.floor((r + 1.0) * rate + u) - math.floor(r * rate + u))
    return out


def test_mixing_equals_a_plain_version(spark, sf):
    src = [(r.doc_id, r.source, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = [(i, s, len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))) for i, s, t in src]
    want = {i: (n, *x) for (i, _, n), x in zip(rows, taken_plainly(rows))}
    got = {r.doc_id: (r["size"], r.source_size, r.target, r.taken) for r in queries.op9_mixing(spark, sf).collect()}
    assert got == {i: (n, total, pytest.approx(goal), c * n) for i, (n, total, goal, c) in want.items()}


def test_mixing_does_not_depend_on_its_groups(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    a = sorted(map(tuple, mixing.mix_report(docs).collect()))
    monkeypatch.setattr(mixing, "GROUP", 9)
    assert sorted(map(tuple, mixing.mix_report(docs).collect())) == a


def test_pipeline_equals_a_plain_version(spark, sf, tok):
    src = [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()]
    labels = spark.read.parquet(f"{sf}/labels.parquet").collect()
    lab = lambda c: {r.doc_id: r[c] for r in labels}
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = src
    for label, cut in (("quality", 0.3), ("toxic", 0.5)):
        s = scored_plainly([(i, t) for i, t, _ in kept], lab(label), label, cut)
        kept = [r for r, x in zip(kept, s) if (x >= cut if label == "quality" else x < cut)]
    f = [fingerprint(t) for _, t, _ in kept]
    g = groups(len(f), lambda i, j: (f[i] ^ f[j]).bit_count() <= 3)
    kept = [r for n, r in enumerate(kept) if g[n] == n]
    sizes = [(i, s, len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))) for i, t, s in kept]
    mixed = Counter({i: c for (i, _, _), (_, _, c) in zip(sizes, taken_plainly(sizes)) if c})
    stages = dict(corpus_pipeline.STAGES)
    for name in ("quality", "toxicity", "simhash"):
        docs = stages[name](spark, docs, sf)
    assert sorted(r.doc_id for r in docs.collect()) == [i for i, _, _ in kept]
    rows = corpus_pipeline.run(spark, sf).collect()
    text = {i: t for i, t, _ in src}
    assert Counter(r.doc_id for r in rows if r.start == 0) == mixed
    lengths = defaultdict(int)
    for r in rows:
        want = ids(tok, text[r.doc_id]) + [2]
        assert r.doc_tokens == len(want) and r.ids_crc32 == zlib.crc32(np.array(want[r.start:r.start + r.length], "<u4").tobytes())
        lengths[r.sequence_id] += r.length
    n = sum(c * (len(ids(tok, text[i])) + 1) for i, c in mixed.items())
    assert sum(lengths.values()) == n and sorted(lengths) == list(range(-(-n // 4096))) and all(lengths[s] == 4096 for s in range(n // 4096))


def test_pipeline_of_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where(F.lit(False))
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0
