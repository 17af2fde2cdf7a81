"""The ten contract queries against plain versions, on the small tables and on hard rows."""

import hashlib
import re
import zlib
from itertools import combinations

import duckdb
import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from waypath.llm import embed_dedup, mixing, packing, queries, simhash, token_counts, winnowing

HARD = [(1, None), (2, ""), (3, "one"), (4, "a b c d"), (5, "a b c d"), (6, "A  B\tC d"), (7, "word " * 6000), (8, "naïve   café <|endoftext|> 中文")]


@pytest.fixture(scope="module")
def tok():
    return Tokenizer.from_file(str(public_tokenizers.path("word_bpe_49k.json")))


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame([(i, t, "en", f"s{i % 2}" if i > 2 else None, 0) for i, t in HARD], "doc_id long, text string, lang string, source string, n_chars long")


def ids(tok, text):
    return tok.encode(text or "", add_special_tokens=False).ids


def groups(n, linked):
    """Smallest index reachable, by plain union."""
    up = list(range(n))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i
    for i, j in combinations(range(n), 2):
        if linked(i, j):
            a, b = sorted((top(i), top(j)))
            up[b] = a
    return [top(i) for i in range(n)]


def texts(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.mark.parametrize("name", ["op1_toxicity", "op6_quality"])
def test_scores(spark, sf, name):
    rows = queries.queries()[name](spark, sf).collect()
    cut, label = (0.5, "toxic") if name == "op1_toxicity" else (0.3, "quality")
    assert {r.doc_id for r in rows} == set(texts(spark, sf))
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= cut) and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    want = {r.doc_id: r[label] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    held = [(r.score, want[r.doc_id]) for r in rows if r.held_out and want.get(r.doc_id) is not None]
    good, bad = [s for s, y in held if y == 1], [s for s, y in held if y == 0]
    if good and bad:
        assert np.mean([(g > b) + 0.5 * (g == b) for g in good for b in bad]) > 0.8


def test_packing_tiles_every_id(spark, hard, tok):
    rows = packing.pack(hard).collect()
    for i, t in HARD:
        mine = sorted((r for r in rows if r.doc_id == i), key=lambda r: r.start)
        want, at = ids(tok, t) + [2], 0
        for r in mine:
            assert r.start == at and r.doc_tokens == len(want) and r.ids_crc32 == zlib.crc32(np.array(want[at:at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(want)
    for s in {r.sequence_id for r in rows}:
        at = 0
        for r in sorted((r for r in rows if r.sequence_id == s), key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 4096


def test_token_counts(hard, tok):
    got = {r.doc_id: (r.n_bytes, r.n_tokens, r.over_limit) for r in token_counts.token_counts(hard).collect()}
    want = {i: (len((t or "").encode()), len(ids(tok, t)), len(ids(tok, t)) > 2048) for i, t in HARD}
    assert got == want


def test_id_files_read_back(spark, sf, tok):
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in queries.op7_id_output(spark, sf).collect()}
    at = 0
    for i, t in sorted(texts(spark, sf).items()):
        x = np.array(ids(tok, t) + [2], "<u4")
        assert got.pop(i) == (at, len(x), zlib.crc32(x.tobytes()))
        at += len(x)
    assert not got


def test_winnowing(hard):
    rows = {r.doc_id: r for r in winnowing.edited_fingerprints(hard).collect()}
    order = sorted(rows, reverse=True)
    text = {i: t or "" for i, t in HARD}
    for n, i in enumerate(order):
        nxt = text[order[(n + 1) % len(order)]]
        k = len(text[i]) // 2
        edited = text[i][:len(text[i]) - k] + nxt[:k]
        assert rows[i].n_chars == len(text[i]) and rows[i].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert 0 <= rows[i].near_edited <= 1 and 0 <= rows[i].near_next <= 1
    assert rows[4].fingerprint == rows[5].fingerprint


def fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    sh = [words] if 0 < len(words) < 3 else [words[i:i + 3] for i in range(len(words) - 2)]
    h = [xxhash.xxh64_intdigest(" ".join(s), seed=42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def check_simhash(rows, text):
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in rows}
    order = sorted(text)
    f = [fingerprint(text[i]) for i in order]
    g = groups(len(f), lambda i, j: (f[i] ^ f[j]).bit_count() <= 3)
    assert got == {i: (f"{f[n]:016x}", order[g[n]]) for n, i in enumerate(order)}


def test_simhash(spark, sf, hard):
    check_simhash(simhash.near_duplicates(hard).collect(), dict(HARD))
    check_simhash(queries.op10_simhash(spark, sf).collect(), texts(spark, sf))


def test_vectors(spark, sf):
    src = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    src = sorted(src, key=lambda r: r.vec_id)
    x = [np.array(r.embedding, float) if r.embedding is not None else None for r in src]
    ok = [v is not None and np.isfinite(v).all() and (v != 0).any() for v in x]
    near = lambda i, j: ok[i] and ok[j] and src[i].label is not None and src[i].label == src[j].label and x[i] @ x[j] / np.sqrt((x[i] @ x[i]) * (x[j] @ x[j])) >= 0.93
    links = {(i, j) for i, j in combinations(range(len(src)), 2) if near(i, j)}
    g = groups(len(src), lambda i, j: (i, j) in links)
    n = [sum(i in p for p in links) for i in range(len(src))]
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in queries.op8_embedding_dedup(spark, sf).collect()}
    assert got == {r.vec_id: (n[i], src[g[i]].vec_id, g[i] == i) for i, r in enumerate(src)}


def test_odd_vectors(spark):
    rows = [(1, [1.0, 0.0], 1), (2, [2.0, 0.0], 1), (3, None, 1), (4, [0.0, 0.0], 1), (5, [float("nan"), 1.0], 1), (6, [1.0, 0.0], None), (7, [1.0, 0.0], 2), (8, [1.0, None], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: (r.n_links, r.component_id) for r in embed_dedup.near_vectors(df).collect()}
    assert got == {1: (1, 1), 2: (1, 1)} | {i: (0, i) for i in range(3, 9)}


def test_mixing(hard):
    rows = mixing.mix_report(hard).collect()
    size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t in HARD}
    assert {r.doc_id: r["size"] for r in rows} == size
    assert all(0 <= r.taken <= 2 * r["size"] for r in rows)
    assert sorted(map(tuple, rows)) == sorted(map(tuple, mixing.mix_report(hard).collect()))


def test_pages(spark, sf):
    rows = queries.op5_html_extraction(spark, sf).collect()
    assert len(rows) == spark.read.parquet(f"{sf}/pages.parquet").count()
    assert all(r.n_chars == len(r.text) and "\t" not in r.text and "  " not in r.text for r in rows)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    df = queries.queries()[name](spark, sf)
    cur = con.execute(queries.oracle_sql()[name])
    cols = [d[0] for d in cur.description]
    assert sorted(cols) == sorted(df.columns)
    show = lambda r: tuple(f"{v:.6f}" if isinstance(v, float) else str(v) for v in r)
    assert sorted(map(show, df.select(*cols).collect())) == sorted(map(show, cur.fetchall()))


def test_empty_tables(hard):
    none = hard.limit(0)
    for f in (packing.pack, token_counts.token_counts, simhash.near_duplicates, mixing.mix_report, winnowing.edited_fingerprints):
        assert f(none).count() == 0
