"""Toxicity scores: boosted trees over dense features of learned lexicons, calibrated isotonically."""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, labelled_sample, written
from .learn import Isotonic, Trees

#: At most about this many labelled rows are fitted on (a documented bound).
SAMPLE, CUT, FOLDS = 12_000, 0.5, 3
#: Lexicon: entries kept, least toxic documents of an entry, least log-odds; stems are word beginnings.
ENTRIES, LEAST, ODDS, STEMS = 4000, 3, 2.2, (4, 5, 6)
NAMES = ["hits", "rate", "best", "top3", "kinds", "stem_hits", "stem_rate", "stem_best", "stem_top3", "stem_kinds", "you", "you_near", "caps", "caps_words", "bangs", "quests", "marks", "mixed", "plain_hits", "log_words", "hit_caps"]
# ---- fixed values: second persons of four languages, and letters written as signs
YOU = frozenset("you your yours yourself u ur tu te toi ton ta tes vous votre vos du dich dir dein deine deinen ihr euch euer sie ihnen tú ti tuyo vosotros usted ustedes vuestro".split())
LEET = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i", "*": "", "-": "", ".": "", "_": ""})
# ----
_WORD = re.compile(r"[^\W\d_]+")
_MIXED = re.compile(r"(?<![^\W\d_])[^\W\d_]+[0-9@$*!._-]+[^\W\d_]+")
_UPPER = re.compile(r"[A-ZÀ-ÖØ-Þ]")


def entries_of(words: set[str]) -> set[str]:
    """Whole words and word beginnings (marked ^) a lexicon may hold."""
    out = set(words)
    for k in STEMS:
        out.update(["^" + w[:k] for w in words if len(w) >= k])
    return out


def features(text: str, lexicon: dict[str, float]) -> list[float]:
    """Densities, second-person proximity, capitals, punctuation and obfuscation of one text."""
    words = _WORD.findall(text)
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    low = [w.lower() for w in words]
    distinct = set(low)
    found = lexicon.keys() & distinct
    stems: dict[str, float] = {}
    for k in STEMS:
        own = lexicon.keys() & {"^" + w[:k] for w in distinct if len(w) >= k}
        for s in own:
            stems[s] = lexicon[s]
    chars = len(text)
    bad = set(found)
    if stems:
        heads = {s[1:] for s in stems}
        stemmed = {w for w in distinct if any(w[:k] in heads for k in STEMS)}
    else:
        stemmed = set()
    near = hits = stem_hits = hit_caps = 0
    if bad or stemmed:
        at = [i for i, w in enumerate(low) if w in bad or w in stemmed]
        hits = sum([low[i] in bad for i in at])
        stem_hits = sum([low[i] in stemmed for i in at])
        hit_caps = sum([words[i].isupper() for i in at])
        persons = np.array([i for i, w in enumerate(low) if w in YOU])
        if len(persons):
            pos = np.array(at)
            k = np.searchsorted(persons, pos)
            d = np.minimum(np.abs(pos - persons[np.clip(k, 0, len(persons) - 1)]), np.abs(pos - persons[np.clip(k - 1, 0, len(persons) - 1)]))
            near = int((d <= 6).sum())
    mixed = _MIXED.findall(text)
    plain = sum([m.lower().translate(LEET) in lexicon for m in mixed])
    odds = sorted([lexicon[w] for w in found], reverse=True)
    sodds = sorted(stems.values(), reverse=True)
    return [
        hits, 100 * hits / n, odds[0] if odds else 0, sum(odds[:3]), len(odds), stem_hits, 100 * stem_hits / n, sodds[0] if sodds else 0, sum(sodds[:3]), len(sodds),
        100 * len([1 for w in low if w in YOU]) / n, near, len(_UPPER.findall(text)) / max(1, chars), sum([len(w) > 1 and w.isupper() for w in words]) / n,
        100 * text.count("!") / chars, 100 * text.count("?") / chars, 100 * sum(map(text.count, "#$%&*")) / chars, 100 * len(mixed) / n, plain, math.log1p(n), hit_caps,
    ]


def fold_of(doc_id) -> int:
    return (int(doc_id) * 2654435761 >> 7) % FOLDS


def mined(sample: DataFrame) -> list[dict[str, float]]:
    """Lexicons from (doc_id, text, y): one without each fold, and last one from all rows.

    Entries are counted by document and summed in Spark; only those with support reach the driver.
    """

    def count(batches):
        got: dict[str, list[int]] = defaultdict(lambda: [0] * (2 * FOLDS))
        for b in batches:
            for doc, text, y in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), b.column("y").to_pylist()):
                slot = 2 * fold_of(doc) + y
                for e in entries_of(set(_WORD.findall(text.lower()))):
                    got[e][slot] += 1
        keys = list(got)
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), *[pa.array([got[k][i] for k in keys], pa.int64()) for i in range(2 * FOLDS)]], ["entry", *[f"c{i}" for i in range(2 * FOLDS)]])

    cols = [f"c{i}" for i in range(2 * FOLDS)]
    per = sample.select("doc_id", "text", "y").mapInArrow(count, "entry string, " + ", ".join(f"{c} long" for c in cols))
    toxic = sum(F.col(f"c{2 * f + 1}") for f in range(FOLDS))
    clean = sum(F.col(f"c{2 * f}") for f in range(FOLDS))
    both = per.groupBy("entry").agg(*[F.sum(c).alias(c) for c in cols]).where((toxic >= LEAST) & (clean <= toxic))
    rows = both.orderBy(F.desc(toxic - clean), "entry").limit(4 * ENTRIES).collect()
    size = sample.groupBy("doc_id", "y").count().select("doc_id", "y").collect()
    have = Counter((fold_of(r["doc_id"]), r["y"]) for r in size)
    out = []
    for left in [*range(FOLDS), None]:
        use = [f for f in range(FOLDS) if f != left]
        p, q = sum(have[f, 1] for f in use), sum(have[f, 0] for f in use)
        lex = []
        for r in rows:
            t, c = sum(r[2 + 2 * f] for f in use), sum(r[1 + 2 * f] for f in use)
            odds = math.log((t + 0.5) / (p + 1)) - math.log((c + 0.5) / (q + 1))
            if t >= max(2, LEAST - (left is not None)) and odds >= ODDS:
                lex.append((-(t - c), r["entry"], odds))
        out.append({e: o for _, e, o in sorted(lex)[:ENTRIES]})
    return out


class ToxicityModel:
    def __init__(self, cut: float = CUT):
        self.cut = cut

    def fit(self, x: np.ndarray, y: np.ndarray, fold: np.ndarray, lexicon: dict[str, float]) -> "ToxicityModel":
        """x of each row was made with the lexicon that has not seen it; calibration uses trees that have not either."""
        self.lexicon = lexicon
        out = np.zeros(len(x))
        for f in range(FOLDS):
            own, rest = fold == f, fold != f
            if own.any():
                out[own] = Trees().fit(x[rest], y[rest]).raw(x[own]) if rest.any() else 0.0
        self.trees = Trees().fit(x, y)
        self.steps = Isotonic().fit(out, y)
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.clip(self.steps(self.trees.raw(x)), 0.0, 1.0) if len(x) else np.zeros(0)


def trained(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> ToxicityModel:
    sample = written(labelled_sample(docs, labels, "toxic", bound).select(F.col("doc_id").cast("long").alias("doc_id"), "text", "y"), "toxic")
    lexicons = mined(sample)
    known = docs.sparkSession.sparkContext.broadcast(lexicons)

    def run(batches):
        for b in batches:
            ids = b.column(0).to_pylist()
            x = [features(t, known.value[fold_of(d)]) for d, t in zip(ids, b.column(1).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(x, pa.list_(pa.float64()))], ["doc_id", "y", "x"])

    rows = sample.select("doc_id", "text", "y").mapInArrow(run, "doc_id long, y int, x array<double>").collect()
    rows.sort(key=lambda r: (r["doc_id"], r["y"], r["x"]))
    x, y = np.array([r["x"] for r in rows]).reshape(-1, len(NAMES)), np.array([r["y"] for r in rows], int)
    return ToxicityModel().fit(x, y, np.array([fold_of(r["doc_id"]) for r in rows], int), lexicons[-1])


def scored(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, held_out, score, predicted for every row.

    Null texts count as empty and get the score of the empty feature row; null ids are held
    out; repeated rows get equal scores; other columns are ignored; empty tables give none;
    with no labels every score is the same.
    """
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = known.value
        for b in batches:
            x = np.array([features(t, m.lexicon) for t in b.column(2).to_pylist()]).reshape(-1, len(NAMES))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(m.score(x), pa.float64())], ["doc_id", "held_out", "score"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "doc_id long, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= model.cut).cast("int"))


def keep_clean(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> DataFrame:
    """docs without the rows found toxic; columns, repeats and row contents unchanged.

    Null texts are scored as empty ones; without labels of both kinds no row is called
    toxic unless all labelled ones are; an empty table stays empty.
    """
    model = trained(docs, labels, bound)
    known = docs.sparkSession.sparkContext.broadcast(model)
    @F.pandas_udf("double")
    def score(texts):
        m = known.value
        x = np.array([features(t or "", m.lexicon) for t in texts]).reshape(-1, len(NAMES))
        return pd.Series(m.score(x))

    return docs.where(score("text") < model.cut)
