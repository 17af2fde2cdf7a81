"""Quality scores learned from preference pairs (Bradley-Terry)."""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, labelled_sample
from .learn import BradleyTerry, sigmoid

#: At most about this many labelled rows are fitted on (a documented bound; everything else sees all rows).
SAMPLE, CUT = 12_000, 0.3
NAMES = ["log_words", "word_len", "distinct", "top_share", "repeat_next", "dup_lines", "caps", "caps_lines", "caps_words", "marks", "mark_lines", "mark_words", "pipes", "pipe_lines", "bangs", "bang_words", "digits", "letters", "short_lines", "no_stop", "line_rep", "log_lines", "bare_lines", "max_run", "bad_lines"]
_MARKS = re.compile(r"[#$%&*^~_=<>\\|@{}\[\]]")
_MARK_RUN = re.compile(r"([^\w\s])\1\1")
_UPPER = re.compile(r"[A-ZÀ-ÖØ-Þ]")
_DIGIT = re.compile(r"\d")
_LETTER = re.compile(r"[^\W\d_]")


def features(text: str) -> list[float]:
    """Counts of form only: no words, language, source or id.  An empty text gives zeros."""
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    chars = len(text)
    low = [w.lower() for w in words]
    counts = Counter(low)
    top = counts.most_common(1)[0][1]
    upper, letters = len(_UPPER.findall(text)), max(1, len(_LETTER.findall(text)))
    marks, runs = len(_MARKS.findall(text)), len(_MARK_RUN.findall(text))
    pipes, bangs = text.count("|"), text.count("!!")
    repeat = sum([a == b for a, b in zip(low, low[1:])])
    caps_words = sum([len(w) > 1 and w.isupper() for w in words])
    lines = [x for x in text.split("\n") if x.strip()]
    caps_l = mark_l = pipe_l = bare_l = short = bad_l = 0
    for x in lines:
        k = len(x)
        up = len(_UPPER.findall(x))
        c, p = up > 0.5 * k, x.count("|") * 12 > k
        m = len(_MARK_RUN.findall(x)) * 14 > k
        caps_l += k * c
        pipe_l += k * p
        mark_l += k * m
        bad_l += k * (c or p or m)
        bare_l += k * (x.rstrip()[-1] not in ".!?:;\"'”»)")
        short += k < 40
    run = best = 1
    for a, b in zip(low, low[1:]):
        run = run + 1 if a == b else 1
        if run > best:
            best = run
    distinct_lines = len(set(lines))
    return [
        math.log1p(n), sum(map(len, words)) / n, len(counts) / n**0.8, top / n, repeat / n, 1 - distinct_lines / len(lines),
        upper / letters, caps_l / chars, caps_words / n, math.log1p(100 * marks / chars), mark_l / chars, min(1.0, runs / n),
        min(1.0, pipes / n), pipe_l / chars, min(1.0, bangs / n), math.log1p(100 * bangs / n), len(_DIGIT.findall(text)) / chars,
        letters / chars, short / len(lines), sum([c for w, c in counts.items() if len(w) <= 3]) / n, math.log(len(lines) / distinct_lines), math.log1p(len(lines)),
        bare_l / chars, math.log1p(best - 1), bad_l / chars,
    ]


def expanded(x: np.ndarray) -> np.ndarray:
    """The features with their square roots' sizes, so a straight strength can bend."""
    return np.hstack([x, np.sqrt(np.abs(x)), (np.abs(x) > 0.02).astype(float)])


def _sample(docs, labels, bound):
    from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructField, StructType

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("y"), pa.array([features(t) for t in b.column("text").to_pylist()], pa.list_(pa.float64()))], ["doc_id", "y", "x"])

    schema = StructType([StructField("doc_id", LongType()), StructField("y", IntegerType()), StructField("x", ArrayType(DoubleType()))])
    rows = labelled_sample(docs, labels, "quality", bound).select(F.col("doc_id").cast("long").alias("doc_id"), "y", "text").mapInArrow(run, schema).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["y"], r["x"]))
    return np.array([r["x"] for r in rows]).reshape(-1, len(NAMES)), np.array([r["y"] for r in rows], int)


class QualityModel:
    """Strengths from pairs; the cut is the score quantile at the share of bad rows in the sample."""

    def __init__(self, cut: float = CUT):
        self.cut = cut

    def fit(self, x: np.ndarray, y: np.ndarray) -> "QualityModel":
        self.rank = BradleyTerry().fit(expanded(x), y)
        s = self.rank.strength(expanded(x))
        bad = float(np.mean(y == 0)) if len(y) else 0.0
        if 0 < bad < 1:
            # between the strengths on both sides of the quantile that the share of bad rows names
            ordered = np.sort(s)
            k = min(max(1, round(bad * len(s))), len(s) - 1)
            self.at = float((ordered[k - 1] + ordered[k]) / 2)
            self.spread = float(max(1e-6, (np.median(s[y == 1]) - np.median(s[y == 0])) / 8))
        else:
            self.at, self.spread = (-1.0 if bad == 0 else 1.0), 1.0
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        """0 to 1; the quantile maps to the cut."""
        if not len(x):
            return np.zeros(0)
        s = self.rank.strength(expanded(x))
        return sigmoid((s - self.at) / self.spread + math.log(self.cut / (1 - self.cut)))


def trained(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> QualityModel:
    return QualityModel().fit(*_sample(docs, labels, bound))


def scored(docs: DataFrame, model: QualityModel, id_col: str = "doc_id") -> DataFrame:
    """doc_id, held_out, score, predicted for every row.

    Null texts count as empty and get the score of the empty feature row; null ids are held
    out; repeated rows get equal scores; other columns are ignored; empty tables give none.
    """
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            x = np.array([features(t) for t in b.column(2).to_pylist()]).reshape(-1, len(NAMES))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(known.value.score(x), pa.float64())], ["doc_id", "held_out", "score"])

    out = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "doc_id long, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= model.cut).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> DataFrame:
    """docs without the rows the classifier rejects; columns, repeats and row contents unchanged.

    Null texts are scored as empty ones; with no labels, or labels of one kind, the score
    says what that kind is (all rows stay where no row is labelled); an empty table stays empty.
    """
    model = trained(docs, labels, bound)
    known = docs.sparkSession.sparkContext.broadcast(model)
    @F.pandas_udf("double")
    def score(texts):
        x = np.array([features(t or "") for t in texts]).reshape(-1, len(NAMES))
        return pd.Series(known.value.score(x))

    return docs.where(score("text") >= model.cut)
