"""Column builders that turn text into terms."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def tokenize(text, shortest: int = 3) -> Column:
    """Lower-cased runs of at least ``shortest`` letters; null gives an empty array."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("(\\p{L}{%d,})" % shortest))


def drop_sequences(terms) -> Column:
    """Without terms that look like nucleotide sequences."""
    return F.filter(terms, lambda t: ~t.rlike("^[acgt]{6,}$"))


def drop_stopwords(terms, stop: list[str]) -> Column:
    return F.filter(terms, lambda t: ~t.isin(stop)) if stop else terms


def stop_words(languages: tuple[str, ...] = ("english", "french", "german", "spanish")) -> list[str]:
    """Spark's own lists of stop words; a few hundred words."""
    from pyspark.ml.feature import StopWordsRemover

    return sorted({w for x in languages for w in StopWordsRemover.loadDefaultStopWords(x)})


def light_stem(term) -> Column:
    """A short suffix rule for plural and participle endings; words of under five letters stay."""
    cut = F.regexp_replace(F.regexp_replace(term, "(ing|edly|ed)$", ""), "(ies|es|s)$", "")
    return F.when(F.length(cut) >= 3, F.when(F.length(term) >= 5, cut).otherwise(term)).otherwise(term)


def strip_html(html) -> Column:
    """Page text without scripts, styles and tags."""
    bare = F.regexp_replace(F.coalesce(html, F.lit("")), "(?is)<(script|style)\\b.*?</(script|style)>", " ")
    return F.regexp_replace(bare, "<[^>]*>", " ")


def tf(df: DataFrame, obj: str, terms: Column) -> DataFrame:
    """(obj, term, val): how often each object holds each term."""
    return df.select(F.col(obj).cast("long").alias("obj"), F.explode(terms).alias("term")).groupBy("obj", "term").agg(F.count(F.lit(1)).cast("double").alias("val"))


def term_profiles(df: DataFrame, obj: str, terms: Column) -> DataFrame:
    """(obj, feats, vals) of objects with a term: hashes of the terms in ascending order and how often each is held; a row is one object, nothing is shuffled."""

    def counted(batches):
        for batch in batches:
            batch = batch.filter(pa.array(batch.column("hashes").value_lengths().to_numpy(zero_copy_only=False) > 0))  # a filter in the plan would read the terms twice
            hashes = batch.column("hashes")
            n = hashes.value_lengths().to_numpy(zero_copy_only=False)
            flat = hashes.flatten().to_numpy(zero_copy_only=False)
            who = np.repeat(np.arange(len(n)), n)
            new = np.flatnonzero(np.r_[True, (flat[1:] != flat[:-1]) | (who[1:] != who[:-1])][:len(flat)])
            starts = pa.array(np.searchsorted(who[new], np.arange(len(n) + 1)).astype("int32"))
            times = np.diff(np.r_[new, len(flat)]).astype("float64")
            yield pa.RecordBatch.from_arrays([batch.column("obj"), pa.ListArray.from_arrays(starts, pa.array(flat[new])), pa.ListArray.from_arrays(starts, pa.array(times))], names=["obj", "feats", "vals"])

    hashes = F.sort_array(F.transform(terms, lambda t: F.xxhash64(t)))
    x = df.select(F.col(obj).cast("long").alias("obj"), hashes.alias("hashes")).where("obj IS NOT NULL")
    return x.mapInArrow(counted, "obj long, feats array<bigint>, vals array<double>")


def tf_idf(counts: DataFrame, n_objects: int) -> DataFrame:
    """(obj, term, val): counts weighed by the logarithm of the inverse share of objects with the term."""
    df = counts.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    return counts.join(df, "term").select("obj", "term", (F.col("val") * F.log(F.lit(float(n_objects)) / F.col("df"))).alias("val"))


def most_common(counts: DataFrame, n: int) -> DataFrame:
    """(term, df, place) of the n terms in most objects, ties by term."""
    df = counts.groupBy("term").agg(F.count(F.lit(1)).alias("df")).orderBy(F.desc("df"), "term").limit(n)
    return df.withColumn("place", F.row_number().over(Window.orderBy(F.desc("df"), "term")))
