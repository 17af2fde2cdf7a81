"""Document fingerprints by winnowing, and texts beside their successor in document order."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Any common passage of GRAM + WINDOW - 1 code points shares a kept gram; none under GRAM does.
GRAM, WINDOW = 12, 16
#: Rows taken from a batch at a time, and bytes of fingerprints after which rows go out: they bound a worker's memory, not the result.
ROWS, YIELD_BYTES = 128, 2 << 20
_MULT = 0x9E3779B97F4A7C15


def rolling_hashes(points: np.ndarray, k: int) -> np.ndarray:
    """32-bit hash of every k-gram of code points; a text shorter than k is one gram; none for an empty one."""
    if not len(points):
        return np.zeros(0, np.uint32)
    k = min(k, len(points))
    p = points.astype(np.uint64) + np.uint64(1)
    n = len(p) - k + 1
    with np.errstate(over="ignore"):
        h = np.zeros(n, np.uint64)
        for i in range(k):  # the polynomial by Horner's rule, all grams at once
            h = h * np.uint64(0x100000001B3) + p[i:i + n]
        h ^= h >> np.uint64(29)
        h = h * np.uint64(_MULT)
    return (h >> np.uint64(32)).astype(np.uint32)


def winnow(text: str, k: int = GRAM, w: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(positions, hashes) kept: the minimum of each window of w grams, the rightmost among equals.

    A sliding minimum by doubling: hash and reversed position share one key, so the
    smallest key is the smallest hash at its rightmost place.
    """
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    h = rolling_hashes(points, k)
    n = len(h)
    if not n:
        return np.zeros(0, np.int64), h
    w = min(w, n)
    key = (h.astype(np.uint64) << np.uint64(32)) | np.uint64(0xFFFFFFFF) - np.arange(n, dtype=np.uint64)
    low, span = key, 1
    while span * 2 <= w:
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    m = n - w + 1
    low = np.minimum(low[:m], low[w - span:w - span + m])
    at = np.int64(0xFFFFFFFF) - (low & np.uint64(0xFFFFFFFF)).astype(np.int64)
    at = at[np.r_[True, at[1:] != at[:-1]]]
    return at, h[at]


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Shared kept hashes over all kept hashes of two fingerprints; two empty ones are alike, one empty is not."""
    a, b = np.unique(a), np.unique(b)
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def written_out(at: np.ndarray, h: np.ndarray) -> str:
    """position:hash in hexadecimal, by position."""
    return " ".join([f"{p:x}:{x:08x}" for p, x in zip(at.tolist(), h.tolist())])


def read_back(fingerprint: str) -> tuple[np.ndarray, np.ndarray]:
    pairs = [x.split(":") for x in fingerprint.split()]
    return np.array([int(p, 16) for p, _ in pairs], np.int64), np.array([int(x, 16) for _, x in pairs], np.uint32)


def fingerprints(docs: DataFrame, k: int = GRAM, w: int = WINDOW) -> DataFrame:
    """doc_id, n_chars, fingerprint of every row; null texts count as empty, whose fingerprint is empty."""

    def make(batches):
        for b in batches:
            texts = b.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([written_out(*winnow(t, k, w)) for t in texts])], ["doc_id", "n_chars", "fingerprint"])

    return docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(make, "doc_id long, n_chars long, fingerprint string")


def edited(text: str, following: str) -> str:
    """The last half of text (rounded down) replaced by as many first code points of the following text, or all it has."""
    half = len(text) // 2
    return text[:len(text) - half] + following[:half]


def with_following(docs: DataFrame, buckets: int | None = None) -> DataFrame:
    """Rows dealt into ranges of descending doc_id, each range ending with a copy of the next row.

    Ranges come from quantiles of doc_id; for each range only its largest id is looked up on
    the driver (one row per range) and its row is copied to the range that precedes it in
    descending order (the first row of all to the last range), so texts move once and no
    window gathers the table.  Null ids sort last; equal ids sort by text.
    Columns: __b (range), __halo (1 for the copy), doc_id, text.
    """
    spark = docs.sparkSession
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    n = buckets or max(8, 4 * int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    cuts = sorted({int(x) for x in base.approxQuantile("doc_id", [i / n for i in range(1, n)], 0.2 / n)}) if n > 1 else []
    place = F.lit(-1)
    if cuts:
        arr = spark.sparkContext.broadcast(np.array(cuts))

        @F.pandas_udf("int")
        def place_of(ids):
            x = ids.fillna(np.iinfo(np.int64).min).to_numpy().astype("int64")
            return pd.Series(np.searchsorted(arr.value, x, side="right").astype("int32"))

        place = F.when(F.col("doc_id").isNull(), F.lit(-1)).otherwise(place_of("doc_id"))
    placed = base.withColumn("__b", place)
    tops = placed.groupBy("__b").agg(F.max("doc_id").alias("top")).collect()
    order = sorted((r["__b"] for r in tops), reverse=True)
    top = {r["__b"]: r["top"] for r in tops}
    before = {b: order[i - 1] for i, b in enumerate(order)}  # its first row is what follows the range before it
    if not order:
        return placed.withColumn("__halo", F.lit(0)).limit(0)
    halo_of = spark.createDataFrame([(b, top[b], before[b]) for b in order], "__hb int, __top long, __to int")
    heads = placed.join(F.broadcast(halo_of), (F.col("__b") == F.col("__hb")) & F.col("doc_id").eqNullSafe(F.col("__top")))
    heads = heads.select(F.col("__to").alias("__b"), F.lit(1).alias("__halo"), "doc_id", "text")
    return placed.select("__b", F.lit(0).alias("__halo"), "doc_id", "text").union(heads)


def edited_fingerprints(docs: DataFrame, k: int = GRAM, w: int = WINDOW, buckets: int | None = None) -> DataFrame:
    """Each document's fingerprint, that of its edited text, and how alike they and the next document are.

    The next document is the one with the next smaller doc_id; after the last comes the
    first.  Null texts are empty; a null doc_id sorts last; equal ids sort by text; a table
    of one row is its own next document; an empty table gives no rows; long texts are
    fingerprinted whole; other columns are ignored.
    """
    rows = with_following(docs, buckets).repartition("__b").sortWithinPartitions("__b", "__halo", F.col("doc_id").desc_nulls_last(), "text")

    def compare(batches):
        names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
        last, ended = None, None

        def row(cur, nxt):
            at, h = cur[2]
            text = edited(cur[1], nxt[1])
            ea, eh = winnow(text, k, w)
            return (cur[0], len(cur[1]), hashlib.sha256(text.encode()).hexdigest(), written_out(at, h), written_out(ea, eh), likeness(h, eh), likeness(h, nxt[2][1]))

        out, size = [], 0

        def packed():
            nonlocal out, size
            cols = list(zip(*out)) if out else [[]] * 7
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            out, size = [], 0
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names)

        for b in batches:
            for at in range(0, b.num_rows, ROWS):
                for bucket, halo, doc, text in zip(*(c.to_pylist() for c in b.slice(at, ROWS).columns)):
                    if halo and ended == bucket:
                        continue  # rows of the same largest id were copied too; the first in order counts
                    cur = (doc, text, winnow(text, k, w))
                    if last is not None:
                        out.append(row(last, cur))
                        size += len(out[-1][3]) + len(out[-1][4])
                        if size >= YIELD_BYTES:
                            yield packed()
                    last = None if halo else cur
                    ended = bucket if halo else None
        if out:
            yield packed()

    return rows.mapInArrow(compare, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
