"""SimHash near-duplicates with pivot distance tables."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, local_components, paired_blocks, written

SHINGLE, SEED, NEAR = 3, 42, 3
PIVOTS, BLOCK = 24, 2048
#: Six blocks of the 64 bits; two fingerprints that differ in 3 bits agree in at least three whole blocks.
_EDGES = [0, 11, 22, 33, 43, 54, 64]
_PIVOT_SEED = 20240607


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit fingerprint of a text's word shingles; 0 where there is no word."""
    words = text.encode().lower().split()  # bytes: only A-Z change and only the six ASCII spaces split
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return digest(b" ".join(words), SEED)
    if shingle == 3:
        grams = [digest(b"%b %b %b" % g, SEED) for g in zip(words, words[1:], words[2:])]
    else:
        grams = [digest(b" ".join(words[i:i + shingle]), SEED) for i in range(len(words) - shingle + 1)]
    h = np.array(grams, "<u8")
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(h), 8192):
        ones += np.unpackbits(h[lo:lo + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long) of every row."""

    def make(batches):
        for b in batches:
            fp = np.array([fingerprint(t, shingle) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp)], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(make, "doc_id long, fp long")


def pivots(n: int = PIVOTS) -> np.ndarray:
    """Reference fingerprints, made from a seed."""
    return np.random.default_rng(_PIVOT_SEED).integers(0, 2**64, n, dtype=np.uint64)


def pivot_table(fp: np.ndarray, refs: np.ndarray) -> np.ndarray:
    """Hamming distance of each fingerprint to each reference, references first."""
    return np.stack([np.bitwise_count(fp ^ p) for p in refs]).astype(np.int8)


def pivot_distances(ids: DataFrame) -> DataFrame:
    """(id, pivots): the distance table, a byte a reference for each fingerprint."""

    def measure(batches):
        for b in batches:
            t = np.ascontiguousarray(pivot_table(b.column(0).to_numpy().view(np.uint64), pivots()).T)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in t], pa.binary())], ["id", "pivots"])

    return ids.mapInArrow(measure, "id long, pivots binary")


def near_pairs(a: np.ndarray, b: np.ndarray, near: int = NEAR, refs: np.ndarray | None = None, tables: tuple | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (i, j) with a[i] and b[j] at most ``near`` bits apart.

    A pair goes as soon as its distances to one reference differ by more than ``near``: by
    the triangle inequality it can't be close.  Survivors are verified bit by bit.
    """
    if tables is None:
        refs = pivots() if refs is None else refs
        tables = pivot_table(a, refs), pivot_table(b, refs)
    ta, tb = tables
    order = np.argsort(tb[0], kind="stable")  # the first coordinate by search, the others by test
    first = tb[0][order]
    lo, hi = np.searchsorted(first, ta[0] - near, "left"), np.searchsorted(first, ta[0] + near, "right")
    out_i, out_j = [], []
    step = max(1, 4_000_000 // max(1, len(b)))
    for s in range(0, len(a), step):
        n = hi[s:s + step] - lo[s:s + step]
        i = np.repeat(np.arange(s, s + len(n)), n)
        j = order[np.repeat(lo[s:s + step] - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())]
        for x, y in zip(ta[1:], tb[1:]):
            if not len(i):
                break
            ok = np.abs(x[i] - y[j]) <= near
            i, j = i[ok], j[ok]
        ok = np.bitwise_count(a[i] ^ b[j]) <= near
        out_i.append(i[ok])
        out_j.append(j[ok])
    return np.concatenate(out_i or [np.zeros(0, int)]), np.concatenate(out_j or [np.zeros(0, int)])


def near_edges(distinct: DataFrame, near: int = NEAR, block: int = BLOCK) -> DataFrame:
    """Edges (u, v) that join exactly what the links of distinct ``fp`` values join, without all pairs of a group.

    Distinct fingerprints meet where three of six blocks agree (no link is lost up to three
    bits).  A unit tests its block of fingerprints through the pivot tables and returns a
    spanning forest, so a group of g near copies gives about g rows and not g squared.
    """
    if near > 3:
        raise ValueError("the blocks are laid out for at most 3 differing bits")
    masks = []
    for chosen in combinations(range(6), 3):
        m = sum(((1 << (_EDGES[c + 1] - _EDGES[c])) - 1) << _EDGES[c] for c in chosen)
        masks.append(m - (1 << 64) if m >= 1 << 63 else m)
    keyed = distinct.select(F.explode(F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for i, m in enumerate(masks)])).alias("x"), F.col("fp").alias("id")).select("x.t", "x.key", "id")
    crowded = keyed.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("t", "key")
    keyed = written(keyed.join(crowded, ["t", "key"]), "keys")
    # each fingerprint's distances to the references, computed once however many keys it has
    keyed = keyed.join(pivot_distances(keyed.select("id").distinct()), "id").select("t", "key", "id", "pivots")

    def unpacked(part):
        return part["id"].to_numpy().view(np.uint64), np.frombuffer(b"".join(part["pivots"]), np.int8).reshape(len(part), -1).T

    def kernel(cache, part):
        if "fp" not in cache:
            cache["fp"], cache["table"] = unpacked(cache["homes"])
        h = cache["fp"]
        p, table = unpacked(part)
        i, j = near_pairs(p, h, near, tables=(table, cache["table"]))
        ok = p[i] != h[j]
        i, j = i[ok], j[ok]
        if not len(i):
            return None
        nodes, at = np.unique(np.r_[p[i], h[j]].view(np.int64), return_inverse=True)
        root = local_components(at[:len(i)], at[len(i):], len(nodes))
        ok = root != np.arange(len(nodes))
        return pd.DataFrame({"u": nodes[ok], "v": nodes[root[ok]]})

    return paired_blocks(keyed, keyed, ["t", "key"], kernel, "u long, v long", block)


def classes(slim: DataFrame, near: int = NEAR) -> DataFrame:
    """(fp, component_id, rep_fp) of slim(doc_id, fp): the smallest doc_id of each fingerprint's component, and the fingerprint it sits at."""
    per = written(slim.groupBy("fp").agg(F.min("doc_id").alias("rep")), "fps")
    comps = components(near_edges(per.select("fp"), near))
    rooted = per.join(comps, per["fp"] == comps["node"], "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    ends = rooted.groupBy("root").agg(F.min(F.struct(F.col("rep").isNull().alias("no"), "rep", "fp")).alias("m"))
    return rooted.join(ends, "root").select("fp", F.col("m.rep").alias("component_id"), F.col("m.fp").alias("rep_fp"))


def near_duplicates(docs: DataFrame, near: int = NEAR) -> DataFrame:
    """doc_id, fingerprint, component_id for every row.

    Null texts are empty; texts without words have fingerprint zero and are linked like any
    other; a null doc_id belongs to its component without naming it; repeated rows keep
    their rows; an empty table gives none; long texts are hashed whole; other columns are
    ignored.
    """
    slim = written(fingerprints(docs), "simhash")
    found = classes(slim, near).select("fp", "component_id")
    return slim.join(found, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, near: int = NEAR) -> DataFrame:
    """docs with one row of each near-duplicate group: that of the smallest doc_id.

    Null texts count as texts without words, which form one group; a group of null ids only
    keeps one of its rows; of rows with the same id and fingerprint one stays; other columns
    travel along; an empty table gives no rows.
    """
    cols = docs.columns
    slim = written(fingerprints(docs), "simhash")
    found = classes(slim, near)
    kept = slim.join(found, "fp").where("fp = rep_fp AND doc_id <=> component_id").select(F.col("doc_id").alias("__id")).distinct()
    chosen = docs.join(kept, docs["doc_id"].cast("long").eqNullSafe(kept["__id"]), "left_semi")

    # Equal ids with other texts: only the row whose fingerprint is the group's stays, once.
    again = slim.groupBy("doc_id").count().where("count > 1").limit(1).count()
    if not again:
        return chosen.select(*cols)
    pairs = slim.join(found, "fp").where("fp = rep_fp AND doc_id <=> component_id").select(F.col("doc_id").alias("__id"), F.col("fp").alias("__fp")).distinct()
    mark = F.pandas_udf(lambda t: pd.Series(np.array([fingerprint(x or "") for x in t], np.uint64).view(np.int64)), "long")
    marked = chosen.withColumn("__fp2", mark("text"))
    both = marked.join(pairs, marked["doc_id"].cast("long").eqNullSafe(pairs["__id"]) & (marked["__fp2"] == pairs["__fp"]), "left_semi")
    return both.dropDuplicates(["doc_id", "__fp2"]).select(*cols)
