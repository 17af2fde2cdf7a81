"""Near-duplicate vectors by randomised-rotation binary codes with stored correction factors."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, local_components, paired_blocks, written

LEAST = 0.93
#: Width of the bound in standard errors of the estimate; at 6 a true link is missed with a chance of some 1e-9.
CONFIDENCE, BLOCK = 6.0, 2048
#: Centres are taken from at most this many vectors; a centre for about so many distinct vectors.
CENTRES, PER_CENTRE = 512, 20_000
_SEED = 1234567


def rotation(d: int, seed: int = _SEED) -> np.ndarray:
    """A random orthogonal matrix."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, d)))
    return q * np.sign(np.diag(r))


def codes(unit: np.ndarray, rot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sign bits of the rotated unit vectors (packed), and each one's factor: the inner product with its own code."""
    z = unit @ rot.T
    bits = np.packbits(z > 0, axis=1)
    return bits, np.abs(z).sum(1) / math.sqrt(unit.shape[1])


def estimate(query_rot: np.ndarray, bits: np.ndarray, factor: np.ndarray, confidence: float = CONFIDENCE) -> tuple[np.ndarray, np.ndarray]:
    """Unbiased estimates of <query, vector> from the vectors' codes, and the half-width of their bound.

    With code c (entries +-1/sqrt(d)) and stored factor f = <c, x>, <c, q> / f has
    expectation <x, q> under a random rotation; its error is of size
    sqrt((1 - f^2) / f^2 / (d - 1)).
    """
    d = query_rot.shape[1]
    signs = np.unpackbits(bits, axis=1, count=d).astype(np.float32) * 2 - 1
    raw = query_rot.astype(np.float32) @ signs.T / math.sqrt(d)
    half = confidence * np.sqrt(np.maximum(0.0, 1 - factor**2) / factor**2 / max(1, d - 1))
    return raw / factor.astype(np.float32), half


def unit_rows(vectors) -> np.ndarray:
    x = np.stack([np.asarray(v, np.float64) for v in vectors])
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def usable(vector, label):
    ok = F.col(label).isNotNull() & F.col(vector).isNotNull() & (F.size(vector) > 0)
    finite = ~F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return F.coalesce(ok & finite & F.exists(vector, lambda x: x != 0), F.lit(False))


def near_vectors(vectors: DataFrame, least: float = LEAST, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", block: int = BLOCK) -> DataFrame:
    """vec_id, n_links, component_id, kept for every vector.

    Vectors of equal non-null labels (and lengths) link at a cosine of ``least`` or more in
    double precision.  Null or zero vectors and those with null or non-finite components
    link with nothing.  Equal vectors are one row until the end, so a group of copies costs
    one.  Every distinct vector lives at its nearest centre and also visits each centre where
    a vector it links with could live: if y is nearest to c and |x - y| <= r, then
    <x, c> >= <x, c'> - r |c - c'| for every centre c', so no link is lost.  Codes then decide
    which pairs are computed exactly.  Repeated ids, other columns and empty tables are fine;
    every null id is a row of its own without links to it by name.
    """
    spark = vectors.sparkSession
    held = dict(vectors.dtypes)[vector]
    held = held if held == "array<float>" else "array<double>"  # single precision travels as it is; sums are in double
    base = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).cast(held).alias("e"), F.col(label).alias("label"))
    base = base.withColumn("ok", usable("e", "label"))
    groups = written(base.where("ok").groupBy("label", "e").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("w")).withColumn("id", F.xxhash64("label", "e")), "vectors")
    n = groups.count()
    centres = spark.sparkContext.broadcast(_centres(groups, n))
    radius = math.sqrt(max(0.0, 2 - 2 * least)) + 1e-9

    def place(batches):
        for pdf in batches:
            for d, part in pdf.groupby(pdf["e"].map(len), sort=True):
                c, gap = centres.value[d]
                x = unit_rows(part["e"])
                dot = x @ c.T
                home = dot.argmax(1)
                near = dot >= dot[np.arange(len(x)), home][:, None] - radius * gap[home] - 1e-9
                i, j = np.nonzero(near)
                own = j == home[i]
                out = part.iloc[i].reset_index(drop=True)
                yield pd.DataFrame({"dim": d, "cell": j.astype("int32"), "label": out["label"], "own": own, "id": out["id"], "rep": out["rep"], "w": out["w"], "e": out["e"]})

    kind = dict(groups.dtypes)["label"]
    placed = written(groups.select("label", "id", "rep", "w", "e").mapInPandas(place, f"dim int, cell int, label {kind}, own boolean, id long, rep long, w long, e {held}"), "cells")
    keys = ["label", "dim", "cell"]
    homes = placed.where("own").drop("own")
    probers = placed.drop("own")

    def kernel(cache, part):
        if "x" not in cache:
            h = cache["homes"]
            cache["x"] = unit_rows(h["e"])
            cache["rot"] = rotation(cache["x"].shape[1])
            cache["bits"], cache["f"] = codes(cache["x"], cache["rot"])
            cache["id"], cache["w"] = h["id"].to_numpy(), h["w"].to_numpy()
        ids, w = part["id"].to_numpy(), part["w"].to_numpy()
        p = unit_rows(part["e"])
        q = p @ cache["rot"].T
        pi, hj = [], []
        for lo in range(0, len(p), 1024):
            est, half = estimate(q[lo:lo + 1024], cache["bits"], cache["f"])
            i, j = np.nonzero(est + half >= least)
            first = ids[lo + i] < cache["id"][j]  # each pair once
            i, j = i[first] + lo, j[first]
            for s in range(0, len(i), 200_000):
                a, b = i[s:s + 200_000], j[s:s + 200_000]
                ok = np.einsum("ij,ij->i", p[a], cache["x"][b]) >= least
                pi.append(a[ok])
                hj.append(b[ok])
        i, j = np.concatenate(pi or [np.zeros(0, int)]), np.concatenate(hj or [np.zeros(0, int)])
        if not len(i):
            return None
        nodes, at = np.unique(np.r_[ids[i], cache["id"][j]], return_inverse=True)
        links = np.bincount(at, np.r_[cache["w"][j], w[i]], len(nodes)).astype("int64")
        root = local_components(at[:len(i)], at[len(i):], len(nodes))
        return pd.DataFrame({"u": nodes, "v": nodes[root], "links": links})

    found = written(paired_blocks(homes, probers, keys, kernel, "u long, v long, links long", block), "links")
    comps = components(found.select("u", "v"))
    links = found.groupBy("u").agg(F.sum("links").alias("links"))
    rows = groups.select("label", "e", "id", "rep", "w").join(links, groups["id"] == links["u"], "left").join(comps, groups["id"] == comps["node"], "left")
    rows = rows.select("label", "e", "rep", "w", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("root", "id").alias("root"))
    low = rows.groupBy("root").agg(F.min("rep").alias("component"))
    rows = rows.join(low, "root").select(F.col("label").alias("l"), F.col("e").alias("x"), (F.col("links") + F.col("w") - 1).alias("n_links"), "component")
    linked = base.where("ok").select("vec_id", "label", "e").join(rows, (F.col("label") == F.col("l")) & (F.col("e") == F.col("x"))).select("vec_id", "n_links", F.col("component").alias("component_id"))
    alone = base.where(~F.col("ok")).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def _centres(groups: DataFrame, n: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By vector length: unit centres from a bounded sample (a few k-means rounds) and their distances."""
    k = min(CENTRES, max(1, -(-n // PER_CENTRE)))
    rows = groups.select("e", F.size("e").alias("d"), "id").orderBy(F.xxhash64("id"), "id").limit(8 * k + 8).collect()
    dims = [r["d"] for r in groups.select(F.size("e").alias("d")).distinct().collect()]
    out = {}
    for d in dims:
        own = [r["e"] for r in rows if r["d"] == d]
        x = unit_rows(own) if own else np.eye(1, d)
        c = x[:k].copy()
        for _ in range(6):
            at = (x @ c.T).argmax(1)
            for i in range(len(c)):
                m = x[at == i].sum(0)
                size = np.linalg.norm(m)
                if size > 1e-9:
                    c[i] = m / size
        out[d] = (c, np.sqrt(np.maximum(0, 2 - 2 * np.clip(c @ c.T, -1, 1))))
    return out
