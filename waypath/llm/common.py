"""What several operators share: written tables, pair blocks, components."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..tables import shared_dir, ship, to_drop, written  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: str = "doc_id"):
    """True where crc32(doc_id as text) mod 5 is 0; a missing id is never trained on."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 5 == 0, F.lit(True))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """(doc_id, text, y) of at most about ``bound`` labelled documents outside the held-out fold.

    The bound is a documented parameter of the classifiers.  Documents are taken by a hash
    of their id, so reruns agree; a repeated id counts once, with its smallest text, so
    repeats don't get past the bound.  The label side has a proven size and is broadcast,
    so only the sample's texts are shuffled.
    """
    lab = labels.select("doc_id", F.col(label).cast("int").alias("y")).where(
        F.col("doc_id").isNotNull() & F.col("y").isin(0, 1) & ~held_out())
    lab = lab.groupBy("doc_id").agg(F.max("y").alias("y"))
    n = lab.count()
    if n > bound:
        lab = lab.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(bound / n * (1 << 30)))
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(lab), "doc_id")
    return found.groupBy("doc_id").agg(F.min("text").alias("text"), F.min("y").alias("y"))


# ---------------------------------------------------------------- connected components

def local_components(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """Smallest reachable index for each of n nodes linked by the pairs (u, v)."""
    label = np.arange(n)
    while len(u):
        a, b = label[u], label[v]
        low = np.minimum(a, b)
        before = label.copy()
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        np.minimum.at(label, u, low)
        np.minimum.at(label, v, low)
        label = label[label]
        if np.array_equal(before, label):
            break
    while True:
        nxt = label[label]
        if np.array_equal(nxt, label):
            return label
        label = nxt


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) of every node of ``edges(u, v)``; root is the smallest node of its component.

    Alternates a step over all neighbours with one over the smaller neighbours, each an
    aggregate (combined before the shuffle) and a join that AQE may split; every round is
    a written table, so lineage stays short and nothing gathers on the driver.
    """
    step = written(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    state = None
    for _ in range(max_rounds):
        now = step.agg(F.count(F.lit(1)), F.sum(F.hash("u", "v").cast("long"))).first()
        if now == state or now[0] == 0:
            break
        state = now
        both = step.union(step.select("v", "u"))
        low = both.groupBy(F.col("u").alias("c")).agg(F.min("v").alias("m")).select("c", F.least("c", "m").alias("m"))
        large = both.where("v > u").join(low, F.col("u") == F.col("c")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small_low = large.groupBy(F.col("u").alias("c")).agg(F.min("v").alias("m"))
        paired = large.join(small_low, F.col("u") == F.col("c"))
        linked = paired.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(small_low.select(F.col("c").alias("u"), F.col("m").alias("v")))
        step = written(linked.where("u <> v").distinct(), "edges")
    else:
        raise RuntimeError(f"components are not settled after {max_rounds} rounds")
    stars = step.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
    roots = stars.select(F.col("root").alias("node")).distinct().select("node", F.col("node").alias("root"))
    return stars.union(roots)


# ---------------------------------------------------------------- blocks of pairs

def paired_blocks(homes: DataFrame, probers: DataFrame, keys: list[str], kernel, schema: str, block: int) -> DataFrame:
    """Run ``kernel`` over every (prober, home) pair of equal keys, in blocks of bounded memory.

    Homes of a key are dealt into blocks of about ``block`` rows by their count, and each
    prober of the key goes to every block, so a key of any size becomes many units instead
    of one task.  Within a unit the homes come first and are held; probers stream past.
    Units are few bytes and much work, so the number of partitions is given: else they
    would be folded into a task or two by their size.
    Both inputs have the columns keys, id and payload columns of one shape.
    """
    counts = homes.groupBy(*keys).agg(F.count(F.lit(1)).alias("__n")).select(
        *keys, F.ceil(F.col("__n") / block).cast("int").alias("__nb"))
    rest = [c for c in homes.columns if c not in keys]
    h = homes.join(counts, keys).select(*keys, F.pmod(F.xxhash64("id"), F.col("__nb")).cast("int").alias("__b"), F.lit(0).alias("__role"), *rest)
    p = probers.join(counts, keys).select(*keys, F.explode(F.sequence(F.lit(0), F.col("__nb") - 1)).alias("__b"), F.lit(1).alias("__role"), *rest)
    unit = [*keys, "__b"]
    tasks = int(homes.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
    dealt = h.union(p).repartition(tasks, *unit).sortWithinPartitions(*unit, "__role", "id")

    def stream(batches):
        held_key, held = None, []
        cache = {}
        for pdf in batches:
            if not len(pdf):
                continue
            codes = pdf[unit].astype("string").agg("|".join, axis=1).to_numpy()
            roles = pdf["__role"].to_numpy()
            cuts = np.flatnonzero((codes[1:] != codes[:-1]) | (roles[1:] != roles[:-1])) + 1
            for lo, hi in zip(np.r_[0, cuts], np.r_[cuts, len(pdf)]):
                part = pdf.iloc[lo:hi]
                if codes[lo] != held_key:
                    held_key, held, cache = codes[lo], [], {}
                if roles[lo] == 0:
                    held.append(part)
                    cache = {}
                elif held:
                    if not cache:
                        cache["homes"] = pd.concat(held) if len(held) > 1 else held[0]
                    out = kernel(cache, part)
                    if out is not None and len(out):
                        yield out

    return dealt.mapInPandas(stream, schema)
