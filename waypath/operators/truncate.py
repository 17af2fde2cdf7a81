"""Lossy datasets: infrequent features dropped, per-object aggregates kept, and the lower bounds they allow."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dataset import AssocDataset


@dataclass(frozen=True)
class TruncatedDataset:
    """kept: the relation over frequent features; stat(obj, n_in, n_out, minw, maxw) over all features of obj."""

    kept: AssocDataset
    stat: DataFrame


def truncate(ds: AssocDataset, minsup: int | float) -> TruncatedDataset:
    """Drop features of less than minsup support; keep what was dropped as counts and extreme weights."""
    rel = ds.rel.join(ds.frequent(ds.support(minsup)).select("feat"), "feat", "left_semi").select("obj", "feat", "val")
    n_in = rel.groupBy("obj").agg(F.count(F.lit(1)).alias("n_in"))
    stat = ds.stats().join(n_in, "obj", "left").select("obj", F.coalesce("n_in", F.lit(0)).alias("n_in"), (F.col("n_feat") - F.coalesce("n_in", F.lit(0))).alias("n_out"), "minw", "maxw")
    return TruncatedDataset(AssocDataset(rel, f"{ds.name}_truncated"), stat)


def dropped_bound(a, b, how: str):
    """|T_O| from the two objects' counts of dropped features; any of these keeps the bound a lower one."""
    return {"sum": a + b, "max": F.greatest(a, b), "min": F.least(a, b)}[how]


def mixed_distance(td: TruncatedDataset, pairs: DataFrame, weighted: bool = True, t_mode: str = "sum", tight: bool = False, union_counts: DataFrame | None = None) -> DataFrame:
    """(a, b, mixed): the lower bound of the distance from kept features and aggregates.

    Uncommon kept features count at the object's least weight (at their real weight with
    ``tight``), common ones exactly, dropped ones as common at the larger of the greatest
    weights.  ``t_mode='union'`` needs union_counts(a, b, t), since counts of two objects
    don't give the size of a union.
    """
    val = F.col("val") if weighted else F.lit(1.0)
    rel = td.kept.rel.select("obj", "feat", val.alias("val"))
    one = F.lit(1.0)
    stat = td.stat.select("obj", "n_in", "n_out", (F.col("minw") if weighted else one).alias("minw"), (F.col("maxw") if weighted else one).alias("maxw"))
    sums = rel.groupBy("obj").agg(F.sum("val").alias("kept_total"))
    stat = stat.join(sums, "obj", "left").withColumn("kept_total", F.coalesce("kept_total", F.lit(0.0)))
    p = pairs.select("a", "b").distinct()
    ra, rb = rel.select(F.col("obj").alias("a"), "feat", F.col("val").alias("va")), rel.select(F.col("obj").alias("b"), "feat", F.col("val").alias("vb"))
    common = p.join(ra, "a").join(rb, ["b", "feat"]).groupBy("a", "b").agg(
        F.count(F.lit(1)).alias("c"), F.sum(F.abs(F.col("va") - F.col("vb"))).alias("diff"), F.sum(F.greatest("va", "vb")).alias("top"), F.sum("va").alias("ca"), F.sum("vb").alias("cb"))
    sa = stat.select([F.col(c).alias("a" if c == "obj" else f"a_{c}") for c in stat.columns])
    sb = stat.select([F.col(c).alias("b" if c == "obj" else f"b_{c}") for c in stat.columns])
    j = p.join(sa, "a").join(sb, "b").join(common, ["a", "b"], "left").na.fill(0, ["c", "diff", "top", "ca", "cb"])
    if t_mode == "union":
        j = j.join(union_counts, ["a", "b"])
        t = F.col("t")
    else:
        t = dropped_bound(F.col("a_n_out"), F.col("b_n_out"), t_mode)
    if tight:
        lone = (F.col("a_kept_total") - F.col("ca")) + (F.col("b_kept_total") - F.col("cb"))
    else:
        lone = (F.col("a_n_in") - F.col("c")) * F.col("a_minw") + (F.col("b_n_in") - F.col("c")) * F.col("b_minw")
    num = lone + F.col("diff")
    den = lone + F.col("top") + t * F.greatest("a_maxw", "b_maxw")
    return j.select("a", "b", F.when(den <= 0, F.lit(0.0)).otherwise(num / den).alias("mixed"))


def dropped_union(ds: AssocDataset, td: TruncatedDataset, pairs: DataFrame) -> DataFrame:
    """(a, b, t): real sizes of the unions of dropped features, which need the full relation."""
    out = ds.rel.join(td.kept.rel.select("feat").distinct(), "feat", "left_anti")
    p = pairs.select("a", "b").distinct()
    both = p.join(out.select(F.col("obj").alias("a"), "feat"), "a").join(out.select(F.col("obj").alias("b"), "feat"), ["b", "feat"]).groupBy("a", "b").agg(F.count(F.lit(1)).alias("both"))
    sa, sb = td.stat.select(F.col("obj").alias("a"), F.col("n_out").alias("na")), td.stat.select(F.col("obj").alias("b"), F.col("n_out").alias("nb"))
    return p.join(sa, "a").join(sb, "b").join(both, ["a", "b"], "left").select("a", "b", (F.col("na") + F.col("nb") - F.coalesce("both", F.lit(0))).alias("t"))
