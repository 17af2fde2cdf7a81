"""Cost, accuracy and significance measures over search results."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.dataset import AssocDataset
from ..operators.distance import pair_distance
from ..operators.truncate import TruncatedDataset, mixed_distance
from ..tables import written


def summarize(paths: DataFrame, by: list[str] = ("hops",)) -> DataFrame:
    """Mean nodes explored, run time, cost and branching of found paths, by length or other columns."""
    mean = lambda c: F.round(F.avg(c), 6).alias(c)
    return paths.where("outcome = 'found'").groupBy(*by).agg(F.count(F.lit(1)).alias("paths"), mean("nodes_explored"), mean("elapsed_ms"), mean("cost"), mean("ebf"))


def by_length(paths: DataFrame, column: str, value: str = "nodes_explored") -> DataFrame:
    """hops, then a column for each value of ``column``: the table behind a plot of curves over path length."""
    return paths.where("outcome = 'found'").groupBy("hops").pivot(column).agg(F.round(F.avg(value), 6))


def longest_path(runs: DataFrame) -> DataFrame:
    """k, longest (hops) of runs with a column k."""
    return runs.where("outcome = 'found'").groupBy("k").agg(F.max("hops").alias("longest"))


def outcome_rates(paths: DataFrame, by: list[str] = ()) -> DataFrame:
    """outcome, n, share, within the groups of ``by`` if given."""
    n = Window.partitionBy(*by)
    return paths.groupBy(*by, "outcome").agg(F.count(F.lit(1)).alias("n")).withColumn("share", F.round(F.col("n") / F.sum("n").over(n), 6))


def pct_saved(bfs: DataFrame, astar: DataFrame) -> DataFrame:
    """By pair found in both runs: 100 x (uninformed / informed - 1) for nodes, run time and branching."""
    a = astar.where("outcome = 'found'").select("pair_id", "hops", F.col("nodes_explored").alias("n1"), F.col("elapsed_ms").alias("t1"), F.col("ebf").alias("e1"))
    z = bfs.where("outcome = 'found'").select("pair_id", F.col("nodes_explored").alias("n0"), F.col("elapsed_ms").alias("t0"), F.col("ebf").alias("e0"))
    s = lambda x, y: F.when(F.col(y) > 0, F.round(100.0 * (F.col(x) / F.col(y) - 1), 6))
    return a.join(z, "pair_id").select("pair_id", "hops", s("n0", "n1").alias("nodes_saved"), s("t0", "t1").alias("time_saved"), s("e0", "e1").alias("ebf_saved"))


def cost_gap(paths: DataFrame, exact: DataFrame) -> DataFrame:
    """pair_id, cost, best, gap against the least cost of the built network; as it is, so a negative gap would show."""
    return paths.where("outcome = 'found'").select("pair_id", "cost").join(exact.select("pair_id", F.col("cost").alias("best")), "pair_id").withColumn("gap", F.col("cost") - F.col("best"))


def recall_at_b(got: DataFrame, truth: DataFrame) -> DataFrame:
    """obj, recall: share of the true neighbours that a generator returned."""
    hit = truth.select("obj", "nbr").join(got.select("obj", "nbr", F.lit(1).alias("hit")), ["obj", "nbr"], "left")
    return hit.groupBy("obj").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def order_inversions(got: DataFrame, value: str = "jaccard") -> DataFrame:
    """obj, inversions: neighbours that come after a worse one."""
    w = Window.partitionBy("obj").orderBy("rnk")
    d = got.withColumn("before", F.lag(value).over(w))
    return d.groupBy("obj").agg(F.sum(F.when(F.col(value) > F.col("before") + 1e-12, 1).otherwise(0)).alias("inversions"))


def audit_admissible(td: TruncatedDataset, ds: AssocDataset, pairs: DataFrame, t_mode: str = "sum", weighted: bool = True) -> DataFrame:
    """n_pairs, worst: the largest lower bound minus true distance; 0 or less when admissible."""
    d = pair_distance(ds, pairs, weighted)
    m = mixed_distance(td, pairs, weighted, t_mode)
    return d.join(m, ["a", "b"]).agg(F.count(F.lit(1)).alias("n_pairs"), F.round(F.max(F.col("mixed") - F.col("dist")), 9).alias("worst"))


def log_factorial(n: np.ndarray) -> np.ndarray:
    """ln n! by the asymptotic series, after moving up to where it is exact to double precision."""
    x = np.asarray(n, np.float64) + 1.0
    low = np.zeros_like(x)
    for _ in range(12):
        small = x < 12
        low = np.where(small, low + np.log(np.where(small, x, 1.0)), low)
        x = np.where(small, x + 1, x)
    r = 1 / (x * x)
    return (x - 0.5) * np.log(x) - x + 0.5 * np.log(2 * np.pi) + (1 / 12 - r * (1 / 360 - r * (1 / 1260 - r * (1 / 1680 - r / 1188)))) / x - low


def tail(overlap: np.ndarray, na: np.ndarray, nb: np.ndarray, f: int) -> np.ndarray:
    """P(X >= overlap) for X common features of two random sets of na and nb out of f; terms follow from the first by their ratio."""
    x = np.maximum(overlap, np.maximum(0, na + nb - f)).astype(np.float64)
    top = np.minimum(na, nb)
    lf = log_factorial
    inside = x <= top
    c = lambda v: np.maximum(v, 0)
    first = lf(na) + lf(nb) + lf(f - na) + lf(f - nb) - lf(np.full_like(x, f)) - lf(x) - lf(c(na - x)) - lf(c(nb - x)) - lf(c(f - na - nb + x))
    term = np.where(inside, np.exp(first), 0.0)
    total = term.copy()
    while (term > 1e-18 * total).any():
        term = term * (na - x) * (nb - x) / ((x + 1) * (f - na - nb + x + 1))
        x = x + 1
        term = np.where(x <= top, term, 0.0)
        total += term
    return np.minimum(total, 1.0)


def hop_pvalues(hops: DataFrame, ds: AssocDataset) -> DataFrame:
    """(a, b, overlap, p): chance of at least that overlap for two feature sets of these sizes (hypergeometric).

    Sums of the tail run in Arrow batches; no table of factorials is built or joined.
    """
    n_feat = ds.rel.agg(F.count_distinct("feat")).first()[0]
    st = ds.stats().select("obj", "n_feat")
    d = pair_distance(ds, hops).select("a", "b", F.col("width").alias("overlap"))
    j = d.join(st.select(F.col("obj").alias("a"), F.col("n_feat").alias("na")), "a").join(st.select(F.col("obj").alias("b"), F.col("n_feat").alias("nb")), "b")

    @F.pandas_udf("double")
    def p(overlap: pd.Series, na: pd.Series, nb: pd.Series) -> pd.Series:
        return pd.Series(tail(overlap.to_numpy(), na.to_numpy(), nb.to_numpy(), n_feat))

    return j.select("a", "b", "overlap", p("overlap", "na", "nb").alias("p"))


def benjamini_hochberg(df: DataFrame, p: str = "p", by: list[str] | None = None, ranges: int = 64) -> DataFrame:
    """df with q: p times count over rank, made monotone from the largest p down, within groups.

    Groups (the steps of a path) are small and take a window each.  Without groups all rows
    are one family, so the distinct values are dealt into ranges between quantiles: how many
    rows lie below a range and the least ratio above it are known from one row a range, and
    no task holds more than its range.
    """
    if by:
        part = Window.partitionBy(*by)
        ranked = df.withColumn("__m", F.count(F.lit(1)).over(part)).withColumn("__i", F.rank().over(part.orderBy(p)) + F.count(F.lit(1)).over(Window.partitionBy(*by, p)) - 1)
        down = part.orderBy(F.desc(p)).rangeBetween(Window.unboundedPreceding, 0)
        return ranked.withColumn("q", F.least(F.lit(1.0), F.min(F.col(p) * F.col("__m") / F.col("__i")).over(down))).drop("__m", "__i")
    known = df.where(F.col(p).isNotNull() & ~F.isnan(p))
    cuts = sorted(set(known.agg(F.percentile_approx(p, [i / ranges for i in range(1, ranges)], 4 * ranges)).first()[0] or []))  # null without rows
    place = F.size(F.filter(F.array(*[F.lit(c) for c in cuts]), lambda c: c < F.col("v"))) if cuts else F.lit(0)
    values = written(df.where(F.col(p).isNotNull()).groupBy(F.col(p).alias("v")).agg(F.count(F.lit(1)).alias("n")).withColumn("range", place), "values")
    below = values.groupBy("range").agg(F.sum("n").alias("n"))
    few = Window.orderBy("range")  # a row a range
    below = below.select("range", F.coalesce(F.sum("n").over(few.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy()).alias("m"))
    w = Window.partitionBy("range").orderBy("v")
    ratio = written(values.join(F.broadcast(below), "range").withColumn("r", F.col("v") * F.col("m") / (F.col("before") + F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)))), "ratio")
    above = ratio.groupBy("range").agg(F.min("r").alias("r"))
    above = above.select("range", F.min("r").over(few.rowsBetween(1, Window.unboundedFollowing)).alias("above"))
    least = F.min("r").over(w.rowsBetween(0, Window.unboundedFollowing))
    q = ratio.join(F.broadcast(above), "range").select("v", F.least(F.lit(1.0), least, F.col("above")).alias("q"))
    return df.join(q, df[p] == q["v"], "left").drop("v")
