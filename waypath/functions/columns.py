"""Column builders for set and array forms of the measures; no Python runs on the rows."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def jaccard(a, b) -> Column:
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(a, b)) / union)


def soergel_set(a, b) -> Column:
    return 1.0 - jaccard(a, b)


def soergel(fa, va, fb, vb) -> Column:
    """Weighted distance of two sparse vectors given as sorted feature arrays with values beside them."""
    total = lambda v: F.aggregate(v, F.lit(0.0), lambda acc, x: acc + x)
    pairs = lambda f, v: F.transform(F.arrays_zip(f, v), lambda x: F.struct(x[f].alias("f"), x[v].cast("double").alias("v")))
    # sorted together, the two values of a common feature stand side by side, the smaller first
    start = F.struct(F.lit(None).cast("long").alias("f"), F.lit(0.0).alias("v"), F.lit(0.0).alias("s"))
    both = F.sort_array(F.concat(pairs(fa, va), pairs(fb, vb)))
    smin = F.aggregate(both, start, lambda acc, x: F.struct(x["f"].cast("long").alias("f"), x["v"].alias("v"), (acc["s"] + F.when(x["f"] == acc["f"], acc["v"]).otherwise(F.lit(0.0))).alias("s")))["s"]
    den = total(va) + total(vb) - smin
    return F.when(den == 0, F.lit(0.0)).otherwise(1.0 - smin / den)


def hammock_width(a, b) -> Column:
    return F.size(F.array_intersect(a, b))


def is_hammock_width(a, b, w: int) -> Column:
    return hammock_width(a, b) >= w


def is_hammock_theta(dist: Column, theta: float) -> Column:
    return dist <= theta


def mixed_set(a, b, out_a: Column, out_b: Column, t_mode: str = "sum") -> Column:
    """Lower bound of the set distance from kept feature arrays and counts of dropped features."""
    t = {"sum": out_a + out_b, "max": F.greatest(out_a, out_b), "min": F.least(out_a, out_b)}[t_mode]
    lone = F.size(F.array_except(a, b)) + F.size(F.array_except(b, a))
    den = lone + F.size(F.array_intersect(a, b)) + t
    return F.when(den == 0, F.lit(0.0)).otherwise(lone / den)


def ebf(n, d, steps: int = 60) -> Column:
    """Branching of a uniform tree of depth d with n nodes below its root: x + x^2 + ... + x^d = n, by bisection."""
    n, d = n.cast("double"), d.cast("int")

    def tree(x):
        return F.aggregate(F.sequence(F.lit(1), d), F.lit(0.0), lambda acc, _: (acc + 1.0) * x)

    low = F.struct(F.lit(0.0).alias("lo"), F.greatest(n, F.lit(1.0)).alias("hi"))
    span = F.aggregate(
        F.sequence(F.lit(1), F.lit(steps)), low,
        lambda s, _: F.when(tree((s["lo"] + s["hi"]) / 2) < n, F.struct(((s["lo"] + s["hi"]) / 2).alias("lo"), s["hi"].alias("hi"))).otherwise(F.struct(s["lo"].alias("lo"), ((s["lo"] + s["hi"]) / 2).alias("hi"))))
    return F.when((d <= 0) | d.isNull() | (n <= 0), F.lit(None).cast("double")).otherwise((span["lo"] + span["hi"]) / 2)
