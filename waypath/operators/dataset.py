"""Association datasets: objects, features and non-negative weights."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import tidy, written

#: How often sample_pairs may draw an object.
COPIES = 8


@dataclass(frozen=True)
class AssocDataset:
    """rel(obj, feat, val), unique on (obj, feat), val > 0; a missing pair has weight 0."""

    rel: DataFrame
    name: str = "data"
    #: What stats() gives, where it is written beside the relation.
    known_stats: DataFrame | None = None
    #: Whether all rows of an object lie in one partition of the relation.
    together: bool = False

    @classmethod
    def from_sets(cls, df: DataFrame, obj: str, feat: str, name: str = "sets") -> "AssocDataset":
        """Set form: every association weighs 1."""
        rel = df.select(F.col(obj).cast("long").alias("obj"), F.col(feat).cast("long").alias("feat")).where("obj IS NOT NULL AND feat IS NOT NULL").distinct()
        return cls(rel.withColumn("val", F.lit(1.0)), name)

    @classmethod
    def from_weights(cls, df: DataFrame, obj: str, feat: str, val: str, agg: str = "sum", name: str = "weights", together: bool = False) -> "AssocDataset":
        """Vector form: values of equal (obj, feat) are aggregated; zero drops out, a negative one raises when read.

        With ``together`` rows are dealt by object before they are summed, so a relation that is
        kept is dealt only once; for relations whose objects have few rows each.
        """
        v = getattr(F, agg)(F.col("val")).alias("val")
        rel = df.select(F.col(obj).cast("long").alias("obj"), F.col(feat).cast("long").alias("feat"), F.col(val).cast("double").alias("val"))
        rel = rel.where("obj IS NOT NULL AND feat IS NOT NULL AND val IS NOT NULL AND NOT isnan(val)")
        rel = (rel.repartition("obj") if together else rel).groupBy("obj", "feat").agg(v).where("val <> 0")
        guarded = F.when(F.col("val") > 0, F.col("val")).otherwise(F.raise_error(F.lit("weights must not be negative: split each feature by sign first")).cast("double"))
        return cls(rel.select("obj", "feat", guarded.alias("val")), name, together=together)

    def kept(self) -> "AssocDataset":
        """The same relation and its statistics as written tables in the order of objects, for methods that read them many times."""
        dealt = self.rel.select("obj", "feat", "val")
        rel = written((dealt if self.together else dealt.repartition("obj")).sortWithinPartitions("obj", "feat"), "rel")
        tidy(rel.sparkSession)
        return AssocDataset(rel, self.name, written(AssocDataset(rel).stats(), "stats"))

    def binary(self) -> "AssocDataset":
        """Every association weighs 1."""
        one = F.lit(1.0)
        known = None if self.known_stats is None else self.known_stats.select("obj", "n_feat", F.col("n_feat").cast("double").alias("total"), one.alias("minw"), one.alias("maxw"))
        return AssocDataset(self.rel.select("obj", "feat", one.alias("val")), self.name, known)

    def objects(self) -> DataFrame:
        return self.rel.select("obj").distinct() if self.known_stats is None else self.known_stats.select("obj")

    def stats(self) -> DataFrame:
        """obj, n_feat, total, minw, maxw."""
        if self.known_stats is not None:
            return self.known_stats
        return self.rel.groupBy("obj").agg(F.count(F.lit(1)).alias("n_feat"), F.sum("val").alias("total"), F.min("val").alias("minw"), F.max("val").alias("maxw"))

    def profiles(self) -> DataFrame:
        """obj, feats (sorted), vals beside them, n, total, minw, maxw."""
        g = self.rel.groupBy("obj").agg(F.sort_array(F.collect_list(F.struct("feat", "val"))).alias("p"), F.sum("val").alias("total"), F.min("val").alias("minw"), F.max("val").alias("maxw"))
        return g.select("obj", F.col("p.feat").alias("feats"), F.col("p.val").alias("vals"), F.size("p").alias("n"), "total", "minw", "maxw")

    def frequent(self, minsup: int) -> DataFrame:
        """feat, df of features that at least ``minsup`` objects have."""
        return self.rel.groupBy("feat").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= minsup)

    def support(self, minsup: int | float) -> int:
        """An absolute support; a float is a share of the objects."""
        if isinstance(minsup, float):
            n = self.rel.agg(F.count_distinct("obj")).first()[0]
            return max(1, -(-int(round(minsup * n * 1e9)) // 10**9))
        return max(1, int(minsup))


def dataset_profile(ds: AssocDataset) -> DataFrame:
    """carrier, n_obj, n_feat, n_rel, sparsity (per cent of empty cells)."""
    a = ds.rel.agg(F.count_distinct("obj").alias("n_obj"), F.count_distinct("feat").alias("n_feat"), F.count(F.lit(1)).alias("n_rel"))
    return a.select(F.lit(ds.name).alias("carrier"), "n_obj", "n_feat", "n_rel", F.round(100.0 * (1 - F.col("n_rel") / (F.col("n_obj").cast("double") * F.col("n_feat"))), 6).alias("sparsity"))


def sample_pairs(ds: AssocDataset, n: int, seed: int = 42, avoid: DataFrame | None = None) -> DataFrame:
    """pair_id, src, dst: n pairs by a stable hash order, not by chance of the plan.

    Objects are ordered by two seeded hashes and joined by rank; pairs in ``avoid(a, b)``
    (for instance the directly linked ones) are left out and more ranks are drawn until n
    pairs are there or every object has been drawn ``COPIES`` times.
    """
    from pyspark.sql import Window

    objs = ds.objects()
    most = COPIES * objs.count()
    links = None
    if avoid is not None:
        avoid = written(avoid.select("a", "b"), "avoid")
        links = avoid.toDF("src", "dst").union(avoid.select(F.col("b").alias("src"), F.col("a").alias("dst")))
    reps = objs.select("obj", F.explode(F.sequence(F.lit(1), F.lit(COPIES))).alias("copy"))

    def ranked(salt, name, many):
        h = F.xxhash64(F.lit(seed), F.lit(salt), "obj", "copy")
        top = reps.select(F.col("obj").alias(name), h.alias("h"), "copy").orderBy("h", name, "copy").limit(many)
        return top.select(name, F.row_number().over(Window.orderBy("h", name, "copy")).alias("r"))

    many = n + 8 if links is None else 3 * n
    while True:
        both = ranked(1, "src", many).join(ranked(2, "dst", many), "r").where("src <> dst").groupBy("src", "dst").agg(F.min("r").alias("r"))
        if links is not None:
            both = both.join(links, ["src", "dst"], "left_anti")
        both = written(both, "drawn")
        if many >= most or both.count() >= n:
            break
        many *= 2
    return both.orderBy("r").limit(n).select(F.row_number().over(Window.orderBy("r")).cast("int").alias("pair_id"), "src", "dst")


def random_intersection(spark, n: int, f: int, p: float, seed: int = 42) -> AssocDataset:
    """Null model: every object takes every feature independently with chance p, by a seeded hash."""
    cells = spark.range(n * f).select((F.col("id") / f).cast("long").alias("obj"), (F.col("id") % f).alias("feat"))
    keep = F.pmod(F.xxhash64(F.lit(seed), "obj", "feat"), F.lit(1_000_000)) < int(p * 1_000_000)
    return AssocDataset(cells.where(keep).withColumn("val", F.lit(1.0)), "random_intersection")
