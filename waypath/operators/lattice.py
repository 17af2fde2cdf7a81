"""Frequent closed concepts, their lattice, and the upper edge of each object."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..tables import drop_since, mark, ship, tidy, written
from .dataset import AssocDataset

#: A lattice grows without bound as minsup falls; beyond this many concepts building stops with an error.
MOST_CONCEPTS = 2_000_000
#: Up to so many concepts their numbers are sent to every task.
MOST_SENT = 1_000_000
#: Ranges of features hold about so many associations, and there are at least so many ranges.
PART_ROWS, LEAST_PARTS = 4_000_000, 8


@dataclass(frozen=True)
class Lattice:
    """concepts(cid, intent, n_feat, support); extents(cid, obj, n_obj_feat), unless built without.

    Built with ``top`` it holds in their place heads(cid, obj, n_obj_feat, rnk), the first
    ``top`` of each object list, and longest(obj, cid, n_feat).
    """

    concepts: DataFrame
    extents: DataFrame | None
    minsup: int
    heads: DataFrame | None = None
    longest: DataFrame | None = None
    top: int = 0

    def save(self, path: str) -> None:
        """Write the lattice, so that later searches need not build it."""
        self.concepts.write.mode("overwrite").parquet(f"{path}/concepts")
        self.extents.repartition("cid").sortWithinPartitions("cid").write.mode("overwrite").parquet(f"{path}/extents")

    @classmethod
    def load(cls, spark: SparkSession, path: str, minsup: int) -> "Lattice":
        return cls(spark.read.parquet(f"{path}/concepts"), spark.read.parquet(f"{path}/extents"), minsup)


def build_concepts(ds: AssocDataset, minsup: int | float | str, min_features: int = 1, most: int = MOST_CONCEPTS, clique: int | None = None, extents: bool = True, top: int | None = None) -> Lattice:
    """All closed (object set, feature set) pairs of at least ``minsup`` objects.

    A concept is extended by a frequent feature beyond its core feature; the features that
    all remaining objects share close it.  It is kept only if closing added no feature below
    the new core, so each concept is met once and no duplicate test is needed.  All concepts
    whose first extension is a feature need only the objects that have it, so ranges of
    features go to tasks of their own with those objects' frequent features, and nothing
    counted on the way is shuffled.  ``minsup`` is a count, a share of the objects, or
    'clique' for the clique size that ``clique`` names.  At the end concepts are numbered in
    the order of their feature lists, so ids depend on the data alone.  Without ``extents``
    no task passes on which objects a concept has, and the lattice holds concepts only; with
    ``top`` a task passes on the first so many of each list, and for each of its objects
    which of its concepts is longest.
    """
    if minsup == "clique":
        if not clique:
            raise ValueError("minsup='clique' needs the clique size")
        minsup = clique
    spark, place = ds.rel.sparkSession, mark()
    of, sizes, n_obj, shared, n = _ranges(ds, minsup)
    extents = extents and top is None

    def mined(key, table):
        return _concepts_of_range(table, n, shared, key[0].as_py(), extents, top)

    lists = ", objs array<bigint>, sizes array<bigint>" * (extents or top is not None) + ", best array<bigint>" * (top is not None)
    found = written(of.groupBy("part").applyInArrow(mined, "part int, seq long, intent array<bigint>, support long" + lists), "found")
    tidy(spark)
    concepts = found.select("part", "seq", "intent", "support")
    if n_obj >= n:  # the root: what all objects share
        root = spark.createDataFrame([(-1, 0, shared, n_obj)], "part int, seq long, intent array<bigint>, support long")
        concepts = concepts.union(root)
    total = concepts.count()
    if total > most:
        raise ValueError(f"more than {most} concepts: raise minsup (now {n})")
    concepts = concepts.select("*", F.size("intent").alias("n_feat")).where(F.col("n_feat") >= min_features)
    # at most ``most`` rows, so one window may number them
    numbered = written(concepts.withColumn("id", F.row_number().over(Window.orderBy("intent")).cast("long")), "numbered")
    if not extents and top is None:
        lat = Lattice(written(numbered.select(F.col("id").alias("cid"), "intent", "n_feat", "support"), "lattice"), None, n)
        drop_since(place, [lat.concepts])
        return lat
    ids = numbered.select("part", "seq", "id", "n_feat")
    if total <= MOST_SENT:
        ids = F.broadcast(ids)
    if top is not None:
        lat = _with_heads(found.join(ids, ["part", "seq"]), numbered, sizes, n, top)
        drop_since(place, [lat.concepts, lat.heads, lat.longest])
        return lat
    held = found.join(ids, ["part", "seq"]).select(F.col("id").alias("cid"), F.explode(F.arrays_zip("objs", "sizes")).alias("x")).select("cid", F.col("x.objs").alias("obj"), F.col("x.sizes").alias("n_obj_feat"))
    whole = numbered.where("part = -1").select(F.col("id").alias("cid"))
    held = held.union(sizes.join(F.broadcast(whole)).select("cid", "obj", "n_obj_feat"))
    lat = Lattice(written(numbered.select(F.col("id").alias("cid"), "intent", "n_feat", "support"), "lattice"), written(held, "lattice"), n)
    drop_since(place, [lat.concepts, lat.extents])
    return lat


def _ranges(ds: AssocDataset, minsup: int | float):
    """The objects dealt to ranges of frequent features, sizes(obj, n_obj_feat), how many objects there are, what all share, and the support."""
    ship(ds.rel.sparkSession)
    n = ds.support(minsup)
    sizes = written(ds.stats().select("obj", F.col("n_feat").cast("long").alias("n_obj_feat")), "sizes")
    n_obj = sizes.count()
    frequent = written(ds.frequent(n), "frequent")
    shared = sorted(r.feat for r in frequent.where(F.col("df") == n_obj).collect())
    rel = ds.rel.join(frequent.select("feat"), "feat", "left_semi").select("obj", "feat")
    profiles = rel.groupBy("obj").agg(F.sort_array(F.collect_list("feat")).alias("feats")).join(sizes, "obj")
    profiles = written(profiles, "profiles")
    tidy(ds.rel.sparkSession)
    return _dealt(profiles, frequent)[0], sizes, n_obj, shared, n


def _with_heads(found: DataFrame, numbered: DataFrame, sizes: DataFrame, n: int, top: int) -> Lattice:
    """A lattice with the first places of its lists and each object's longest concept; a range has told its own longest one of each of its objects."""
    first = found.select(F.col("id").alias("cid"), F.posexplode(F.arrays_zip("objs", "sizes")).alias("rnk", "x")).select("cid", F.col("x.objs").alias("obj"), F.col("x.sizes").alias("n_obj_feat"), (F.col("rnk") + 1).alias("rnk"))
    whole = F.broadcast(numbered.where("part = -1").select("id", "n_feat", "support"))  # a row or none
    every = sizes.orderBy(F.desc("n_obj_feat"), "obj").limit(top).withColumn("rnk", F.row_number().over(Window.orderBy(F.desc("n_obj_feat"), "obj")))
    first = first.union(every.join(whole).select(F.col("id").alias("cid"), "obj", "n_obj_feat", "rnk"))
    own = found.select(F.explode("best").alias("obj"), "id", "n_feat", "support").union(sizes.join(whole).select("obj", "id", "n_feat", "support"))
    longest = own.groupBy("obj").agg(F.max(F.struct("n_feat", "support", (-F.col("id")).alias("m"))).alias("x")).select("obj", (-F.col("x.m")).alias("cid"), F.col("x.n_feat").alias("n_feat"))
    concepts = written(numbered.select(F.col("id").alias("cid"), "intent", "n_feat", "support"), "lattice")
    return Lattice(concepts, None, n, written(first, "heads"), written(longest, "longest"), top)


def listed_extents(ds: AssocDataset, minsup: int | float, most: int = MOST_CONCEPTS) -> DataFrame:
    """(intent, obj, n_obj_feat, rnk): every concept's object list by number of features, ties by id, as the ranges give them.

    A range of features has all objects of its concepts, so its task ranks them: nothing is
    written or shuffled once concepts are known, and no lattice is kept.
    """
    of, sizes, n_obj, shared, n = _ranges(ds, minsup)

    def mined(key, table):
        out = _concepts_of_range(table, n, shared, key[0].as_py(), False, len(table), best=False)
        if len(out) > most:
            raise ValueError(f"more than {most} concepts: raise minsup (now {n})")
        return out.select(["intent", "objs", "sizes"])

    found = of.groupBy("part").applyInArrow(mined, "intent array<bigint>, objs array<bigint>, sizes array<bigint>")
    out = found.select("intent", F.posexplode(F.arrays_zip("objs", "sizes")).alias("rnk", "x")).select("intent", F.col("x.objs").alias("obj"), F.col("x.sizes").alias("n_obj_feat"), (F.col("rnk") + 1).alias("rnk"))
    if shared and n_obj >= n:
        every = sizes.withColumn("rnk", F.row_number().over(Window.orderBy(F.desc("n_obj_feat"), "obj")))
        out = out.union(every.select(F.lit(shared).cast("array<bigint>"), "obj", "n_obj_feat", "rnk"))
    return out


def _dealt(profiles: DataFrame, features: DataFrame, later: bool = False) -> tuple[DataFrame, list]:
    """(part, low, high, obj, n_obj_feat, feats) of profiles(obj, feats, n_obj_feat): each goes to the ranges of features in which it has one.

    Ranges hold about equally many associations; with ``later`` only features from the range on travel.
    """
    total = features.agg(F.sum("df")).first()[0] or 0
    parts = max(LEAST_PARTS, -(-total // PART_ROWS))
    run = Window.orderBy("feat").rowsBetween(Window.unboundedPreceding, -1)
    share = F.floor(F.coalesce(F.sum("df").over(run), F.lit(0)) * parts / F.lit(max(1, total))).cast("int")
    bounds = features.select("feat", share.alias("part")).groupBy("part").agg(F.min("feat").alias("low"), F.max("feat").alias("high")).orderBy("low").collect()
    where = F.array(*[F.struct(F.lit(r.part).cast("int").alias("part"), F.lit(r.low).cast("long").alias("low"), F.lit(r.high).cast("long").alias("high")) for r in bounds]) if bounds else F.expr("CAST(array() AS array<struct<part: int, low: bigint, high: bigint>>)")
    x = profiles.select("obj", "n_obj_feat", "feats", F.explode(where).alias("r"))
    x = x.where(F.exists("feats", lambda f: (f >= F.col("r.low")) & (f <= F.col("r.high"))))
    feats = F.filter("feats", lambda f: f >= F.col("r.low")) if later else F.col("feats")
    return x.select("r.part", "r.low", "r.high", "obj", "n_obj_feat", feats.alias("feats")), bounds


def _held(table: pa.Table):
    """The features of a range's objects as numbers in their order: features, where each object begins, and for each place its object and its feature's number."""
    lists = table.column("feats").combine_chunks()
    lists = lists if isinstance(lists, pa.ListArray) else lists.chunk(0)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    starts = np.r_[0, np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]
    feats, codes = np.unique(flat, return_inverse=True)
    codes = codes.astype("int32")
    rows = np.repeat(np.arange(len(lists), dtype="int32"), np.diff(starts))
    return feats, starts, rows, codes


def _by_feature(rows: np.ndarray, codes: np.ndarray, low: int, high: int, n: int):
    """(code, objects) for the features numbered from low to high that at least n objects have."""
    at = np.flatnonzero((codes >= low) & (codes < high))
    at = at[np.argsort(codes[at], kind="stable")]
    cuts = np.searchsorted(codes[at], np.arange(low, high + 1))
    for c in range(low, high):
        own = at[cuts[c - low]:cuts[c - low + 1]]
        if len(own) >= n:
            yield c, rows[own]


def _places(starts: np.ndarray, own: np.ndarray):
    """Where the features of the given objects lie, and for each the number of its object among them."""
    many = starts[own + 1] - starts[own]
    nth = np.repeat(np.arange(len(own)), many)
    return np.repeat(starts[own] - np.cumsum(many) + many, many) + np.arange(len(nth)), nth


def _concepts_of_range(table: pa.Table, n: int, shared: list[int], part: int, extents: bool = True, top: int | None = None, best: bool = True) -> pa.Table:
    """All concepts whose first extension lies in a range of features, with their objects unless these are left out.

    With ``top`` the objects are the first so many by number of features, ties by id, and
    ``best`` are those that have no longer concept here (then larger, then first by its features).
    """
    feats, starts, rows, codes = _held(table)
    objs, sizes = table.column("obj").to_numpy(), table.column("n_obj_feat").to_numpy()
    low, high = (np.searchsorted(feats, table.column(c)[0].as_py(), side) for c, side in (("low", "left"), ("high", "right")))
    root = set(np.searchsorted(feats, shared).tolist()) if shared else set()
    intents, supports, members = [], [], []
    for core, own in _by_feature(rows, codes, low, high, n):
        if core in root:
            continue
        at, nth = _places(starts, own)
        seen = np.bincount(codes[at], minlength=len(feats))
        cols = np.flatnonzero(seen >= n)  # what no n of these objects have closes and extends nothing here
        col = np.full(len(feats), -1, "int32")
        col[cols] = np.arange(len(cols))
        here = col[codes[at]]
        has = np.zeros((len(own), len(cols)), bool)
        has[nth[here >= 0], here[here >= 0]] = True
        waiting = [(int(col[core]), None, frozenset(int(col[r]) for r in root))]
        while waiting:
            c, picked, before = waiting.pop()
            m = has if picked is None else has[picked]
            counts = m.sum(axis=0)
            full = frozenset(np.flatnonzero(counts == len(m)).tolist())
            if any(f < c and f not in before for f in full):
                continue
            who = own if picked is None else own[picked]
            intents.append(feats[cols[sorted(full)]])
            supports.append(len(m))
            if extents or top is not None:
                members.append(who)
            for f in np.flatnonzero(counts >= n).tolist():
                if f > c and f not in full:
                    rest = np.flatnonzero(m[:, f])
                    waiting.append((f, rest if picked is None else picked[rest], full))
    owners = [[] for _ in members]
    if top is not None:
        if best:
            longest = np.full(len(objs), -1, "int64")
            for i in sorted(sorted(range(len(members)), key=lambda i: intents[i].tolist(), reverse=True), key=lambda i: (len(intents[i]), supports[i])):
                longest[members[i]] = i
            by = np.argsort(longest, kind="stable")
            owners = np.split(by, np.searchsorted(longest[by], np.arange(len(members) + 1)))[1:-1]
        by = np.lexsort((objs, -sizes))
        place = np.empty(len(objs), "int64")
        place[by] = np.arange(len(objs))
        members = [by[np.sort(place[m])[:top]] for m in members]
    who = np.concatenate(members) if members else np.empty(0, "int64")
    lists = lambda lengths, flat: pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(lengths)].astype("int32")), pa.array(flat))
    lengths = [len(x) for x in members]
    out = {
        "part": pa.array(np.full(len(intents), part, "int32")), "seq": pa.array(np.arange(len(intents), dtype="int64")),
        "intent": lists([len(x) for x in intents], np.concatenate(intents) if intents else np.empty(0, "int64")),
        "support": pa.array(np.array(supports, "int64"))}
    if extents or top is not None:
        out |= {"objs": lists(lengths, objs[who]), "sizes": lists(lengths, sizes[who])}
    if top is not None and best:
        mine = np.concatenate(owners) if members else np.empty(0, "int64")
        out["best"] = lists([len(x) for x in owners], objs[mine])
    return pa.table(out)


def pair_support(ds: AssocDataset, per_feature: int = 5) -> int:
    """The largest support at which at least ``per_feature`` pairs a feature are frequent; that of the rarest pair where there are fewer.

    Pairs are counted in ranges of their first feature, each in a task that holds the objects
    with one; only how many pairs have each count leaves a task.
    """
    place = mark()
    ship(ds.rel.sparkSession)
    features = written(ds.frequent(1), "features")
    profiles = ds.rel.groupBy("obj").agg(F.sort_array(F.collect_list("feat")).alias("feats")).withColumn("n_obj_feat", F.size("feats").cast("long"))
    of, _ = _dealt(written(profiles, "profiles"), features, later=True)

    def counted(key, table):
        feats, starts, rows, codes = _held(table)
        low, high = (np.searchsorted(feats, table.column(c)[0].as_py(), side) for c, side in (("low", "left"), ("high", "right")))
        found = np.zeros(1, "int64")
        for core, own in _by_feature(rows, codes, low, high, 1):
            at, _ = _places(starts, own)
            seen = np.bincount(np.bincount(codes[at], minlength=len(feats))[core + 1:])
            found = np.r_[found, np.zeros(max(0, len(seen) - len(found)), "int64")]
            found[:len(seen)] += seen
        n = np.flatnonzero(found[1:]) + 1
        return pa.table({"n": pa.array(n.astype("int64")), "pairs": pa.array(found[n].astype("int64"))})

    counts = of.groupBy("part").applyInArrow(counted, "n long, pairs long").groupBy("n").agg(F.sum("pairs").alias("pairs"))
    reach = F.sum("pairs").over(Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, 0))
    want = per_feature * features.count()
    found = counts.select("n", reach.alias("reach")).agg(F.max(F.when(F.col("reach") >= want, F.col("n"))), F.min("n")).first()
    drop_since(place)
    tidy(ds.rel.sparkSession)
    return max(1, found[0] or found[1] or 1)


def build_edges(lat: Lattice) -> DataFrame:
    """(cid, child_cid): covers, where a child has fewer features and nothing lies between.

    Pairs meet through the child's rarest feature only, so each candidate parent is met once.
    """
    inv = lat.concepts.select("cid", "n_feat", "intent", F.explode("intent").alias("feat"))
    df = inv.groupBy("feat").agg(F.count(F.lit(1)).alias("df"))
    key = inv.select("cid", "n_feat", "intent", "feat").join(df, "feat").groupBy("cid").agg(F.min_by("feat", F.struct("df", "feat")).alias("feat"), F.first("n_feat").alias("n_feat"), F.first("intent").alias("intent"))
    child = key.select(F.col("cid").alias("child_cid"), "feat", F.col("n_feat").alias("nc"), F.col("intent").alias("ci"))
    under = inv.join(child, "feat").where((F.col("nc") < F.col("n_feat")) & (F.size(F.array_except("ci", "intent")) == 0)).select("cid", "child_cid")
    under = written(under, "under")
    via = under.alias("x").join(under.alias("y"), F.col("x.child_cid") == F.col("y.cid")).select(F.col("x.cid").alias("cid"), F.col("y.child_cid").alias("child_cid")).distinct()
    return under.join(via, ["cid", "child_cid"], "left_anti")


def rank_extents(lat: Lattice, order: str = "features_desc", top: int | None = None) -> DataFrame:
    """(cid, obj, n_obj_feat, rnk): each concept's object list by number of features, ties by id.

    With ``top`` only the first places: Spark then cuts every list before it is shuffled, so
    the list of a concept that holds most objects is never sorted in one task.
    """
    if lat.heads is not None:
        if order != "features_desc" or top is None or top > lat.top:
            raise ValueError(f"the lattice holds only the first {lat.top} of each list, by number of features")
        return lat.heads.where(F.col("rnk") <= top)
    by = {"features_desc": F.col("n_obj_feat").desc(), "features_asc": F.col("n_obj_feat").asc()}[order]
    out = lat.extents.withColumn("rnk", F.row_number().over(Window.partitionBy("cid").orderBy(by, "obj")))
    return out if top is None else out.where(F.col("rnk") <= top)


def top_edge(lat: Lattice, edges: DataFrame | None = None) -> DataFrame:
    """(obj, cid, n_feat): concepts of an object with no larger concept that holds it too.

    If a larger concept holds the object, so does one that covers this one, so the objects
    of each concept are struck from what it covers and no concepts are compared by object.
    """
    e = build_edges(lat) if edges is None else edges
    beaten = lat.extents.select("cid", "obj").join(e, "cid").select("obj", F.col("child_cid").alias("cid")).distinct()
    own = lat.extents.select("cid", "obj").join(beaten, ["obj", "cid"], "left_anti")
    return own.join(lat.concepts.select("cid", "n_feat"), "cid").select("obj", "cid", "n_feat")


def tau(lat: Lattice, edges: DataFrame | None = None) -> DataFrame:
    """(obj, cid, holds) for every concept that holds the object."""
    top = top_edge(lat, edges).select("obj", "cid", F.lit(True).alias("t"))
    return lat.extents.select("obj", "cid").join(top, ["obj", "cid"], "left").select("obj", "cid", F.coalesce("t", F.lit(False)).alias("holds"))


def longest_concept(lat: Lattice) -> DataFrame:
    """(obj, cid, n_feat): most features, then larger support, then lowest cid."""
    if lat.longest is not None:
        return lat.longest
    j = lat.extents.select("cid", "obj").join(lat.concepts.select("cid", "n_feat", "support"), "cid")
    best = j.groupBy("obj").agg(F.max(F.struct("n_feat", "support", (-F.col("cid")).alias("m"), "cid")).alias("x"))
    return best.select("obj", F.col("x.cid").alias("cid"), F.col("x.n_feat").alias("n_feat"))


def lattice_stats(lat: Lattice, edges: DataFrame | None = None) -> DataFrame:
    """n_concepts, n_minimal (no child), n_maximal (nothing above): both readings of a leaf."""
    e = build_edges(lat) if edges is None else edges
    c = lat.concepts.select("cid")
    lows = c.join(e.select("cid").distinct(), "cid", "left_anti").agg(F.count(F.lit(1)).alias("n_minimal"))
    highs = c.join(e.select(F.col("child_cid").alias("cid")).distinct(), "cid", "left_anti").agg(F.count(F.lit(1)).alias("n_maximal"))
    return c.agg(F.count(F.lit(1)).alias("n_concepts")).join(lows).join(highs)
