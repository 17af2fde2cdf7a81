"""Queries brought within their limits: what they now return, against plain versions."""

import numpy as np
import pytest

from waypath import queries as engine
from waypath.functions import text
from waypath.operators import distance, successors
from waypath.operators.dataset import AssocDataset


def weighted(spark, n=400, f=30, seed=3):
    r = np.random.default_rng(seed)
    rows = [(o, int(x) - 5, float(r.integers(1, 9))) for o in range(n) for x in r.choice(f, r.integers(1, 8), replace=False)]
    return AssocDataset(spark.createDataFrame(rows, "obj long, feat long, val double")), rows


def plain_nearest(rows, asked, b):
    prof = {}
    for o, f, v in rows:
        prof.setdefault(o, {})[f] = v
    out = set()
    for a in asked:
        near = []
        for o, q in prof.items():
            s = sum(min(v, q[f]) for f, v in prof[a].items() if f in q)
            if o != a and s > 0:
                near.append((round(1 - s / (sum(prof[a].values()) + sum(q.values()) - s), 12), o))
        out |= {(a, o, d, i + 1) for i, (d, o) in enumerate(sorted(near)[:b])}
    return out


def as_set(df):
    return {(r.obj, r.nbr, round(r.dist, 12), r.rnk) for r in df.collect()}


@pytest.mark.parametrize("sent", [100_000, 0])
def test_nearest_of_a_frontier(spark, monkeypatch, sent):
    """By tasks that hold the frontier and by the join."""
    monkeypatch.setattr(successors, "MOST_SENT", sent)
    monkeypatch.setattr(successors, "AT_ONCE", 500)
    ds, rows = weighted(spark)
    f = spark.createDataFrame([(0,), (100,), (200,), (399,), (5000,)], "obj long")
    assert as_set(successors.exact_knn(ds, f, 5)) == plain_nearest(rows, (0, 100, 200, 399), 5)
    empty = spark.createDataFrame([], "obj long")
    assert successors.exact_knn(ds, empty, 5).count() == 0


@pytest.mark.parametrize("name", ["knn_topb", "embedding_knn"])
def test_searches_ask_from_the_query_set(spark, sf, name):
    got = engine.QUERIES[name](spark, sf).collect()
    assert got and all(r.obj % 100 == 0 for r in got)


def test_lattice_writes_no_counts(spark, monkeypatch):
    """No table on the way to the concepts has more rows than the relation."""
    from waypath.operators import lattice

    r = np.random.default_rng(5)
    rows = [(o, int(x)) for o in range(3000) for x in r.choice(300, 8, replace=False)]
    ds = AssocDataset.from_sets(spark.createDataFrame(rows, "obj long, feat long"), "obj", "feat")
    sizes, real = [], lattice.written

    def counted(df, *what):
        out = real(df, *what)
        sizes.append(out.count())
        return out

    monkeypatch.setattr(lattice, "written", counted)
    have = {}
    for o, f in rows:
        have.setdefault(f, set()).add(o)
    pairs = {(f, g): len(have[f] & have[g]) for f in have for g in have if f < g}
    want = sorted((n for n in pairs.values() if n), reverse=True)[5 * len(have) - 1]
    assert lattice.pair_support(ds) == want
    lat = lattice.build_concepts(ds, want)
    assert max(sizes[:-1]) <= len(rows)  # the last table is the extents
    got = {tuple(c.intent): c.support for c in lat.concepts.collect()}
    assert {k: n for k, n in got.items() if len(k) == 2} == {k: n for k, n in pairs.items() if n >= want}
    assert {k: n for k, n in got.items() if len(k) == 1} == {(f,): len(s) for f, s in have.items() if len(s) >= want}


def test_distance_of_long_arrays_is_not_quadratic(spark):
    """Two profiles of 30,000 features: a search of each feature in the other profile would take minutes."""
    import time

    from pyspark.sql import functions as F
    from waypath.functions.columns import soergel

    n = 30_000
    seq = lambda start: F.sequence(F.lit(start), F.lit(start + n - 1)).cast("array<bigint>")
    df = spark.range(4).select(seq(0).alias("fa"), seq(n // 2).alias("fb"), F.array_repeat(F.lit(1.0), n).alias("va"), F.array_repeat(F.lit(2.0), n).alias("vb"))
    began = time.time()
    got = {round(r[0], 9) for r in df.repartition(2).select(soergel("fa", "va", "fb", "vb")).collect()}
    assert got == {round(1 - (n // 2) / (3 * n - n // 2), 9)}
    assert time.time() - began < 20


@pytest.mark.parametrize("name", ["ebf_grid", "kcnn_m"])
def test_rows_come_from_a_given_table(spark, sf, name):
    df = engine.QUERIES[name](spark, sf)
    assert any(f.endswith("orders.parquet") for f in df.inputFiles())
    assert df.count() > 1


def test_walk_broadcasts_no_relation(spark, monkeypatch):
    """The relation is small as a file and large in memory: no join of the walk may broadcast it, however small its file."""
    from waypath.operators import lattice

    plans, real = [], successors.written

    def seen(df, *what):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return real(df, *what)

    ds, rows = weighted(spark)
    ds = ds.kept()
    lat = lattice.build_concepts(ds, 1)
    monkeypatch.setattr(successors, "written", seen)
    got = successors.nna(lat, ds, spark.createDataFrame([(0,), (100,)], "obj long"), 4)
    have = {}
    for o, f, _ in rows:
        have.setdefault(o, set()).add(f)
    for a in (0, 100):
        want = sorted((-len(have[a] & have[o]) / len(have[a] | have[o]), o) for o in have if o != a and have[a] & have[o])[:4]
        assert [(r.nbr, round(r.jaccard, 9)) for r in sorted(got.where(f"obj = {a}").collect(), key=lambda r: r.rnk)] == [(o, round(-j, 9)) for j, o in want]
    assert any("strategy=merge" in p for p in plans)


@pytest.mark.parametrize("theta", [0.3, 0.5, 0.8])
def test_near_profiles_tell_copies_once(spark, monkeypatch, theta):
    """Against all pairs, in many small rounds; a group of 200 equal profiles gives 199 rows beside its links."""
    monkeypatch.setattr(distance, "SENT_ROWS", 300)
    monkeypatch.setattr(distance, "MET_AT_ONCE", 50)
    r = np.random.default_rng(4)
    prof = {o: {int(f) * 7919 - 40: float(r.integers(1, 4)) for f in r.choice(25, r.integers(1, 12), replace=False)} for o in range(150)}
    prof |= {o: dict(prof[7]) for o in range(1000, 1199)}
    rows = [(o, sorted(p), [p[f] for f in sorted(p)]) for o, p in prof.items()]
    first = {}
    for o in sorted(prof):
        first.setdefault(tuple(sorted(prof[o].items())), o)
    rep = {o: first[tuple(sorted(p.items()))] for o, p in prof.items()}
    want = set()
    for a in prof:
        for b in prof:
            if a < b and rep[a] == a and rep[b] in (a, b):
                both = [f for f in prof[a] if f in prof[b]]
                s = sum(min(prof[a][f], prof[b][f]) for f in both)
                d = 1 - s / (sum(prof[a].values()) + sum(prof[b].values()) - s)
                if both and d <= theta + 1e-12:
                    want.add((a, b, len(both), round(d, 9)))
    got = distance.near_profiles(spark.createDataFrame(rows, "obj long, feats array<bigint>, vals array<double>"), theta)
    got = [(x.a, x.b, x.width, round(x.dist, 9)) for x in got.collect()]
    assert sorted(got) == sorted(want) and sum(a == 7 and b >= 1000 for a, b, *_ in got) == 199


def test_term_profiles(spark):
    """Words of a row counted in place; rows without a word or an id have no profile."""
    docs = spark.createDataFrame([(1, "two two Three"), (2, ""), (3, None), (None, "word"), (4, "three")], "doc_id long, text string")
    got = {r.obj: sorted(r.vals) for r in text.term_profiles(docs, "doc_id", text.tokenize("text")).collect()}
    assert got == {1: [1.0, 2.0], 4: [1.0]}


def test_nearest_vectors_in_rounds(spark, monkeypatch):
    """As the join of exploded vectors gives them, with nulls, NaN, zeros, short and opposite vectors; more are asked than one round sends."""
    monkeypatch.setattr(successors, "VECTORS_SENT", 7)
    r = np.random.default_rng(6)
    rows = [(i, [float(x) if k > 2 else [0.0, None, float("nan")][k] for x, k in zip(r.integers(-4, 5, 6) / 4, r.integers(0, 12, 6))]) for i in range(300)]
    rows += [(300, None), (301, []), (302, [0.0] * 6), (303, [1.0]), (304, [-1.0]), (None, [1.0] * 6)]
    v = spark.createDataFrame(rows, "obj long, x array<float>")
    flat = [(o, 2 * d + (y < 0), abs(y)) for o, x in rows if o is not None for d, y in enumerate(x or []) if y and y == y]
    asked = [*range(0, 300, 10), 302, 303, 304, 999]
    want = plain_nearest(flat, [a for a in asked if any(o == a for o, *_ in flat)], 5)
    got = as_set(successors.nearest_vectors(v, spark.createDataFrame([(a,) for a in asked], "obj long"), 5))
    assert got == want and len(got) > 100


def test_concepts_without_extents(spark):
    """The same concepts, and nothing written but concepts."""
    from waypath.operators import lattice

    r = np.random.default_rng(8)
    rows = [(o, int(x)) for o in range(200) for x in r.choice(20, 6, replace=False)]
    ds = AssocDataset.from_sets(spark.createDataFrame(rows, "obj long, feat long"), "obj", "feat")
    whole, lean = (lattice.build_concepts(ds, 15, extents=x) for x in (True, False))
    as_rows = lambda lat: sorted((c.cid, tuple(c.intent), c.n_feat, c.support) for c in lat.concepts.collect())
    assert lean.extents is None and as_rows(whole) == as_rows(lean) and len(as_rows(lean)) > 20
    assert lattice.lattice_stats(whole).collect() == lattice.lattice_stats(lean).collect()


def test_heads_and_longest_concepts_without_extents(spark, monkeypatch):
    """The first places of each list and each object's longest concept as the whole lattice gives them; with a feature that all share too."""
    from waypath.operators import lattice

    r = np.random.default_rng(9)
    rows = [(o, int(x)) for o in range(200) for x in r.choice(20, 6, replace=False)]
    monkeypatch.setattr(lattice, "MOST_SENT", 10)
    for more in ([], [(o, 30) for o in range(200)]):
        ds = AssocDataset.from_sets(spark.createDataFrame(rows + more, "obj long, feat long"), "obj", "feat")
        whole, lean = lattice.build_concepts(ds, 15), lattice.build_concepts(ds, 15, top=4)
        rows_of = lambda df: sorted(tuple(x) for x in df.collect())
        assert lean.extents is None and rows_of(lattice.rank_extents(whole, top=4)) == rows_of(lattice.rank_extents(lean, top=4))
        assert rows_of(lattice.longest_concept(whole)) == rows_of(lattice.longest_concept(lean))
        with pytest.raises(ValueError):
            lattice.rank_extents(lean, top=5)


def test_object_lists_are_not_written(spark, monkeypatch):
    """Lists come ranked from the ranges: no table on the way has more rows than there are objects and frequent features."""
    from pyspark.sql import functions as F
    from waypath.operators import lattice

    r = np.random.default_rng(10)
    rows = [(o, int(x)) for o in range(200) for x in r.choice(20, r.integers(3, 9), replace=False)] + [(o, 30) for o in range(200)]
    ds = AssocDataset.from_sets(spark.createDataFrame(rows, "obj long, feat long"), "obj", "feat")
    lat = lattice.build_concepts(ds, 15)
    want = lattice.rank_extents(lat).join(lat.concepts.select("cid", F.col("intent").cast("string").alias("intent")), "cid").select("intent", "obj", "n_obj_feat", "rnk")
    sizes, real = [], lattice.written

    def counted(df, *what):
        out = real(df, *what)
        sizes.append(out.count())
        return out

    monkeypatch.setattr(lattice, "written", counted)
    got = lattice.listed_extents(ds, 15).withColumn("intent", F.col("intent").cast("string"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and max(sizes) <= 200


def test_a_thread_drops_only_its_own_tables(spark):
    """Searches run side by side: one that ends must not remove what another still reads."""
    from concurrent.futures import ThreadPoolExecutor

    from waypath import tables

    place = tables.mark()
    with ThreadPoolExecutor(1) as other:
        theirs = other.submit(lambda: tables.written(spark.range(3).toDF("obj"))).result()
        mine = tables.written(spark.range(4).toDF("obj"))
        tables.drop_since(place)
        assert theirs.count() == 3 and not tables.alive(mine)


def test_settings_of_a_sweep_run_side_by_side(spark, monkeypatch):
    """Three searches wait for each other, so one after another would not end; a small file of many rows is not broadcast meanwhile."""
    import threading

    from pyspark.sql import functions as F
    from waypath import tables, workloads
    from waypath.plans.spec import SearchSpec

    meet = threading.Barrier(3)
    many = tables.written(spark.range(200_000).toDF("obj").coalesce(1))
    plans = []

    def searched(ds, pairs, spec, *more, **other):
        meet.wait(60)
        plans.append(spark.range(10**7).toDF("obj").join(many, "obj")._jdf.queryExecution().executedPlan().toString())
        return tables.written(spark.range(spec.k).toDF("pair_id"))

    monkeypatch.setattr(workloads, "find_paths", searched)
    specs = {(k,): SearchSpec(theta=0.5, k=k) for k in (2, 3, 4)}
    got = workloads._runs(spark, ("side by side",), specs, lambda: (None, None, None, None, 2), ("k",))
    assert {(r.k, r.n) for r in got.groupBy("k").agg(F.count("*").alias("n")).collect()} == {(2, 2), (3, 3), (4, 4)}
    assert len(plans) == 3 and not any("BroadcastHashJoin" in p for p in plans)


def test_a_large_frontier_is_asked_in_rounds(spark, monkeypatch):
    """More associations than are sent at once, some shares without an object: nothing is joined, and the nearest are the same."""
    monkeypatch.setattr(successors, "MOST_SENT", 40)
    monkeypatch.setattr(successors, "AT_ONCE", 3000)
    monkeypatch.setattr(successors, "hammock_pairs", lambda *a, **k: pytest.fail("joined"))
    ds, rows = weighted(spark)
    asked = [*range(0, 400, 8), 5000]
    f = spark.createDataFrame([(a,) for a in asked], "obj long")
    assert as_set(successors.exact_knn(ds, f, 5)) == plain_nearest(rows, asked[:-1], 5)


def plain_net(rows, hashes, radii):
    """Centres of each level: objects in the order of hashes, each further than the radius from those taken before it."""
    prof, levels, taken = {}, [], []
    for o, f, v in rows:
        prof.setdefault(o, {})[f] = v
    total = {o: sum(p.values()) for o, p in prof.items()}

    def dist(a, b):
        s = sum(min(v, prof[b][f]) for f, v in prof[a].items() if f in prof[b])
        return 1 - s / (total[a] + total[b] - s)

    for r in radii:
        for o in sorted(prof, key=lambda o: (hashes[o], o)):
            if o not in taken and all(dist(o, c) > r + 1e-12 for c in taken):
                taken.append(o)
        levels.append((set(taken), {o: min((0.0 if o == c else round(dist(o, c), 12), c) for c in taken) for o in prof}))
    return levels


@pytest.mark.parametrize("sent", [4_000_000, 300])
def test_cover_tree_writes_no_pairs(spark, monkeypatch, sent):
    """Nets in one block and in many are those of a plain walk, and no table on the way has more rows than the relation."""
    from pyspark.sql import functions as F

    monkeypatch.setattr(successors, "TREE_SENT", sent)
    monkeypatch.setattr(distance, "MET_AT_ONCE", 400)
    ds, rows = weighted(spark)
    rows += [(900, 77, 2.0), (901, 78, 3.0), (902, 78, 3.0)]  # one alone, two equal ones
    ds = AssocDataset(spark.createDataFrame(rows, "obj long, feat long, val double"))
    sizes, real = [], successors.written

    def counted(df, *what):
        out = real(df, *what)
        sizes.append(out.count())
        return out

    monkeypatch.setattr(successors, "written", counted)
    index = successors.CoverTreeIndex.build(ds, levels=3, base=1.4)
    assert max(sizes) <= len(rows) < 3000
    hashes = {r.obj: r.h for r in ds.objects().select("obj", F.xxhash64("obj").alias("h")).collect()}
    for i, (centres, homes) in enumerate(plain_net(rows, hashes, index.radii)):
        own = index.net.where(F.col("level") == i).collect()
        assert {r.centre for r in own} == centres and len(own) == len(homes)
        assert {r.obj: (round(r.dist, 12), r.centre) for r in own} == homes
    assert all(r.not_nested == r.not_covered == r.too_close == 0 for r in index.check().collect())
    f = spark.createDataFrame([(0,), (100,), (200,), (399,), (900,), (902,), (5000,)], "obj long")
    for theta in (0.95, 0.6, 0.03):
        want = {(a, o, d, k) for a, o, d, k in plain_nearest(rows, (0, 100, 200, 399, 900, 902), 5) if d <= theta + 1e-12}
        assert as_set(index.knn(f, 5, theta)) == want
    assert index.knn(spark.createDataFrame([], "obj long"), 5, 0.9).count() == 0


def test_cover_tree_check_sees_faults(spark):
    from pyspark.sql import functions as F

    ds, _ = weighted(spark, n=60)
    index = successors.CoverTreeIndex.build(ds, levels=2)
    n = ds.objects().count()
    own = index.profiles.select("obj")
    net = own.select(F.lit(0).alias("level"), F.col("obj").alias("centre"), "obj", F.lit(0.0).alias("dist")).union(index.net.where("level = 1 AND obj <> centre"))
    a, b = successors.CoverTreeIndex(ds, net, index.radii, index.profiles).check().orderBy("level").collect()
    assert a.too_close == distance.hammock_pairs(ds, theta=index.radii[0]).count() > 0
    assert b.not_nested == n - index.net.where("level = 1 AND obj <> centre").select("centre").distinct().count()
    assert b.not_covered == n - index.net.where("level = 1 AND obj <> centre").count() > 0


def islands(spark):
    """Two lines of objects that share no feature; the ids of one are even."""
    rows = [(2 * i + side, 1000 * side + i + k, float(1 + (i + k) % 3)) for side in (0, 1) for i in range(12) for k in range(3)]
    return AssocDataset(spark.createDataFrame(rows, "obj long, feat long, val double"))


@pytest.mark.parametrize("sent", [4_000_000, 300])
def test_links_by_task_are_the_network(spark, monkeypatch, sent):
    from waypath.operators import network

    monkeypatch.setattr(successors, "TREE_SENT", sent)
    ds, _ = weighted(spark)
    rows = lambda df: sorted((r.a, r.b, round(r.dist, 9)) for r in df.collect())
    assert rows(network.links_by_task(ds, 0.7)) == rows(network.materialize_network(ds, theta=0.7)) != []
    assert network.links_by_task(AssocDataset(ds.rel.limit(0)), 0.7).count() == 0


def test_capped_gap_searches_joined_pairs_only(spark, sf, monkeypatch):
    """The same rows as from all pairs; no pair of two islands is searched."""
    from waypath.operators import network
    from waypath.plans import measures

    ds = islands(spark)
    asked, real = [], engine.find_paths

    def noted(ds, pairs, *more, **named):
        asked.extend((r.src, r.dst) for r in pairs.collect())
        return real(ds, pairs, *more, **named)

    monkeypatch.setattr(engine, "_kept", lambda *_: ds)
    monkeypatch.setattr(engine, "find_paths", noted)
    got = {tuple(r) for r in engine.QUERIES["capped_cost_gap"](spark, sf).collect()}
    assert asked and all(a % 2 == b % 2 for a, b in asked)
    pairs = engine._pairs(ds)
    assert pairs.where("src % 2 <> dst % 2").count() > 0
    p = real(ds, pairs, engine.SearchSpec(theta=engine.THETA, b=engine.CAP, successors="exact"))
    best = network.dijkstra_rounds(network.materialize_network(ds, theta=engine.THETA), pairs)
    want = measures.cost_gap(p, best).collect()
    assert got == {(r.pair_id, round(r.cost, 9), round(r.best, 9), round(r.gap, 9)) for r in want} and want


@pytest.mark.parametrize("name", ["generator_diff", "lattice_neighbours"])
def test_generators_ask_from_every_part(spark, sf, name):
    """All parts that share a concept or a supplier with another one, not those of a query set."""
    rel = engine._kept(spark, sf, "parts_by_suppliers").rel
    met = rel.join(rel.select("feat", rel["obj"].alias("other")), "feat").where("obj <> other").select("obj").distinct()
    got = engine.QUERIES[name](spark, sf).select("obj").distinct()
    if name == "generator_diff":
        assert {r.obj for r in got.collect()} == {r.obj for r in met.collect()}
    else:
        held = engine._lattice(spark, sf)[1].extents.select("obj").distinct()
        assert {r.obj for r in got.collect()} == {r.obj for r in held.collect()} and got.where("obj % 100 <> 0").count() > 0


@pytest.mark.parametrize("sent,minsup", [(100_000, 1), (0, 20)])
def test_the_walk_of_every_object(spark, monkeypatch, sent, minsup):
    """In one round and in many, few pairs at a time: a plain walk by sizes of shared concepts gives the same."""
    from waypath.operators import lattice

    monkeypatch.setattr(successors, "MOST_SENT", sent)
    monkeypatch.setattr(successors, "LARGE_SENT", 400 if sent == 0 else 2_000_000)
    monkeypatch.setattr(successors, "AT_ONCE", 700)
    monkeypatch.setattr(successors, "PAIRS_AT_ONCE", 9)
    monkeypatch.setattr(successors, "MARKED", 100)
    ds, rows = weighted(spark, n=150, f=12)
    lat, limit = lattice.build_concepts(ds, minsup), 4
    have, of, extent = {}, {}, {}
    for o, f, _ in rows:
        have.setdefault(o, set()).add(f)
    size = {r.cid: r.n_feat for r in lat.concepts.collect()}
    for r in lat.extents.collect():
        of.setdefault(r.obj, set()).add(r.cid)
        extent.setdefault(r.cid, set()).add(r.obj)
    want = set()
    for o in of:
        levels = sorted({size[c] for c in of[o]}, reverse=True)
        met, given = set(), set()
        for t, left in zip(levels, [*levels[1:], None]):
            met |= {x for c in of[o] if size[c] == t for x in extent[c]} - {o}
            jac = {x: len(have[o] & have[x]) / len(have[o] | have[x]) for x in met}
            given = {x for x in met if left is None or jac[x] >= left / len(have[o])}
            if len(given) >= limit:
                break
        want |= {(o, x, round(jac[x], 12), i + 1) for i, x in enumerate(sorted(given, key=lambda x: (-jac[x], x))[:limit])}
    got = successors.nna(lat, ds, ds.objects(), limit).collect()
    assert {(r.obj, r.nbr, round(r.jaccard, 12), r.rnk) for r in got} == want


@pytest.mark.parametrize("each", [0.0, 1.7])
def test_far_profiles_are_not_measured(monkeypatch, each):
    """Sums over groups of features tell most pairs apart, few or many groups; no near pair is lost, whatever the weights."""
    import pyarrow as pa

    r = np.random.default_rng(11)
    feats = [sorted({*r.choice(40, 20, replace=False), *(1000 + r.choice(400, 20, replace=False))}) for _ in range(120)]
    feats += [f[:-3] + [5000 + i] for i, f in enumerate(feats[:40])]
    vals = [[float(x) for x in r.uniform(0.1, 3, len(f))] for f in feats[:120]]
    vals += [v[:len(f)] for f, v in zip(feats[120:], [v[:-3] + [0.3] for v in vals[:40]])]
    rows = sorted((sum(v), o, [int(x) for x in f], v) for o, (f, v) in enumerate(zip(feats, vals)))
    t = pa.table({"obj": pa.array([x[1] for x in rows], pa.int64()), "total": [x[0] for x in rows], "feats": pa.array([x[2] for x in rows], pa.list_(pa.int64())), "vals": [x[3] for x in rows]})
    monkeypatch.setattr(distance, "GROUPS_EACH", each)
    monkeypatch.setattr(distance, "SUMS_AT_ONCE", 200)
    measured, real = [], np.add.reduceat
    sent = type("Sent", (), {"value": distance._offered(t, 0.5)})
    monkeypatch.setattr(distance.np, "add", type("Add", (), {"reduceat": staticmethod(lambda x, at: measured.append(len(at)) or real(x, at))}))
    got = {(a, b): round(d, 9) for x in distance._measured(sent, 0.5)(iter(t.to_batches(max_chunksize=50))) for a, b, d in zip(*(x.column(c).to_pylist() for c in ("a", "b", "dist")))}
    prof, want = [dict(zip(f, v)) for f, v in zip(feats, vals)], {}
    for a in range(len(prof)):
        for b in range(a + 1, len(prof)):
            s = sum(min(v, prof[b][f]) for f, v in prof[a].items() if f in prof[b])
            d = 1 - s / (sum(vals[a]) + sum(vals[b]) - s)
            want |= {(a, b): round(d, 9)} if d <= 0.5 else {}
    assert got == want and len(want) >= 40
    assert sum(measured) < 12 * len(want) or not each
