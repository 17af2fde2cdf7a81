"""Lattices, generators and searches against brute force on a seeded relation, and the trends the experiments report."""

import heapq
import math
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_engine import data, five, ring

from waypath.functions import text
from waypath.operators import distance, lattice, network, successors, truncate
from waypath.operators.dataset import sample_pairs
from waypath.plans import measures
from waypath.plans.search import find_paths
from waypath.plans.spec import SearchSpec
from waypath.sources import sinks

N, FEATS, THETA, B = 60, 14, 0.78, 20


@pytest.fixture(scope="module")
def sets():
    rng = np.random.default_rng(5)
    return {o: {int(f): int(rng.integers(1, 5)) for f in rng.choice(FEATS, rng.integers(3, 7), replace=False)} for o in range(N)}


@pytest.fixture(scope="module")
def ds(spark, sets):
    return data(spark, sets).kept()


@pytest.fixture(scope="module")
def lat(ds):
    return lattice.build_concepts(ds, 8)


def soergel(x, y):
    fs = set(x) | set(y)
    return 1 - sum(min(x.get(f, 0), y.get(f, 0)) for f in fs) / sum(max(x.get(f, 0), y.get(f, 0)) for f in fs)


def jac(x, y):
    return len(set(x) & set(y)) / len(set(x) | set(y))


def closed_sets(sets, minsup):
    """{intent: extent} by closing every set of features."""
    out = {}
    for k in range(1, FEATS + 1):
        some = False
        for fs in combinations(range(FEATS), k):
            ext = [o for o, s in sets.items() if s.keys() >= set(fs)]
            if len(ext) >= minsup:
                some = True
                out[tuple(sorted(set.intersection(*[set(sets[o]) for o in ext])))] = ext
        if not some:
            return out
    return out


def test_concepts_by_brute_force(ds, lat, sets):
    want = closed_sets(sets, 8)
    assert {tuple(r.intent): r.support for r in lat.concepts.collect()} == {i: len(e) for i, e in want.items()}
    intents = {r.cid: tuple(r.intent) for r in lat.concepts.collect()}
    assert [intents[c] for c in sorted(intents)] == sorted(want)
    held = {}
    for r in lat.extents.collect():
        held.setdefault(intents[r.cid], []).append(r.obj)
    assert {i: sorted(e) for i, e in held.items()} == want
    edges = {(intents[r.cid], intents[r.child_cid]) for r in lattice.build_edges(lat).collect()}
    below = {(p, c) for p in want for c in want if set(c) < set(p)}
    assert edges == {(p, c) for p, c in below if not any((p, m) in below and (m, c) in below for m in want)}


def test_concepts_by_frequent_patterns(spark, ds, lat):
    """Spark's frequent item sets without those that a larger one of equal support holds."""
    from pyspark.ml.fpm import FPGrowth

    baskets = ds.rel.groupBy("obj").agg(F.collect_set("feat").alias("items"))
    found = [(frozenset(r["items"]), r.freq) for r in FPGrowth(minSupport=7.5 / N, minConfidence=1.0).fit(baskets).freqItemsets.collect()]
    closed = {(tuple(sorted(i)), n) for i, n in found if not any(i < j and n == m for j, m in found)}
    assert closed == {(tuple(r.intent), r.support) for r in lat.concepts.collect()}


def test_support_of_the_clique_size(spark):
    ds = five(spark)
    assert sorted(r.intent for r in lattice.build_concepts(ds, "clique", clique=5).concepts.collect()) == sorted(r.intent for r in lattice.build_concepts(ds, 5).concepts.collect())
    with pytest.raises(ValueError, match="clique size"):
        lattice.build_concepts(ds, "clique")


def test_saved_lattice_gives_the_same_neighbours(spark, ds, lat, tmp_path):
    lat.save(str(tmp_path / "lattice"))
    again = lattice.Lattice.load(spark, str(tmp_path / "lattice"), lat.minsup)
    rows = lambda x: sorted(map(str, successors.kcnn(x, ds, ds.objects(), 2, 5).collect()))
    assert rows(again) == rows(lat) != []


def longest(sets, minsup=8):
    """The object list of each object's longest concept, most features first."""
    closed = closed_sets(sets, minsup)
    out = {}
    for o in sets:
        mine = [(-len(i), -len(e), i) for i, e in closed.items() if o in e]
        if mine:
            ext = closed[min(mine)[2]]
            out[o] = sorted(ext, key=lambda x: (-len(sets[x]), x))
    return out


def tries(sets, size, b, order="features_desc"):
    """{object: [(members, score)]}: the best b combinations of the first m others."""
    m = successors.min_candidates(size, b)
    out = {}
    for o, ext in longest(sets).items():
        others = [x for x in ext if x != o]
        if order == "closest":
            others.sort(key=lambda x: (round(soergel(sets[o], sets[x]), 12), x))
        cand = others[:m]
        scored = [(round(sum(soergel(sets[o], sets[x]) for x in c) / size, 12), n, c) for n, c in enumerate(combinations(cand, size))]
        out[o] = [(tuple(sorted(c)), s) for s, _, c in sorted(scored)[:b]]
    return out


def linked(sets, a, b):
    return soergel(sets[a], sets[b]) <= THETA + 1e-12


def is_clique(sets, members):
    return all(linked(sets, a, b) for a, b in combinations(members, 2))


def members_of(df):
    return {(r.obj, tuple(r.members)): pytest.approx(r.score) for r in df.collect()}


@pytest.mark.parametrize("k,arity,order", [(2, "printed", "features_desc"), (3, "printed", "features_desc"), (4, "printed", "closest"), (2, "with_source", "features_desc"), (4, "with_source", "features_desc")])
def test_near_cliques_by_brute_force(ds, lat, sets, k, arity, order):
    size = k if arity == "printed" else k - 1
    want = tries(sets, size, B, order)
    got = successors.kcnn(lat, ds, ds.objects(), k, B, arity, order)
    assert members_of(got) == {(o, c): s for o, cs in want.items() for c, s in cs}
    good = {(o, c): s for o, cs in want.items() for c, s in cs if is_clique(sets, (o, *c))}
    assert 0 < len(good) < sum(map(len, want.values()))
    assert members_of(successors.verify_cliques(ds, got, theta=THETA)) == good
    assert members_of(successors.kcnn(lat, ds, ds.objects(), k, B, arity, order, theta=THETA)) == good
    r = successors.clique_yield(ds, got, theta=THETA).first()
    assert (r.n_candidates, r.n_cliques) == (sum(map(len, want.values())), len(good))


def test_short_lists_are_filled_from_other_concepts(ds, sets):
    lat = lattice.build_concepts(ds, 2)
    short = successors.kcnn(lat, ds, ds.objects(), 2, B).groupBy("obj").count()
    full = successors.kcnn(lat, ds, ds.objects(), 2, B, fallback="next_concept").groupBy("obj").count()
    assert short.where("count < 20").count() > full.where("count < 20").count()


def test_lattice_neighbours_by_brute_force(ds, sets):
    lat = lattice.build_concepts(ds, 2)
    got = successors.nna(lat, ds, ds.objects(), 6).collect()
    for o in sets:
        want = sorted((jac(sets[o], sets[x]) for x in sets if x != o and set(sets[o]) & set(sets[x])), reverse=True)[:6]
        assert [r.jaccard for r in sorted((r for r in got if r.obj == o), key=lambda r: r.rnk)] == pytest.approx(want)
    kth = {r.obj: r.jaccard for r in successors.nna_kth(lat, ds, ds.objects(), 6).collect()}
    assert kth == {r.obj: pytest.approx(r.jaccard) for r in got if r.rnk == 6}
    assert successors.nna(lat, ds, ds.objects(), 6, bound="printed", drain=False).count() == 0


def test_lattice_cliques_by_brute_force(ds, sets):
    lat = lattice.build_concepts(ds, 2)
    m = successors.min_candidates(2, 6)
    order = {o: [r.nbr for r in sorted((r for r in rows), key=lambda r: r.rnk)] for o, rows in by(successors.nna(lat, ds, ds.objects(), m).collect(), "obj").items()}
    want = {}
    for o, cand in order.items():
        scored = sorted((round(sum(1 - jac(sets[o], sets[x]) for x in c) / 2, 12), n, c) for n, c in enumerate(combinations(cand, 2)))[:6]
        want |= {(o, tuple(sorted(c))): s for s, _, c in scored}
    assert members_of(successors.nna_cliques(lat, ds, ds.objects(), 2, 6)) == want


def by(rows, column):
    out = {}
    for r in rows:
        out.setdefault(r[column], []).append(r)
    return out


def successors_plainly(sets, k, arity):
    """{object: {other: distance}} over verified cliques, and the test of a goal link."""
    size = k if arity == "printed" else k - 1
    arcs = {o: {} for o in sets}
    for o, cs in tries(sets, size, B).items():
        for c, _ in cs:
            if is_clique(sets, (o, *c)):
                arcs[o] |= {x: soergel(sets[o], sets[x]) for x in c}
    m = successors.min_candidates(size, B)
    cand = {o: [x for x in ext if x != o][:m] for o, ext in longest(sets).items()}

    def joins(o, goal):
        if not linked(sets, o, goal):
            return False
        pool = [x for x in cand.get(o, []) if x != goal]
        return any(is_clique(sets, (o, goal, *c)) for c in combinations(pool, size - 1))

    return arcs, joins


def least_cost(arcs, joins, sets, src, dst):
    best, heap = {src: 0.0}, [(0.0, src)]
    while heap:
        g, o = heapq.heappop(heap)
        if o == dst:
            return g
        if g > best[o]:
            continue
        step = dict(arcs[o])
        if joins(o, dst):
            step[dst] = soergel(sets[o], sets[dst])
        for x, d in step.items():
            if g + d < best.get(x, math.inf):
                best[x] = g + d
                heapq.heappush(heap, (g + d, x))
    return None


@pytest.mark.parametrize("k,arity,more", [(2, "printed", {}), (4, "with_source", {}), (3, "printed", {"heuristic": "zero"}), (2, "with_source", {"mode": "mixed"})])
def test_clique_searches_by_brute_force(spark, ds, lat, sets, k, arity, more):
    rng = np.random.default_rng(k)
    ends = [tuple(map(int, rng.choice(N, 2, replace=False))) for _ in range(25)] + [(3, 3), (1, 999)]
    pairs = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(ends)], "pair_id long, src long, dst long")
    p = find_paths(ds, pairs, SearchSpec(theta=THETA, k=k, b=B, arity=arity, **more), lat, minsup=14)
    got = {r.pair_id: r for r in p.collect()}
    arcs, joins = successors_plainly(sets, k, arity)
    costs = []
    for i, (a, b) in enumerate(ends):
        want = least_cost(arcs, joins, sets, a, b) if b in sets else None
        assert got[i].outcome == ("no_path" if want is None else "found")
        assert got[i].cost == (None if want is None else pytest.approx(want))
        costs.append(want)
    assert sum(c is not None and c > 0 for c in costs) >= 2
    found = p.where("outcome = 'found' AND hops > 0")
    assert all(r.ok for r in distance.validate_paths(ds, found, theta=THETA).collect())
    assert all(r.ok for r in distance.validate_clique_paths(ds, found, theta=THETA).collect())
    size = k + 1 if arity == "printed" else k
    assert all(len(q) == size for r in found.collect() for q in r.cliques) and all(r.cost == pytest.approx(sum(r.steps)) for r in found.collect())


def nodes_explored(sets, src, dst, informed, theta):
    """Objects popped before the goal by a plain search over all links."""
    h = lambda o: soergel(sets[o], sets[dst]) if informed else 0.0
    best, closed, heap = {src: 0.0}, set(), [(0.0, 0.0, src)]
    while heap:
        _, minus, o = heapq.heappop(heap)
        if o in closed or -minus > best[o] + 1e-12:
            continue
        if o == dst:
            return len(closed)
        closed.add(o)
        for x in sets:
            d = soergel(sets[o], sets[x])
            if x not in closed and d <= theta + 1e-12 and best[o] + d < best.get(x, math.inf) - 1e-12:
                best[x] = best[o] + d
                heapq.heappush(heap, (round(best[x] + h(x), 9), -best[x], x))
    return len(closed)


def test_explored_objects_are_those_of_a_plain_search(spark, ds, sets):
    """However many objects are asked for ahead."""
    theta = 0.6
    ends = [(0, 9), (4, 31), (17, 50), (22, 41)]
    pairs = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(ends)], "pair_id long, src long, dst long")
    for heuristic, pop in (("straight", 1), ("zero", 64)):
        got = {r.pair_id: r.nodes_explored for r in find_paths(ds, pairs, SearchSpec(theta=theta, successors="exact", b=1000, heuristic=heuristic, pop=pop)).collect()}
        assert got == {i: nodes_explored(sets, a, b, heuristic == "straight", theta) for i, (a, b) in enumerate(ends)}


def test_budgets_end_a_search(spark, ds):
    pairs = spark.createDataFrame([(1, 0, 9)], "pair_id long, src long, dst long")
    few = SearchSpec(theta=0.6, successors="exact", link_goal=False, max_nodes=1)
    assert find_paths(ds, pairs, few).first().outcome == "budget"
    assert find_paths(ds, pairs, few.but(max_nodes=1000, max_rounds=1, pop=1)).first().outcome == "budget"


def test_a_search_of_one_object_ends_at_once(spark, ds):
    pairs = spark.createDataFrame([(1, 5, 5)], "pair_id long, src long, dst long")
    r = find_paths(ds, pairs, SearchSpec(theta=0.6, successors="exact")).first()
    assert (r.outcome, r.hops, r.cost, r.nodes, r.cliques) == ("found", 0, 0.0, [5], [])


def test_widths_lengthen_and_cliques_shorten(spark, ds, lat):
    """Links by width: the wider, the fewer; a path of width one needs no more hops than one of width three."""
    pairs = sample_pairs(ds, 12)
    hops = {}
    for spec in (SearchSpec.simple(successors="exact", b=1000), SearchSpec(width=3, successors="exact", b=1000)):
        hops[spec.width] = {r.pair_id: r.hops for r in find_paths(ds, pairs, spec).where("outcome = 'found'").collect()}
    assert all(hops[1][i] <= h for i, h in hops[3].items())


def test_sampled_pairs_are_as_many_as_asked(ds, sets):
    links = distance.hammock_pairs(ds, theta=0.9)
    close = {(r.a, r.b) for r in links.collect()}
    free = sum((a, b) not in close for a, b in combinations(sets, 2))
    got = [(r.src, r.dst) for r in sample_pairs(ds, 30, avoid=links).collect()]
    assert len(got) == len(set(got)) == 30 <= free and not any((min(p), max(p)) in close for p in got)
    assert got == [(r.src, r.dst) for r in sample_pairs(ds, 30, avoid=links).collect()]


def test_union_of_dropped_features_is_tightest(ds, sets):
    td = truncate.truncate(ds, 22)
    pairs = distance.hammock_pairs(ds, theta=1.0).select("a", "b")
    t = {(r.a, r.b): r.t for r in truncate.dropped_union(ds, td, pairs).collect()}
    kept = {r.feat for r in td.kept.rel.select("feat").distinct().collect()}
    assert t == {(a, b): len((set(sets[a]) | set(sets[b])) - kept) for a, b in t}
    true = {(r.a, r.b): r.dist for r in distance.pair_distance(ds, pairs).collect()}
    for how in ("union", "sum", "max", "min"):
        m = truncate.mixed_distance(td, pairs, t_mode=how, union_counts=truncate.dropped_union(ds, td, pairs) if how == "union" else None).collect()
        assert all(r.mixed <= true[r.a, r.b] + 1e-12 for r in m)


def test_adjusted_chances(spark):
    rng = np.random.default_rng(1)
    p = np.round(rng.random(400) ** 2, 2)
    df = spark.createDataFrame([(i, float(x), i % 3) for i, x in enumerate(p)], "id long, p double, part int")

    def plain(v):
        order = np.argsort(-v, kind="stable")
        q, low = np.zeros(len(v)), 1.0
        for i in order:
            low = min(low, v[i] * len(v) / (v <= v[i]).sum())
            q[i] = low
        return q

    for ranges in (1, 7, 64):
        got = {r.id: r.q for r in measures.benjamini_hochberg(df, ranges=ranges).collect()}
        assert [got[i] for i in range(400)] == pytest.approx(list(plain(p)))
    got = {r.id: r.q for r in measures.benjamini_hochberg(df, by=["part"]).collect()}
    for part in range(3):
        own = [i for i in range(400) if i % 3 == part]
        assert [got[i] for i in own] == pytest.approx(list(plain(p[own])))
    assert measures.benjamini_hochberg(df.limit(0)).count() == 0


def test_log_factorials_and_tails():
    n = np.arange(3000)
    assert np.allclose(measures.log_factorial(n), [math.lgamma(i + 1) for i in n], rtol=1e-13, atol=1e-11)
    exact = lambda x, a, b, f: sum(math.comb(a, i) * math.comb(f - a, b - i) for i in range(x, min(a, b) + 1) if 0 <= b - i <= f - a) / math.comb(f, b)
    cases = [(x, a, b, 30) for a in (1, 7, 20, 30) for b in (1, 12, 29) for x in range(0, 13)]
    got = measures.tail(*(np.array(c) for c in zip(*[c[:3] for c in cases])), 30)
    assert got == pytest.approx([exact(*c) for c in cases], abs=1e-12)


def test_least_costs_have_no_cap_on_hops(spark):
    chain = data(spark, {i: {i: 1, i + 1: 1} for i in range(20)})
    e = network.materialize_network(chain, theta=0.7)
    hops = {r.node: r.hops for r in network.bfs_hops(e, spark.createDataFrame([(0,)], "src long")).collect()}
    assert hops == {i: i for i in range(20)}
    assert network.bfs_hops(e, spark.createDataFrame([(0,)], "src long"), 3).count() == 4


def test_cover_tree_search_is_the_exact_search(spark):
    ds = ring(spark)
    pairs = spark.createDataFrame([(1, 0, 6), (2, 7, 1)], "pair_id long, src long, dst long")
    cost = lambda s: [r.cost for r in find_paths(ds, pairs, SearchSpec(theta=0.7, successors=s)).orderBy("pair_id").collect()]
    assert cost("cover") == cost("exact")


def test_cleaned_terms(spark):
    df = spark.createDataFrame([("The genes ACGTACGT were being tested in 42 mice; the genes!",), (None,)], "t string")
    stop = text.stop_words()
    terms = text.drop_stopwords(text.drop_sequences(text.tokenize(F.col("t"))), stop)
    assert [r.x for r in df.select(F.transform(terms, text.light_stem).alias("x")).collect()] == [["gen", "test", "mice", "gen"], []]


def test_exports(spark, ds, tmp_path):
    pairs = spark.createDataFrame([(1, 0, 9), (2, 1, 999)], "pair_id long, src long, dst long")
    p = find_paths(ds, pairs, SearchSpec(theta=0.9, successors="exact"))
    sinks.export_paths(p, str(tmp_path / "j"))
    sinks.export_paths(p, str(tmp_path / "c"), "csv")
    back = {r.pair_id: r for r in spark.read.schema(p.schema).json(str(tmp_path / "j")).collect()}
    assert back[1].nodes == p.where("pair_id = 1").first().nodes and back[2].outcome == "no_path"
    flat = spark.read.option("header", True).csv(str(tmp_path / "c")).where("pair_id = 1").first()
    assert flat.nodes == ">".join(map(str, back[1].nodes))
    spark.sql("DROP TABLE IF EXISTS waypath_test_rel")
    sinks.save_bucketed(ds.rel, "waypath_test_rel", 4)
    t = spark.table("waypath_test_rel")
    assert t.count() == ds.rel.count()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    plan = t.alias("x").join(t.alias("y"), "feat")._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "Exchange" not in plan.split("Initial Plan")[0]
    spark.sql("DROP TABLE waypath_test_rel")


@pytest.mark.parametrize("bound", [{"theta": 0.5}, {"theta": 0.8}, {"width": 3}])
def test_prefixes_lose_no_pair(ds, bound):
    rows = lambda x: sorted((r.a, r.b, r.width, round(r.dist, 9)) for r in x.collect())
    assert rows(distance.hammocks_by_prefix(ds, **bound)) == rows(distance.hammock_pairs(ds, **bound)) != []


def test_concepts_of_hashed_features(spark, sets):
    """Feature ids anywhere in 64 bits, the smallest included."""
    ids = [-(2**63), -(2**63) + 1, -(2**62) - 5, -7, 0, 3, 2**61, 2**62, 2**63 - 1, -(2**61), 11, 12, -(2**62), 99]
    moved = {o: {ids[f]: v for f, v in fs.items()} for o, fs in sets.items()}
    got = lattice.build_concepts(data(spark, moved), 8).concepts.collect()
    want = {tuple(sorted(ids[f] for f in i)): len(e) for i, e in closed_sets(sets, 8).items()}
    assert {tuple(r.intent): r.support for r in got} == want
