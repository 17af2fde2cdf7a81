import math

import pytest
from pyspark.sql import functions as F

from waypath.operators import distance, lattice, network, successors, truncate
from waypath.operators.dataset import AssocDataset
from waypath.plans import measures
from waypath.plans.search import find_paths
from waypath.plans.spec import SearchSpec


def data(spark, sets):
    """An association dataset from {object: {feature: weight}}."""
    rows = [(o, f, float(v)) for o, fs in sets.items() for f, v in fs.items()]
    return AssocDataset(spark.createDataFrame(rows, "obj long, feat long, val double"))


A, B, C, D, E = range(1, 6)
FIVE = {1: [A, D, E], 2: [A, B], 3: [A, B], 4: [A, B], 5: [A, B], 6: [C, D, E], 7: [C, D, E], 8: [C, D, E], 9: [C, D, E]}


def five(spark):
    return data(spark, {o: dict.fromkeys(fs, 1) for o, fs in FIVE.items()})


@pytest.mark.parametrize("minsup,intents,upper", [
    (1, [[A], [D, E], [A, B], [C, D, E], [A, D, E]], [[A, D, E]]),
    (5, [[A], [D, E]], [[A], [D, E]]),
])
def test_concepts_and_upper_edge(spark, minsup, intents, upper):
    lat = lattice.build_concepts(five(spark), minsup)
    assert sorted(r.intent for r in lat.concepts.collect()) == sorted(intents)
    top = lattice.top_edge(lat).where("obj = 1").join(lat.concepts.select("cid", "intent"), "cid").collect()
    assert sorted(r.intent for r in top) == sorted(upper)


def test_distances_by_hand(spark):
    ds = data(spark, {1: {A: 3, B: 1, C: 2}, 2: {A: 1, B: 1, D: 4}})
    p = spark.createDataFrame([(1, 2)], "a long, b long")
    assert distance.pair_distance(ds, p).first().dist == pytest.approx(0.8)
    assert distance.pair_distance(ds, p, weighted=False).first().dist == pytest.approx(0.5)
    kept = data(spark, {1: {A: 3, B: 1}, 2: {A: 1, B: 1}})
    st = ds.stats().select("obj", F.lit(2).alias("n_in"), F.lit(1).alias("n_out"), "minw", "maxw")
    td = truncate.TruncatedDataset(kept, st)
    assert truncate.mixed_distance(td, p).first().mixed == pytest.approx(2 / 12)
    assert truncate.mixed_distance(td, p, t_mode="min").first().mixed == pytest.approx(0.25)
    assert truncate.mixed_distance(td, p, weighted=False).first().mixed == 0


def test_candidate_counts():
    want = {2: 7, 4: 7, 6: 8, 7: 9, 9: 11, 12: 14, 14: 16, 15: 17, 18: 20}
    assert {k: successors.min_candidates(k, 20) for k in want} == want


def test_negative_weights_are_refused(spark):
    df = spark.createDataFrame([(1, 1, -2.0)], "o long, f long, v double")
    with pytest.raises(Exception, match="negative"):
        AssocDataset.from_weights(df, "o", "f", "v").rel.collect()


def ring(spark, n=8):
    """Objects in a line, each sharing two of its features with the next."""
    return data(spark, {i: {2 * i: 1, 2 * i + 1: 1, 2 * i + 2: 1, 2 * i + 3: 1} for i in range(n)})


def test_paths_cost_what_the_whole_network_says(spark):
    ds = ring(spark)
    pairs = spark.createDataFrame([(1, 0, 5), (2, 3, 3), (3, 0, 99), (4, 7, 6)], "pair_id long, src long, dst long")
    spec = SearchSpec(theta=0.7, successors="exact", max_rounds=30)
    got = {r.pair_id: r for r in find_paths(ds, pairs, spec).collect()}
    best = {r.pair_id: r.cost for r in network.dijkstra_rounds(network.materialize_network(ds, theta=0.7), pairs).collect()}
    assert got[1].nodes == [0, 1, 2, 3, 4, 5] and got[1].cost == pytest.approx(best[1])
    assert got[2].hops == 0 and got[3].outcome == "no_path" and got[4].hops == 1
    ok = distance.validate_paths(ds, spark.createDataFrame([(1, 0, 5, got[1].nodes)], "pair_id long, src long, dst long, nodes array<long>"), theta=0.7)
    assert ok.first().ok


def test_zero_bound_finds_the_same_cost_with_no_fewer_nodes(spark):
    ds = ring(spark)
    pairs = spark.createDataFrame([(1, 2, 6)], "pair_id long, src long, dst long")
    spec = SearchSpec(theta=0.7, successors="exact", max_rounds=30)
    a, z = find_paths(ds, pairs, spec).first(), find_paths(ds, pairs, spec.but(heuristic="zero")).first()
    assert a.cost == pytest.approx(z.cost) and a.nodes_explored <= z.nodes_explored


def test_cover_tree_is_sound_and_exact(spark):
    ds = ring(spark)
    index = successors.CoverTreeIndex.build(ds, levels=2)
    assert all(r.not_nested == r.not_covered == r.too_close == 0 for r in index.check().collect())
    f = ds.rel.select("obj").distinct()
    got = {(r.obj, r.nbr) for r in index.knn(f, 3, 0.7).collect()}
    want = {(r.obj, r.nbr) for r in successors.exact_knn(ds, f, 3).where("dist <= 0.7").collect()}
    assert got == want


def test_lattice_neighbours_come_in_order(spark):
    ds = five(spark)
    lat = lattice.build_concepts(ds, 1)
    f = spark.createDataFrame([(1,), (6,)], "obj long")
    got = successors.nna(lat, ds, f, 4)
    assert all(r.inversions == 0 for r in measures.order_inversions(got).collect())
    assert all(r.recall == 1 for r in measures.recall_at_b(got, successors.exact_knn(ds, f, 4, weighted=False)).collect())


def test_tail_probability(spark):
    ds = data(spark, {1: dict.fromkeys([1, 2, 3, 4], 1), 2: dict.fromkeys([3, 4, 5], 1), 3: dict.fromkeys(range(5, 11), 1)})
    p = measures.hop_pvalues(spark.createDataFrame([(1, 2)], "a long, b long"), ds).first().p
    want = sum(math.comb(4, x) * math.comb(6, 3 - x) for x in (2, 3)) / math.comb(10, 3)
    assert p == pytest.approx(want)


def test_empty_dataset(spark):
    ds = data(spark, {}) if False else AssocDataset(spark.createDataFrame([], "obj long, feat long, val double"))
    assert lattice.build_concepts(ds, 1).concepts.count() == 0
    assert distance.hammock_pairs(ds, theta=0.9).count() == 0
