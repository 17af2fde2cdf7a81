"""Work that an earlier round left out."""

import pytest

from waypath import queries
from waypath.operators import lattice, network
from waypath.operators.dataset import random_intersection
from waypath.plans.spec import SearchSpec
from waypath.sources import carriers


def frequent_pairs(ds, support):
    rel = ds.rel.select("obj", "feat")
    return rel.join(rel.withColumnRenamed("feat", "other"), "obj").where("feat < other").groupBy("feat", "other").count().where(f"count >= {support}").count()


def test_support_keeps_pairs_frequent_on_a_larger_table(spark):
    ds = carriers.parts_by_suppliers(spark, "/root/testdata/sf0.1").kept()
    n = queries._support(ds)
    assert ds.frequent(n).count() == 1000
    assert frequent_pairs(ds, n) >= 5000 > frequent_pairs(ds, n + 1)


def test_lattice_of_many_rare_features_is_not_empty(spark):
    ds = random_intersection(spark, 400, 80, 0.05).kept()
    assert lattice.build_concepts(ds, queries.MINSHARE).concepts.where("n_feat >= 2").isEmpty()
    assert lattice.build_concepts(ds, queries._support(ds)).concepts.where("n_feat >= 2").count() > 0


def test_frontier_grows_with_the_table(spark):
    ds = carriers.parts_by_suppliers(spark, "/root/testdata/sf0.01")
    assert sorted(r.obj for r in queries._frontier(ds).collect()) == list(range(0, 2000, 100))


def test_unsettled_components_are_refused(spark):
    chain = [(i, i + 1) for i in range(20)]
    nodes = spark.range(21).withColumnRenamed("id", "obj")
    with pytest.raises(RuntimeError, match="not settled"):
        network.component_labels(nodes, spark.createDataFrame(chain, "a long, b long"), 2)


def test_mixed_step_costs_are_refused():
    with pytest.raises(TypeError, match="mixed_cost"):
        SearchSpec(theta=0.9, mixed_cost=True)
