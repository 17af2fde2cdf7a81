"""Baselines that build the whole network: edges, hop counts, shortest paths, connectivity by width."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import drop_since, mark, written
from .dataset import AssocDataset
from .distance import hammock_pairs
from .successors import close_pairs, hashed_profiles


def materialize_network(ds: AssocDataset, theta: float | None = None, width: int | None = None) -> DataFrame:
    """(a, b, width, dist), a < b: every hammock of the dataset.  Quadratic in hub features; ground truth at small scale."""
    return hammock_pairs(ds, theta=theta, width=width)


def links_by_task(ds: AssocDataset, theta: float) -> DataFrame:
    """(a, b, dist), a < b: the same hammocks within a theta under 1, met and measured in tasks, so that nothing but them is written."""
    place = mark()
    profiles = hashed_profiles(ds)
    pair = [F.least("obj", "other").alias("a"), F.greatest("obj", "other").alias("b"), "dist"]
    parts = [written(p.select(*pair), "links") for p in close_pairs(profiles, profiles.select("obj", "h", "n"), theta)]
    links = reduce(DataFrame.union, parts) if parts else written(profiles.limit(0).select(F.col("obj").alias("a"), F.col("obj").alias("b"), F.lit(0.0).alias("dist")), "links")
    drop_since(place, [links])
    return links


def joined_pairs(links: DataFrame, pairs: DataFrame) -> DataFrame:
    """Of pairs(pair_id, src, dst) those whose ends some chain of links(a, b) joins: the others have no path of any cost."""
    ends = links.select(F.col("a").alias("obj")).union(links.select("b")).distinct()
    lab = component_labels(written(ends, "ends"), links)
    both = pairs.join(lab.toDF("src", "l1"), "src").join(lab.toDF("dst", "l2"), "dst").where("l1 = l2")
    return both.select("pair_id", "src", "dst")


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b", "dist").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "dist"))


def shortest_costs(edges: DataFrame, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """(src, node, cost) of least cost, by rounds of relaxation until nothing improves; only improved rows travel on.

    ``max_hops`` asks for the least cost within so many hops instead.
    """
    e = written(both_ways(edges), "edges")
    best = written(sources.select("src", F.col("src").alias("node"), F.lit(0.0).alias("cost")).distinct(), "best")
    front, hops = best, 0
    while max_hops is None or hops < max_hops:
        hops += 1
        step = front.join(e, F.col("node") == F.col("a")).groupBy("src", "b").agg(F.min(F.col("cost") + F.col("dist")).alias("new"))
        j = step.join(best.withColumnRenamed("node", "b"), ["src", "b"], "left")
        front = written(j.where(F.col("cost").isNull() | (F.col("new") < F.col("cost") - 1e-12)).select("src", F.col("b").alias("node"), F.col("new").alias("cost")), "front")
        if front.isEmpty():
            break
        best = written(best.union(front).groupBy("src", "node").agg(F.min("cost").alias("cost")), "best")
    return best


def dijkstra_rounds(edges: DataFrame, pairs: DataFrame, max_hops: int | None = None) -> DataFrame:
    """(pair_id, cost): least cost of each pair over the built network; missing where there is no path."""
    best = shortest_costs(edges, pairs.select("src"), max_hops)
    return pairs.join(best.withColumnRenamed("node", "dst"), ["src", "dst"]).select("pair_id", "cost")


def bfs_hops(edges: DataFrame, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """(src, node, hops) of every node that can be reached."""
    ones = edges.select("a", "b", F.lit(1.0).alias("dist"))
    return shortest_costs(ones, sources, max_hops).select("src", "node", F.col("cost").cast("int").alias("hops"))


def component_labels(nodes: DataFrame, edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(obj, label): smallest object of each connected component, by label spreading with pointer jumps."""
    e = written(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    lab = written(nodes.select("obj", F.col("obj").alias("label")), "labels")
    state = None
    for _ in range(max_rounds):
        near = e.join(lab.select(F.col("obj").alias("b"), "label"), "b").groupBy(F.col("a").alias("obj")).agg(F.min("label").alias("m"))
        low = lab.join(near, "obj", "left").select("obj", F.least("label", F.coalesce("m", "label")).alias("label"))
        jump = low.join(low.select(F.col("obj").alias("o2"), F.col("label").alias("l2")), F.col("label") == F.col("o2")).select("obj", F.least("label", "l2").alias("label"))
        lab = written(jump, "labels")
        now = lab.agg(F.sum(F.xxhash64("obj", "label").cast("decimal(38,0)"))).first()
        if now == state:
            return lab
        state = now
    raise RuntimeError(f"components are not settled after {max_rounds} rounds")


def connectivity_by_width(ds: AssocDataset, widths: list[int]) -> DataFrame:
    """width, n_components, largest: how the network falls apart as hammocks must be wider."""
    nodes = ds.rel.select("obj").distinct()
    all_edges = written(materialize_network(ds, width=min(widths)), "network")
    rows = None
    for w in widths:
        lab = component_labels(nodes, all_edges.where(F.col("width") >= w))
        sizes = lab.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
        row = sizes.agg(F.count(F.lit(1)).alias("n_components"), F.max("n").alias("largest")).select(F.lit(w).alias("width"), "n_components", "largest")
        rows = row if rows is None else rows.union(row)
    return rows
