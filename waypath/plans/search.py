"""Best-first search over a network that is never built: batched rounds shared by all pairs.

Successors don't depend on the goal, so an object is expanded once for all pairs.  A round
expands what the searches asked for, as DataFrame joins over all pairs together, bounds the
new candidates' distances to the goals, and then replays every unfinished pair's search over
all arcs known for it, in exact best-first order, until it ends or pops an object that is
not expanded yet.  A search asks for a few open objects ahead, four times as many each
round, so rounds grow with the logarithm of the objects explored.  All that passes between
rounds are written tables of arcs: a lost executor repeats a step, not the search, and the
driver only learns whether anything is left.
"""

from __future__ import annotations

import heapq
import time
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.dataset import AssocDataset
from ..operators.distance import hammock_pairs, pair_distance, passes
from ..operators.network import both_ways
from ..operators.lattice import Lattice, build_edges, longest_concept, rank_extents
from ..operators.successors import CoverTreeIndex, candidate_cliques, kcnn, kcnn_candidates, min_candidates, nna, rank_combinations, verify_cliques
from ..operators.truncate import TruncatedDataset, mixed_distance, truncate
from ..functions.columns import ebf
from ..tables import drop_since, mark, written
from .spec import SearchSpec

RESULT = ["pair_id", "src", "dst", "outcome", "hops", "cost", "nodes", "steps", "cliques", "nodes_explored", "rounds", "elapsed_ms", "ebf"]
#: A search asks for at most so many objects ahead.
MOST_AHEAD = 512


class Expander:
    """Successors (obj, nbr, dist, clique) of requested objects, each computed once."""

    def __init__(self, ds: AssocDataset, spec: SearchSpec, lattice: Lattice | None, index: CoverTreeIndex | None, links: DataFrame | None = None):
        self.ds, self.spec, self.lattice, self.index, self.links = ds, spec, lattice, index, links
        self.known: DataFrame | None = None
        self.asked: DataFrame | None = None
        self.lists: DataFrame | None = None
        if spec.successors in ("kcnn", "nna"):
            if lattice is None:
                raise ValueError(f"{spec.successors} needs a lattice")
            if spec.successors == "nna":
                self.edges = written(build_edges(lattice), "covers")
            else:
                top = None if spec.order == "closest" else min_candidates(spec.others, spec.b) + 1
                self.ranked = written(rank_extents(lattice, "features_desc" if spec.order == "closest" else spec.order, top), "ranked")
                self.longest = written(longest_concept(lattice), "longest")
        if spec.successors == "cover" and index is None:
            self.index = CoverTreeIndex.build(ds)

    def _fresh(self, objs: DataFrame) -> DataFrame:
        s = self.spec
        if s.successors in ("exact", "cover"):
            if s.successors == "exact" or s.theta is None:
                if self.links is None:
                    p = hammock_pairs(self.ds, theta=s.theta, width=s.width, sources=objs, ordered=False)
                else:
                    p = both_ways(self.links).join(objs.select(F.col("obj").alias("a")), "a", "left_semi")
                w = Window.partitionBy("a").orderBy("dist", "b")
                got = p.withColumn("r", F.row_number().over(w)).where(F.col("r") <= s.b).select(F.col("a").alias("obj"), F.col("b").alias("nbr"), "dist")
            else:
                got = self.index.knn(objs, s.b, s.theta).select("obj", "nbr", "dist")
            return got.withColumn("clique", F.sort_array(F.array("obj", "nbr")))
        if s.successors == "kcnn":
            good = kcnn(self.lattice, self.ds, objs, s.k, s.b, s.arity, s.order, s.fallback, self.ranked, self.longest, s.theta, s.width)
        else:
            # ordered by Jaccard, checked by the search's own distance
            m = min_candidates(s.others, s.b)
            met = nna(self.lattice, self.ds, objs, m, edges=self.edges).select("obj", "nbr", F.col("rnk").alias("crank"))
            met = written(met, "lists")
            self.lists = met if self.lists is None else self.lists.union(met)
            good = verify_cliques(self.ds, written(candidate_cliques(self.ds.binary(), met, s.others, s.b, m), "sets"), s.theta, s.width)
        good = written(good, "cliques")
        one = good.select("obj", F.explode("members").alias("nbr"), "score", F.sort_array(F.array_union("members", F.array("obj"))).alias("clique"))
        one = one.groupBy("obj", "nbr").agg(F.min(F.struct("score", "clique")).alias("x")).select("obj", "nbr", F.col("x.clique").alias("clique"))
        d = pair_distance(self.ds, one.select(F.col("obj").alias("a"), F.col("nbr").alias("b"))).select(F.col("a").alias("obj"), F.col("b").alias("nbr"), "dist")
        return one.join(d, ["obj", "nbr"]).select("obj", "nbr", "dist", "clique")

    def candidates(self, objs: DataFrame, m: int) -> DataFrame:
        """(obj, nbr, crank): the objects from which a clique around the goal may be completed."""
        s = self.spec
        if s.successors == "kcnn":
            return kcnn_candidates(self.ranked, self.longest, self.ds, objs, m, s.order, s.fallback, self.lattice)
        return self.lists.join(objs.distinct(), "obj", "left_semi")  # met when they were expanded

    def __call__(self, objs: DataFrame) -> DataFrame:
        """(obj, nbr, dist, clique) of all objects asked for so far."""
        ask = objs.select("obj").distinct()
        new = written(ask if self.asked is None else ask.join(self.asked, "obj", "left_anti"), "asked")
        if self.known is None or not new.isEmpty():
            got = written(self._fresh(new), "expanded")
            self.known = got if self.known is None else self.known.union(got)
            self.asked = new if self.asked is None else self.asked.union(new)
        return self.known


def goal_links(ex: Expander, near: DataFrame) -> DataFrame:
    """near(pair_id, node, dst, ...), whose goals pass the hammock test, with the clique of the last hop.

    With cliques asked for, the last hop must lie in one: the goal, the object and enough of
    the object's candidates that are hammocks of both and of each other; rows without one go.
    """
    s = ex.spec
    fill = s.others - 1
    if fill == 0 or s.goal_clique == "hammock" or s.successors in ("exact", "cover"):
        return near.withColumn("clique", F.sort_array(F.array("node", "dst")))
    near = written(near, "near")
    return near.join(_goal_cliques(ex, near.select("pair_id", "node", "dst"), fill), ["pair_id", "node", "dst"])


def _goal_cliques(ex: Expander, near: DataFrame, fill: int) -> DataFrame:
    """(pair_id, node, dst, clique)."""
    s = ex.spec
    m = min_candidates(s.others, s.b)
    cands = ex.candidates(near.select(F.col("node").alias("obj")), m)
    j = near.join(cands, near["node"] == cands["obj"]).where("nbr <> dst").select("pair_id", "node", "dst", "nbr", "crank")
    ends = [j.select(F.least("nbr", e).alias("a"), F.greatest("nbr", e).alias("b"), F.lit(0)) for e in ("node", "dst")]
    ok = written(pair_distance(ex.ds, ends[0].union(ends[1]).select("a", "b")).where(passes(s.theta, s.width)).select("a", "b"), "ok")
    for e in ("node", "dst"):
        both = ok.union(ok.select("b", "a")).toDF(e, "nbr")
        j = j.join(both, [e, "nbr"], "left_semi")
    # what is left is near both ends: rank it by pair and ask for a clique among it
    lists = j.withColumn("crank", F.row_number().over(Window.partitionBy("pair_id", "node").orderBy("crank")))
    lists = written(lists, "lists")
    if fill == 1:
        best = lists.where("crank = 1")
        return best.select("pair_id", "node", "dst", F.sort_array(F.array("node", "dst", "nbr")).alias("clique"))
    pairs = lists.alias("x").join(lists.alias("y"), ["pair_id", "node"]).where("x.crank < y.crank").select("pair_id", "node", F.col("x.crank").alias("i"), F.col("y.crank").alias("j"), F.least("x.nbr", "y.nbr").alias("a"), F.greatest("x.nbr", "y.nbr").alias("b"))
    pairs = written(pairs, "between")
    good = pair_distance(ex.ds, pairs.select("a", "b")).where(passes(s.theta, s.width)).select("a", "b")
    linked = pairs.join(good, ["a", "b"]).select("pair_id", "node", F.explode(F.array(F.struct("i", "j"), F.struct(F.col("j").alias("i"), F.col("i").alias("j")))).alias("x"))
    bits = linked.groupBy("pair_id", "node", F.col("x.i").alias("crank")).agg(F.bit_or(F.expr("shiftleft(1L, x.j - 1)")).alias("links"))
    full = lists.join(bits, ["pair_id", "node", "crank"], "left").groupBy("pair_id", "node", "dst").agg(
        F.array_sort(F.collect_list(F.struct("crank", "nbr", F.expr("coalesce(links, 0L) | shiftleft(1L, crank - 1)").alias("links")))).alias("list"))
    # enough members must have enough links before any set of them is tried
    full = full.where(F.size(F.filter("list", lambda x: F.bit_count(x["links"]) >= fill)) >= fill)
    combos = F.broadcast(rank_combinations(ex.ds.rel.sparkSession, m, fill))
    t = full.join(combos, F.element_at("picks", -1) <= F.size("list")).where(F.expr("forall(picks, r -> (get(list, r - 1).links & mask) = mask)"))
    best = t.groupBy("pair_id", "node", "dst").agg(F.min(F.struct("combo", F.expr("transform(picks, r -> get(list, r - 1).nbr)").alias("members"))).alias("x"))
    return best.select("pair_id", "node", "dst", F.sort_array(F.array_union("x.members", F.array("node", "dst"))).alias("clique"))


def find_paths(ds: AssocDataset, pairs: DataFrame, spec: SearchSpec, lattice: Lattice | None = None, index: CoverTreeIndex | None = None, truncated: TruncatedDataset | None = None, minsup: int | float = 2, links: DataFrame | None = None) -> DataFrame:
    """One row per pair(pair_id, src, dst) with the columns of RESULT.

    outcome is found, no_path (nothing left to pop) or budget (nodes, rounds or time ran
    out).  A path is accepted when its goal is popped, so costs are least among what the
    successors offer.  In mixed mode the goal distance is the lower bound from the truncated
    data; it may be inconsistent, so closed objects re-open.  The goal distance itself is
    read only where it bounds (normal mode) and at objects that are expanded, for the link
    to the goal.  A pair of one object is found at once; a pair with an unknown object has
    no path.  Exact successors are read from ``links(a, b, dist)``, all hammocks of the spec,
    where these are built anyway.
    """
    place, began = mark(), time.time()
    spark = ds.rel.sparkSession
    ex = Expander(ds, spec, lattice, index, links)
    td = truncated or (truncate(ds, minsup) if spec.mode == "mixed" and spec.heuristic != "zero" else None)
    if td is not None and truncated is None:
        td = TruncatedDataset(AssocDataset(written(td.kept.rel, "kept")), written(td.stat, "kept"))
    pairs = written(pairs.select(F.col("pair_id").cast("long").alias("pair_id"), F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")), "pairs")
    known = ds.objects()
    valid = pairs.join(known.withColumnRenamed("obj", "src"), "src", "left_semi").join(known.withColumnRenamed("obj", "dst"), "dst", "left_semi")
    valid = valid.select("pair_id", "src", "dst")

    def bounded(moves: DataFrame) -> DataFrame:
        """moves with h, the bound of the distance from nbr to dst; each distinct pair is measured once."""
        if spec.heuristic == "zero":
            return moves.withColumn("h", F.lit(0.0))
        moves = written(moves, "moves")
        ask = moves.select(F.col("nbr").alias("a"), F.col("dst").alias("b")).where("a <> b").distinct()
        d = mixed_distance(td, ask, t_mode=spec.t_mode).withColumnRenamed("mixed", "h") if spec.mode == "mixed" else pair_distance(ds, ask).withColumnRenamed("dist", "h")
        return moves.join(d.select(F.col("a").alias("nbr"), F.col("b").alias("dst"), "h"), ["nbr", "dst"], "left").withColumn("h", F.coalesce("h", F.lit(0.0)))

    want = valid.where("src <> dst").select("pair_id", "src", "dst", F.col("src").alias("node"))
    same = valid.where("src = dst").select("pair_id", F.lit("found").alias("outcome"), F.array("src").alias("nodes"), F.lit(0.0).alias("cost"), F.lit(0).cast("long").alias("nodes_explored"))
    arcs, ended = [], [same.withColumn("rounds", F.lit(0)).withColumn("elapsed_ms", F.lit(0.0))]
    rounds, ahead = 0, spec.pop
    cols = ["pair_id", "src", "dst", "node", "nbr", "dist", "h", "clique"]
    while True:
        rounds += 1
        nxt = ex(want.select(F.col("node").alias("obj")))
        moves = want.join(nxt, want["node"] == nxt["obj"]).select("pair_id", "src", "dst", "node", "nbr", "dist", "clique")
        if spec.link_goal:
            near = pair_distance(ds, want.select(F.col("node").alias("a"), F.col("dst").alias("b"))).where(passes(spec.theta, spec.width))
            near = want.join(near.select(F.col("a").alias("node"), F.col("b").alias("dst"), "dist"), ["node", "dst"])
            near = goal_links(ex, near.select("pair_id", "src", "dst", "node", F.col("dst").alias("nbr"), "dist"))
            moves = moves.union(near.select(moves.columns))
        # an expanded object without successors stays as a row, so that the replay knows it
        told = want.select("pair_id", "src", "dst", "node", F.lit(None).cast("long").alias("nbr"), F.lit(0.0).alias("dist"), F.lit(0.0).alias("h"), F.lit(None).cast("array<bigint>").alias("clique"))
        arcs.append(written(bounded(moves).select(*cols).union(told), "arcs"))
        everything = reduce(DataFrame.union, arcs).join(want.select("pair_id").distinct(), "pair_id", "left_semi")
        state = written(_replayed(everything, spec, ahead), "replay")
        done = state.where("outcome <> 'want'").select("pair_id", "outcome", "nodes", "cost", "nodes_explored")
        late = rounds >= spec.max_rounds or time.time() - began >= spec.time_limit_s
        want = state.where("outcome = 'want'").select("pair_id", "src", "dst", "node")
        if late:
            left = state.where("outcome = 'want'").groupBy("pair_id").agg(F.first("nodes_explored").alias("n"))
            done = done.union(left.select("pair_id", F.lit("budget"), F.lit(None).cast("array<bigint>"), F.lit(None).cast("double"), "n"))
        ended.append(done.withColumn("rounds", F.lit(rounds)).withColumn("elapsed_ms", F.lit(round(1000 * (time.time() - began), 1))))
        if late or want.isEmpty():
            break
        ahead = min(8 * ahead, MOST_AHEAD)
    done = reduce(DataFrame.union, ended)
    hops = done.where(F.size("nodes") > 1).select("pair_id", F.posexplode(F.expr("transform(sequence(1, size(nodes) - 1), i -> struct(nodes[i - 1] AS node, nodes[i] AS nbr))")).alias("i", "hop")).select("pair_id", "i", "hop.node", "hop.nbr")
    arc = reduce(DataFrame.union, arcs).select("pair_id", "node", "nbr", "dist", "clique")
    walked = hops.join(arc, ["pair_id", "node", "nbr"]).groupBy("pair_id", "i").agg(F.min(F.struct("dist", "clique")).alias("x"))
    walked = walked.groupBy("pair_id").agg(F.array_sort(F.collect_list(F.struct("i", F.col("x.dist").alias("dist"), F.col("x.clique").alias("clique")))).alias("x"))
    out = pairs.join(done, "pair_id", "left").join(walked, "pair_id", "left")
    out = out.select(
        "pair_id", "src", "dst", F.coalesce("outcome", F.lit("no_path")).alias("outcome"), F.when(F.col("nodes").isNotNull(), F.size("nodes") - 1).alias("hops"), "cost", "nodes",
        F.when(F.col("nodes").isNotNull(), F.coalesce("x.dist", F.array().cast("array<double>"))).alias("steps"), F.when(F.col("nodes").isNotNull(), F.coalesce("x.clique", F.array().cast("array<array<bigint>>"))).alias("cliques"),
        F.coalesce("nodes_explored", F.lit(0)).cast("long").alias("nodes_explored"), F.coalesce("rounds", F.lit(0)).alias("rounds"), F.coalesce("elapsed_ms", F.lit(0.0)).alias("elapsed_ms"))
    out = written(out.withColumn("ebf", F.when(F.col("hops") > 0, ebf(F.col("nodes_explored"), F.col("hops")))).select(*RESULT), "paths")
    drop_since(place, [out])
    return out


def _replayed(arcs: DataFrame, spec: SearchSpec, ahead: int) -> DataFrame:
    """(pair_id, src, dst, outcome, node, nodes, cost, nodes_explored) after running each pair's search over its known arcs.

    A search that pops an object whose successors are not known yet stops with rows of
    outcome 'want': that object and the best others it holds open, ``ahead`` in all.  What is
    asked for ahead and never popped is not counted as explored.  A pair's arcs are bounded
    by the nodes it may explore times the branching cap, whatever the size of the data.
    """
    reopens, most = spec.reopens, spec.max_nodes

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pair, src, dst = int(pdf["pair_id"].iat[0]), int(pdf["src"].iat[0]), int(pdf["dst"].iat[0])
        node, dist, h = pdf["node"].to_numpy(), pdf["dist"].to_numpy(), pdf["h"].to_numpy()
        nbr = pdf["nbr"].fillna(-1).to_numpy().astype("int64")
        real = pdf["nbr"].notna().to_numpy()
        order = np.lexsort((nbr, node))
        starts = np.flatnonzero(np.r_[True, node[order][1:] != node[order][:-1]])
        at = {int(node[order[s]]): order[s:e] for s, e in zip(starts, np.r_[starts[1:], len(order)])}
        best, parent, closed = {src: 0.0}, {src: None}, set()
        heap = [(0.0, -0.0, src)]
        explored = 0

        def rows(outcome, wanted=(None,), nodes=None, cost=None):
            return pd.DataFrame({"pair_id": pair, "src": src, "dst": dst, "outcome": outcome, "node": pd.array(list(wanted), "Int64"), "nodes": [nodes] * len(wanted), "cost": pd.array([cost] * len(wanted), "Float64"), "nodes_explored": explored})

        while heap:
            f, minus, o = heapq.heappop(heap)
            if o in closed or -minus > best[o] + 1e-12:
                continue
            if o == dst:
                path, x = [], o
                while x is not None:
                    path.append(x)
                    x = parent[x]
                return rows("found", nodes=path[::-1], cost=best[dst])
            if explored >= most:
                return rows("budget")
            if o not in at:
                wanted = [o]
                while heap and len(wanted) < ahead:
                    _, minus, x = heapq.heappop(heap)
                    if x not in closed and x not in at and x != dst and x not in wanted and -minus <= best[x] + 1e-12:
                        wanted.append(x)
                return rows("want", wanted)
            closed.add(o)
            explored += 1
            g = best[o]
            for i in at[o]:
                if not real[i]:
                    continue
                x, new = int(nbr[i]), g + dist[i]
                if new < best.get(x, np.inf) - 1e-12 and (reopens or x not in closed):
                    best[x], parent[x] = new, o
                    closed.discard(x)
                    heapq.heappush(heap, (round(new + h[i], 9), -new, x))
        return rows("no_path")

    return arcs.select("pair_id", "src", "dst", "node", "nbr", "dist", "h").groupBy("pair_id").applyInPandas(run, "pair_id long, src long, dst long, outcome string, node long, nodes array<long>, cost double, nodes_explored long")
