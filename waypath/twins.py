"""SQL of the twins: common table expressions over the given tables, written out by size."""

from __future__ import annotations

PBC = "SELECT l_partkey AS obj, o_custkey AS feat, sum(l_quantity) AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"
PBS = "SELECT l_partkey AS obj, l_suppkey AS feat, sum(l_quantity) AS val FROM lineitem GROUP BY 1, 2"
STATS = "st AS MATERIALIZED (SELECT obj, count(*) AS n_feat, sum(val) AS total, min(val) AS minw, max(val) AS maxw FROM rel GROUP BY obj)"


def base(rel: str) -> str:
    return f"WITH rel AS MATERIALIZED ({rel}), {STATS}"


REL, REL_PBS = base(PBC), base(PBS)
#: Every unordered pair with a common feature.
PAIR_STEPS = """, j AS (SELECT x.obj AS a, y.obj AS b, count(*) AS width, sum(least(x.val, y.val)) AS smin
  FROM rel x JOIN rel y ON x.feat = y.feat AND x.obj < y.obj GROUP BY 1, 2),
d AS MATERIALIZED (SELECT a, b, width, 1.0 - smin / (p.total + q.total - smin) AS dist,
  1.0 - width::DOUBLE / (p.n_feat + q.n_feat - width) AS sdist, p.n_feat AS na, q.n_feat AS nb
  FROM j JOIN st p ON p.obj = a JOIN st q ON q.obj = b)"""
PAIRS, PAIRS_PBS = REL + PAIR_STEPS, REL_PBS + PAIR_STEPS
#: The same pairs in both directions.
BOTH_STEPS = ", d2 AS MATERIALIZED (SELECT a, b, dist FROM d UNION ALL SELECT b, a, dist FROM d)"


def lattice(share: float, per_feature: int = 5, levels: int = 12) -> str:
    """Steps after REL_PBS: itemsets by size, their closures, and concepts(cid, intent, n_feat, support), ext(cid, obj, n_obj_feat).

    Right while no frequent set has more than ``levels`` features.
    """
    out = f""", pc AS (SELECT n, sum(count(*)) OVER (ORDER BY n DESC) AS reach FROM (SELECT count(*) AS n FROM rel x JOIN rel y ON x.obj = y.obj AND x.feat < y.feat GROUP BY x.feat, y.feat) GROUP BY n),
sup AS MATERIALIZED (SELECT greatest(1, least((SELECT ceil({share} * count(*)) FROM st), coalesce((SELECT max(n) FROM pc WHERE reach >= {per_feature} * (SELECT count(DISTINCT feat) FROM rel)), (SELECT min(n) FROM pc), 1))) AS s),
i1 AS MATERIALIZED (SELECT [feat] AS items, feat AS last, obj FROM rel QUALIFY count(*) OVER (PARTITION BY feat) >= (SELECT s FROM sup))"""
    for k in range(2, levels + 1):
        out += f""",
i{k} AS MATERIALIZED (SELECT list_append(i.items, r.feat) AS items, r.feat AS last, i.obj FROM i{k - 1} i JOIN rel r ON r.obj = i.obj AND r.feat > i.last QUALIFY count(*) OVER (PARTITION BY list_append(i.items, r.feat)) >= (SELECT s FROM sup))"""
    union = " UNION ALL ".join(f"SELECT items, obj FROM i{k}" for k in range(1, levels + 1))
    return out + f""",
sets AS MATERIALIZED ({union}),
ns AS (SELECT items, count(*) AS n FROM sets GROUP BY items),
shared AS (SELECT s.items, r.feat, count(*) AS c FROM sets s JOIN rel r ON r.obj = s.obj GROUP BY 1, 2),
closed AS (SELECT DISTINCT intent, n FROM (SELECT h.items, list(h.feat ORDER BY h.feat) AS intent, any_value(ns.n) AS n FROM shared h JOIN ns ON ns.items = h.items AND ns.n = h.c GROUP BY h.items)),
concepts AS MATERIALIZED (SELECT row_number() OVER (ORDER BY intent) AS cid, intent, len(intent)::INT AS n_feat, n AS support FROM closed),
ext AS MATERIALIZED (SELECT cid, s.obj, n_feat.n_feat AS n_obj_feat FROM concepts JOIN sets s ON s.items = intent JOIN st n_feat ON n_feat.obj = s.obj)"""


UNDER = """, under AS MATERIALIZED (SELECT p.cid, c.cid AS child_cid FROM concepts p JOIN concepts c ON c.n_feat < p.n_feat AND list_has_all(p.intent, c.intent))"""
COVERS = UNDER + """, via AS (SELECT DISTINCT x.cid, y.child_cid FROM under x JOIN under y ON x.child_cid = y.cid),
cov AS MATERIALIZED (SELECT u.cid, u.child_cid FROM under u ANTI JOIN via ON via.cid = u.cid AND via.child_cid = u.child_cid)"""
BEATEN = UNDER + """, beaten AS MATERIALIZED (SELECT DISTINCT e.obj, u.child_cid AS cid FROM ext e JOIN under u ON u.cid = e.cid)"""
LONGEST = """, longest AS MATERIALIZED (SELECT e.obj, c.cid, c.n_feat FROM ext e JOIN concepts c USING (cid) QUALIFY row_number() OVER (PARTITION BY e.obj ORDER BY c.n_feat DESC, c.support DESC, c.cid) = 1)"""
RANKED = """, ranked AS MATERIALIZED (SELECT cid, obj, n_obj_feat, row_number() OVER (PARTITION BY cid ORDER BY n_obj_feat DESC, obj) AS rnk FROM ext)"""


def near_cliques(k: int, m: int, b: int, theta: float) -> str:
    """Steps after lattice, LONGEST, RANKED, PAIR_STEPS and BOTH_STEPS: cand(obj, nbr, crank, dist), tries and good(obj, n1..nk, score)."""
    ns = [f"n{i}" for i in range(1, k + 1)]
    join = "cand c1" + "".join(f" JOIN cand c{i} ON c{i}.obj = c1.obj AND c{i}.crank > c{i - 1}.crank" for i in range(2, k + 1))
    picks = ", ".join(f"c{i}.nbr AS n{i}, c{i}.crank AS r{i}" for i in range(1, k + 1))
    score = f"({' + '.join(f'c{i}.dist' for i in range(1, k + 1))}) / {float(k)}"
    ranks = ", ".join(f"r{i}" for i in range(1, k + 1))
    tests = " ".join(f"SEMI JOIN near x{a}{b_} ON x{a}{b_}.a = t.{a} AND x{a}{b_}.b = t.{b_}" for i, a in enumerate(["obj", *ns]) for b_ in ["obj", *ns][i + 1:])
    return f""", near AS MATERIALIZED (SELECT a, b, dist FROM d2 WHERE dist <= {theta} + 1e-12),
cand AS MATERIALIZED (SELECT l.obj, r.obj AS nbr, row_number() OVER (PARTITION BY l.obj ORDER BY r.rnk) AS crank, d2.dist FROM longest l JOIN ranked r ON r.cid = l.cid AND r.obj <> l.obj JOIN d2 ON d2.a = l.obj AND d2.b = r.obj QUALIFY row_number() OVER (PARTITION BY l.obj ORDER BY r.rnk) <= {m}),
tries AS MATERIALIZED (SELECT obj, {', '.join(ns)}, score FROM (SELECT c1.obj, {picks}, {score} AS score FROM {join}) QUALIFY row_number() OVER (PARTITION BY obj ORDER BY score, {ranks}) <= {b}),
good AS MATERIALIZED (SELECT t.* FROM tries t {tests})"""


def asked(theta: float, targets: int) -> str:
    """pairs(pair_id, src, dst): see queries._pairs."""
    return f""", many AS (SELECT count(*) AS n FROM st),
pairs AS MATERIALIZED (SELECT pair_id, src, dst FROM (SELECT obj * 1000 + t AS pair_id, obj AS src, (obj * 31 + t * 97 + 17) % n AS dst FROM st, many, generate_series(0, {targets - 1}) AS g(t) WHERE obj % 100 = 0) p
  WHERE src <> dst AND NOT EXISTS (SELECT 1 FROM d2 WHERE a = src AND b = dst AND dist <= {theta} + 1e-12))"""


def least(rounds: int) -> str:
    """Steps after pairs, arcs(a, b, dist) and goals(src of the last hop a, dst b, dist): paths(pair_id, src, dst, cost), cost null without a path."""
    out = ", w0 AS MATERIALIZED (SELECT DISTINCT src, src AS node, 0.0::DOUBLE AS cost FROM pairs)"
    for i in range(1, rounds + 1):
        out += f""",
w{i} AS MATERIALIZED (SELECT src, node, min(cost) AS cost FROM (SELECT src, node, cost FROM w{i - 1} UNION ALL SELECT w.src, arcs.b, w.cost + arcs.dist FROM w{i - 1} w JOIN arcs ON arcs.a = w.node) GROUP BY 1, 2)"""
    return out + f""",
ways AS (SELECT p.pair_id, w.cost FROM pairs p JOIN w{rounds} w ON w.src = p.src AND w.node = p.dst
  UNION ALL SELECT p.pair_id, w.cost + g.dist FROM pairs p JOIN w{rounds} w ON w.src = p.src JOIN goals g ON g.a = w.node AND g.b = p.dst),
paths AS MATERIALIZED (SELECT p.pair_id, p.src, p.dst, min(ways.cost) AS cost FROM pairs p LEFT JOIN ways USING (pair_id) GROUP BY 1, 2, 3)"""


SHOWN = " SELECT pair_id, src, dst, CASE WHEN cost IS NULL THEN 'no_path' ELSE 'found' END AS outcome, round(cost, 6) AS cost FROM paths"


def exact_paths(theta: float, b: int, targets: int, rounds: int = 16) -> str:
    """Least costs where an object offers its b nearest within theta, and the goal itself where it is near."""
    return PAIRS + BOTH_STEPS + f""", near AS MATERIALIZED (SELECT a, b, dist FROM d2 WHERE dist <= {theta} + 1e-12),
arcs AS MATERIALIZED (SELECT a, b, dist FROM near QUALIFY row_number() OVER (PARTITION BY a ORDER BY dist, b) <= {b}), goals AS (SELECT a, b, dist FROM near)""" + asked(theta, targets) + least(rounds)


def clique_paths(share: float, theta: float, m: int, b: int, targets: int, rounds: int = 16) -> str:
    """The same over the verified sets of two near neighbours; a last hop needs a candidate that is near both ends."""
    return REL_PBS + PAIR_STEPS + BOTH_STEPS + lattice(share) + LONGEST + RANKED + near_cliques(2, m, b, theta) + """,
arcs AS MATERIALIZED (SELECT DISTINCT obj AS a, n AS b, near.dist FROM (SELECT obj, unnest([n1, n2]) AS n FROM good) JOIN near ON near.a = obj AND near.b = n)""" + asked(theta, targets) + """,
goals AS MATERIALIZED (SELECT DISTINCT n.a, n.b, n.dist FROM (SELECT DISTINCT dst FROM pairs) p JOIN near n ON n.b = p.dst JOIN cand c ON c.obj = n.a AND c.nbr <> n.b AND c.dist <= """ + f"{theta} + 1e-12" + """
  JOIN near y ON y.a = c.nbr AND y.b = n.b)""" + least(rounds)


#: A relation by arithmetic, small enough for a lattice without pruning.
MICRO = "SELECT o::BIGINT AS obj, f::BIGINT AS feat, 1.0::DOUBLE AS val FROM generate_series(0, 39) AS a(o), generate_series(0, 11) AS b(f) WHERE (o * o + 3 * o * f + 7 * f) % 5 < 2"
