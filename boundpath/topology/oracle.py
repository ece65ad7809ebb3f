"""The networks as DuckDB SQL: common table expressions that the oracles start with."""

from __future__ import annotations

from boundpath.topology.networks import SEVERITY

SNODE = """snode AS (SELECT s_suppkey AS v, (s_suppkey * 7919 + CAST(s_nationkey AS BIGINT) * 104729) % 1000 AS x,
 (s_suppkey * 6101 + CAST(round(s_acctbal * 100) AS BIGINT) + 1000000) % 1000 AS y FROM supplier)"""
CNODE = """cnode AS (SELECT c_custkey AS v, (c_custkey * 7919 + CAST(c_nationkey AS BIGINT) * 104729) % 1000 AS x,
 (c_custkey * 6101 + CAST(round(c_acctbal * 100) AS BIGINT) + 1000000) % 1000 AS y FROM customer)"""
_DIST = "CAST(floor(sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE))) AS BIGINT) + 1"


def _net(name: str, arcs: str, nodes: str, bw: str, degree: int, where: str = "true") -> str:
    return f"""{name}_arc AS (SELECT src, dst, count(*) AS n, sum(CAST(l_quantity AS BIGINT)) AS qty FROM ({arcs})
   WHERE dst IS NOT NULL AND src <> dst AND {where} GROUP BY src, dst),
 {name}_top AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY n DESC, qty DESC, dst) AS r FROM {name}_arc) WHERE r <= {degree}),
 {name} AS (SELECT src * 1000000 + dst AS link_id, src, dst, CAST({bw} AS BIGINT) AS bw, {_DIST} AS delay,
   CAST(1 + (7 * qty + 3 * src + 5 * dst) % 10 AS BIGINT) AS cost FROM {name}_top JOIN {nodes} a ON a.v = src JOIN {nodes} b ON b.v = dst)"""


_SUCC = """SELECT l_suppkey AS src, l_quantity, lead(l_suppkey) OVER (PARTITION BY l_orderkey
   ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS dst FROM lineitem"""
_CSUCC = """SELECT o_custkey AS src, l_quantity, lead(o_custkey) OVER (PARTITION BY l_suppkey
   ORDER BY l_shipdate, l_orderkey, o_custkey, l_linenumber, l_quantity) AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey"""
_TRADE = """SELECT CAST(s_nationkey AS BIGINT) AS src, CAST(c_nationkey AS BIGINT) AS dst, l_quantity FROM lineitem
   JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey JOIN customer ON c_custkey = o_custkey"""


def n1(degree: int = 4) -> str:
    return SNODE + ",\n " + _net("n1", _SUCC, "snode", "1 + qty % 9", degree)


def n2(degree: int = 4) -> str:
    return CNODE + ",\n " + _net("n2", _CSUCC, "cnode", "1 + qty % 10", degree, "src < 10000 AND dst < 10000")


N3NODE = """n3node AS (SELECT CAST(n_nationkey AS BIGINT) AS v, (CAST(n_nationkey AS BIGINT) * 397) % 1000 AS x,
  (CAST(n_nationkey AS BIGINT) * 613 + CAST(n_regionkey AS BIGINT) * 200) % 1000 AS y,
  (7 * (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) + 13 * CAST(n_nationkey AS BIGINT)) % 101 AS cpu FROM nation WHERE n_nationkey < 20)"""


def n3() -> str:
    return N3NODE + ",\n " + _net("n3", _TRADE, "n3node", "qty % 101", 8, "src < 20 AND dst < 20")


def n4() -> str:
    core = SNODE + ",\n " + _net("n4core", _SUCC, "snode", "1 + qty % 9", 4, "src < 10 AND dst < 10")
    return core + """,
 hosts AS (SELECT CAST(r_regionkey AS BIGINT) + 100 AS h, CAST(r_regionkey AS BIGINT) * 2 AS s FROM region),
 n4 AS (SELECT * FROM n4core UNION ALL SELECT h * 1000000 + s, h, s, 10, 1, 0 FROM hosts UNION ALL SELECT s * 1000000 + h, s, h, 10, 1, 0 FROM hosts)"""


WAXMAN = SNODE + """,
 wpair AS (SELECT a.v AS av, b.v AS bv, sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE)) AS d FROM snode a JOIN snode b ON a.v < b.v),
 whalf AS (SELECT av, bv, d FROM wpair WHERE (av * 7919 + bv * 104729 + 31 * ((av * bv) % 1009)) % 10007
   < floor(10007.0 * least(1.0, 26.0 / (SELECT count(*) FROM snode)) * exp(-d / 200))),
 wend AS (SELECT av AS src, bv AS dst, d FROM whalf UNION ALL SELECT bv, av, d FROM whalf),
 waxman AS (SELECT src * 1000000 + dst AS link_id, src, dst, 1 + (src + dst) % 9 AS bw, CAST(floor(d) AS BIGINT) + 1 AS delay, 1 + (7 * (src + dst) + 3) % 10 AS cost FROM wend)"""


def requests(severity: str = "low", count: str | None = None, vertices: str = "supplier") -> str:
    bw, delay, cost = SEVERITY[severity]
    n = f"(SELECT least(count(*), 10000) FROM {vertices})"
    many = count or f"greatest(10, {n} // 10)"
    return f"""req AS (SELECT r AS req_id, (37 * r) % {n} AS src,
   CASE WHEN (37 * r) % {n} = (53 * r + 11) % {n} THEN ((53 * r + 11) % {n} + 1) % {n} ELSE (53 * r + 11) % {n} END AS dst,
   CAST({bw} AS BIGINT) AS bw, CAST({delay} AS BIGINT) AS delay, CAST({cost} AS BIGINT) AS cost FROM (SELECT unnest(range({many})) AS r))"""


def all_paths(net: str = "n1", hops: int | None = None, dominance: bool = False) -> str:
    """walk: every loop-free path from a request's source under its bounds (of at most ``hops`` links); done: those that reach the destination.

    dominance: of the paths to one vertex by equally many links, those that another beats in delay and cost are left out, so that best
    paths of any length can be listed."""
    step = f"""SELECT w.req_id, l.dst AS v, w.dst, w.bw, w.dmax, w.cmax, w.hops + 1 AS hops, w.delay + l.delay AS delay, w.cost + l.cost AS cost, list_append(w.path, l.dst) AS path
   FROM walk w JOIN {net} l ON l.src = w.v AND l.bw >= w.bw WHERE w.v <> w.dst{f' AND w.hops < {hops}' if hops else ''} AND NOT list_contains(w.path, l.dst)
     AND w.delay + l.delay <= w.dmax AND w.cost + l.cost <= w.cmax"""
    if dominance:
        step = f"""SELECT req_id, v, dst, bw, dmax, cmax, hops, delay, cost, path FROM (SELECT *, min(cost) OVER (PARTITION BY req_id, v, delay) AS level,
     min(cost) OVER (PARTITION BY req_id, v ORDER BY delay RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS less FROM ({step})) WHERE cost = level AND (less IS NULL OR less > cost)"""
    return f"""walk AS (SELECT req_id, src AS v, dst, bw, delay AS dmax, cost AS cmax, 0 AS hops, CAST(0 AS BIGINT) AS delay, CAST(0 AS BIGINT) AS cost, [src] AS path FROM req
   UNION ALL {step}),
 done AS (SELECT * FROM walk WHERE v = dst)"""


def best(objective: str = "hops") -> str:
    """The canonical best path of each request, as answers."""
    order = {"hops": "hops, delay, cost, path", "cost": "cost, hops, delay, path"}[objective]
    return f"""SELECT q.req_id, CASE WHEN d.hops IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, CAST(d.hops AS BIGINT) AS hops, d.delay, d.cost,
 array_to_string(d.path, '>') AS path FROM req q LEFT JOIN (SELECT *, row_number() OVER (PARTITION BY req_id ORDER BY {order}) AS r FROM done) d ON d.req_id = q.req_id AND d.r = 1"""


#: Copies of earlier slots followed to an owner (even slots own themselves; the first vertex copies vertex 0).
ATTACH = """far AS (SELECT s_suppkey AS i, e, 4 * s_suppkey + 2 * e + 1 AS cur FROM supplier, (VALUES (0), (1)) t(e) WHERE s_suppkey > 0),
 chase AS (SELECT i, e, CAST(cur AS BIGINT) AS cur FROM far
   UNION ALL SELECT i, e, CASE WHEN cur // 4 = 1 THEN -1 ELSE 4 + ((cur - 1) * 7919 + 104729 * ((cur % 4) // 2) + 13) % greatest((cur // 4) * 4 - 4, 1) END FROM chase WHERE cur > 0 AND cur % 2 = 1),
 ends AS (SELECT DISTINCT greatest(i, g) AS a, least(i, g) AS b FROM (SELECT i, CASE WHEN cur < 0 THEN 0 ELSE cur // 4 END AS g FROM chase WHERE cur < 0 OR cur % 2 = 0) WHERE i <> g),
 both_ways AS (SELECT a AS src, b AS dst, a + b AS q FROM ends UNION ALL SELECT b, a, a + b FROM ends),
 attach AS (SELECT src * 1000000 + dst AS link_id, src, dst, 1 + q % 9 AS bw, 1 + (q * 37) % 1000 AS delay, 1 + (7 * q + 3) % 10 AS cost FROM both_ways)"""
