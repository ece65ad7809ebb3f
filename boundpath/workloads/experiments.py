"""The paper's experiments on the given tables: one row for each setting and method.

Pools of one experiment are row groups of one job (``services/pools.py``, ``embed_pools``)."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.baselines import kernels as K
from boundpath.baselines.exact import path_links
from boundpath.measures import measures as M
from boundpath.services import allocate as A
from boundpath.services import embed as E
from boundpath.services import pools as P
from boundpath.services.lp import max_min
from boundpath.topology import networks as N
from boundpath.topology import oracle as O
from boundpath.workloads.services import FLOWS_SQL, flows, testbed_requests

QUERIES, ORACLES = {}, {}


def register(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


#: The five solvers of the scaling comparison; all but the program use dominance.
SOLVERS = {"layered": "ldp", "layered_prefix": "ldp_prefix", "exhaustive": "ebfs", "exhaustive_suffix": "ebfs_suffix", "program": "arc_ip"}
#: The one that tells the others the network's states.
SCOUT = "layered_prefix"


def _summary(filled):
    """One row a pool: requests with a path, copies that fit, mean hops of a copy, partial paths (or program nodes) made per search."""
    return filled.groupBy("network", "severity", "solver").agg(
        F.count("*").alias("requests"), F.sum(F.when(F.col("copies") > 0, 1).otherwise(0)).alias("served"), F.sum("copies").alias("copies"),
        F.round(F.try_divide(F.sum("hops"), F.sum("copies")), 6).alias("mean_hops"), F.sum("searches").alias("searches"), F.sum("generated").alias("generated"), F.round(F.try_divide(F.sum("generated"), F.sum("searches")), 6).alias("per_search"),
    )


def _scale_pools(spark, d, networks):
    """networks: name -> (vertices' table, severities, solvers); a tenth of the vertices as requests."""
    parts = []
    for net, (who, severities, solvers) in networks.items():
        for sev in severities:
            parts += [({"network": net, "severity": sev, "solver": s}, N.requests(spark, d, sev, None, who)) for s in solvers]
    return P.as_pools(parts)


def _at_once(makers):
    """name -> network, made side by side."""
    with ThreadPoolExecutor(len(makers)) as threads:
        return dict(zip(makers, threads.map(lambda make: make(), makers.values()), strict=True))


def _scale(spark, d):
    nets = _at_once({"suppliers": lambda: N.n1_links(spark, d), "customers": lambda: N.n2_links(spark, d, most=None)})
    four = [s for s in SOLVERS if s != "program"]
    asks = _scale_pools(spark, d, {"suppliers": ("supplier", ("low", "med", "tight"), four), "customers": ("customer", ("low", "med", "tight"), four)})
    return P.fill_pools(nets, asks, SOLVERS, scout=SCOUT)


@register("w1_scale")
def w1_scale(spark, d):
    """A tenth of the vertices as requests, as many copies as fit, by severity and solver, on the supplier and customer networks."""
    return _summary(_scale(spark, d))


@register("w3_program")
def w3_program(spark, d):
    """The arc program beside the layered search on the testbed network (its graph is the smallest published size)."""
    asks = testbed_requests(spark)
    pools = P.as_pools([({"network": "testbed", "severity": "low", "solver": s}, asks) for s in SOLVERS])
    return _summary(P.fill_pools({"testbed": N.n4_links(spark, d)}, pools, SOLVERS))


@register("c2_path_times")
def c2_path_times(spark, d):
    """Milliseconds per search of every pool of the scaling comparison (times differ from run to run)."""
    return _scale(spark, d).groupBy("network", "severity", "solver").agg(F.round(F.try_divide(F.sum("map_ms"), F.sum("searches")), 4).alias("ms_per_search"), F.sum("searches").alias("searches"))


@register("w10_robust")
def w10_robust(spark, d):
    """The comparison on distance-random and preferential-attachment networks."""
    nets = _at_once({"distance": lambda: N.waxman_links(spark, d), "attachment": lambda: N.attach_links(spark, d)})
    four = [s for s in SOLVERS if s != "program"]
    return _summary(P.fill_pools(nets, _scale_pools(spark, d, {n: ("supplier", ("low", "med"), four) for n in nets}), SOLVERS, scout=SCOUT))


# testbed ------------------------------------------------------------------------------------------------------------------
#: Path finders of the testbed: extended Dijkstra on the bounded metric, iterative Bellman-Ford, the layered search in its one-bound
#: and its general form, exhaustive breadth first.
BED = {"ext_dijkstra": "least_cost", "iter_bellman_ford": "ibf", "layered_one_bound": "single", "layered_general": "ldp_prefix", "exhaustive": "ebfs"}


def _bed(spark, d):
    asks = testbed_requests(spark).withColumn("delay", F.lit(1 << 40))
    pools = P.as_pools([({"network": "testbed", "severity": "low", "solver": s}, asks) for s in BED])
    return P.fill_pools({"testbed": N.n4_links(spark, d)}, pools, BED)


@register("w9_testbed")
def w9_testbed(spark, d):
    """Units and hops that each path finder places on the testbed: five host pairs, one unit a copy, cost at most 50."""
    return _bed(spark, d).groupBy(F.col("solver").alias("method")).agg(F.sum("copies").alias("throughput"), F.round(F.try_divide(F.sum("hops"), F.sum("copies")), 6).alias("mean_hops"))


@register("c12_mapping_allocation")
def c12_mapping_allocation(spark, d):
    """Milliseconds to find a path and to enter it, in memory, and to commit the testbed's requests through the ledger's tables."""
    inside = _bed(spark, d).groupBy(F.col("solver").alias("method")).agg(F.round(F.try_divide(F.sum("map_ms"), F.sum("searches")), 4).alias("map_ms"), F.round(F.try_divide(F.sum("allocate_ms"), F.sum("paths")), 4).alias("allocate_ms"))
    links, asks = N.n4_links(spark, d), testbed_requests(spark).withColumn("delay", F.lit(1 << 40))
    _, find = timed(lambda: K.search(links, asks, "ldp_prefix"))
    rows, commit = timed(lambda: A.allocate(links, asks)[0])
    tables = spark.createDataFrame([("ledger", round(1000 * find / rows, 4), round(1000 * (commit - find) / rows, 4))], "method string, map_ms double, allocate_ms double")
    return inside.unionByName(tables)


# traffic engineering --------------------------------------------------------------------------------------------------------
STRETCHES = {"low": 4.0, "mid": 1.5, "high": 1.0}


def paths_for(arcs, r, k: int, constrained: bool) -> list[list]:
    """k paths of one flow: of fewest hops under its delay bound, or of least delay, of which those within the bound can be used."""
    g = K.Graph((s, t, bw, delay, delay) for s, t, bw, delay, _ in arcs)
    out = []
    for i, (key, _) in enumerate(K.next_shortest(g, r, "hops" if constrained else "cost", len(g.vertices), constrained)):
        if i == k or not constrained and key[0] > r.delay:
            break
        out.append(list(zip(key[3], key[3][1:], strict=False)))
    return out


TE_SCHEMA = "stretch double, k int, paths string, flows bigint, throughput double, least double, median double, mean_hops double"


def te_pools(spark, d, count: int, ks, stretches=tuple(STRETCHES.values()), degree: int = 4):
    """Max-min rates over k constrained or k shortest paths a flow, a task for each pool."""
    sent = P.broadcast_networks({"n1": N.n1_links(spark, d, degree)})
    parts = [({"stretch": s, "k": k, "paths": p}, flows(spark, d, count, s)) for s in stretches for k in ks for p in ("constrained", "k_shortest")]

    def run(f: pd.DataFrame) -> pd.DataFrame:
        arcs = P.arcs_of(sent, "n1")
        label = [f[c].iloc[0] for c in ("stretch", "k", "paths")]
        asks = sorted(f.assign(bw=0, cost=f["delay"]).itertuples(index=False), key=lambda r: r.flow_id)
        held = [paths_for(arcs, r, int(label[1]), label[2] == "constrained") for r in asks]
        got = max_min(held, {(s, t): bw for s, t, bw, _, _ in arcs})
        rates = sorted(sum(x) for x in got)
        total = sum(rates)
        hops = sum(x * len(p) for i, ps in enumerate(held) for p, x in zip(ps, got[i], strict=True))
        return pd.DataFrame([(*label, len(asks), round(total, 6), round(rates[0], 6), round(rates[len(rates) // 2], 6), round(hops / total, 6) if total else 0.0)], columns=[c.split()[0] for c in TE_SCHEMA.split(", ")])

    return P.as_pools(parts).groupBy("stretch", "k", "paths").applyInPandas(run, TE_SCHEMA)


@register("w4_te_sweep")
def w4_te_sweep(spark, d):
    """Total and least max-min throughput of twelve flows by the number of paths (1 to 25), three severities."""
    return te_pools(spark, d, 12, (1, 2, 5, 10, 25))


FINDERS = {"layered": "ldp_prefix", "least_delay": "least_delay"}


def _greedy(spark, d, count, degrees, stretches):
    nets = {f"n1-{g}": N.n1_links(spark, d, g) for g in degrees}
    parts = [({"network": f"n1-{g}", "degree": g, "stretch": s, "finder": x}, flows(spark, d, count, s)) for g in degrees for s in stretches for x in FINDERS]
    return P.greedy_pools(nets, P.as_pools(parts), FINDERS)


@register("w5_degree")
def w5_degree(spark, d):
    """Greedy filling of fifty flows by node degree, severity and finder: throughput, least rate, hops, energy over idle."""
    done = _greedy(spark, d, 50, (8, 6, 4, 2, 1), tuple(STRETCHES.values()))
    energy = 100 * (M.BUSY_W - M.IDLE_W) * F.max("used") / (M.IDLE_W * F.max("links"))
    return done.groupBy("degree", "stretch", "finder").agg(
        F.count("*").alias("flows"), F.round(F.sum("rate"), 3).alias("throughput"), F.round(F.min("rate"), 3).alias("least"),
        F.round(F.try_divide(F.sum(F.col("rate") * F.col("hops")), F.sum("rate")), 6).alias("mean_hops"), F.round(energy, 6).alias("energy_increase"),
    )


@register("te_fairness")
def te_fairness(spark, d):
    """Distribution of the flows' rates under greedy filling, degree 4 and low bounds: rate, flows at most so fast."""
    done = _greedy(spark, d, 50, (4,), (4.0,))
    each = done.groupBy("finder", "rate").agg(F.count("*").alias("n"))
    return each.withColumn("share", F.round(F.sum("n").over(Window.partitionBy("finder").orderBy("rate")) / F.sum("n").over(Window.partitionBy("finder")), 6))


@register("te_customers")
def te_customers(spark, d):
    """Greedy filling of a thousand flows on the customer network at the low bound, by finder."""
    nets = {"n2": N.n2_links(spark, d)}
    fl = flows(spark, d, 1000, 4.0, "customer")
    done = P.greedy_pools(nets, P.as_pools([({"network": "n2", "degree": 4, "stretch": 4.0, "finder": x}, fl) for x in FINDERS]), FINDERS)
    return done.groupBy("finder").agg(F.count("*").alias("flows"), F.round(F.sum("rate"), 3).alias("throughput"), F.round(F.try_divide(F.sum(F.col("rate") * F.col("hops")), F.sum("rate")), 6).alias("mean_hops"))


# embedding and chaining -------------------------------------------------------------------------------------------------------
METHODS = ("joint", "colgen", "auction")


def _pool_measures(done):
    """Allocation ratio, paths, hops of a path and energy over idle of every pool."""
    energy = 100 * (M.BUSY_W - M.IDLE_W) * F.max("used") / (M.IDLE_W * F.max("wires"))
    return done.groupBy("setting", "method", "finder").agg(
        F.round(F.avg("accepted"), 6).alias("ratio"), F.sum("paths").alias("paths"), F.round(F.try_divide(F.sum("hops"), F.sum("paths")), 6).alias("mean_hops"), F.round(energy, 6).alias("energy_increase")
    )


@register("w6_embedding")
def w6_embedding(spark, d):
    """Forty virtual networks of six nodes, virtual degree 1 to 5, by algorithm and finder."""
    nodes = E.vn_nodes(spark, d)
    pools = [(f"degree {g}", E.vn_links(nodes, g), METHODS, ("dijkstra", "ldp")) for g in (1, 2, 3, 4, 5)]
    return _pool_measures(E.embed_pools(N.n3_nodes(spark, d), N.n3_links(spark, d), nodes, pools))


@register("w7_chaining")
def w7_chaining(spark, d):
    """Forty chains of six functions by latency bound, from none to a quarter of the stretch."""
    nodes = E.vn_nodes(spark, d)
    pools = [(f"stretch {x}", E.chain_links(nodes, x), METHODS, ("dijkstra", "ldp")) for x in (None, 1.0, 0.5, 0.25)]
    return _pool_measures(E.embed_pools(N.n3_nodes(spark, d), N.n3_links(spark, d), nodes, pools))


@register("w8_optimum")
def w8_optimum(spark, d):
    """The optimum (one-shot, online) beside the other algorithms: forty virtual networks of three nodes, as chains and as full meshes; split links and
    paths computed beforehand too."""
    nodes = E.vn_nodes(spark, d).filter("pos < 3")
    pools = []
    for g, name in ((1, "chain"), (2, "mesh")):
        pools.append((name, E.vn_links(nodes, g), ("opt", "joint", "colgen", "colgen_split", "auction"), ("ldp",)))
        pools.append((name, E.vn_links(nodes, g), ("joint", "colgen", "auction"), ("dijkstra",)))
        pools.append((name, E.vn_links(nodes, g), ("joint", "auction"), ("kpaths",)))
    return _pool_measures(E.embed_pools(N.n3_nodes(spark, d), N.n3_links(spark, d), nodes, pools))


# batches and streams ------------------------------------------------------------------------------------------------------------
# the best path of a pair is within what dominance leaves of its source's paths, so sources are searched once
_BATCH = f"""WITH RECURSIVE {O.n1()},
 pair AS (SELECT DISTINCT flow_id, src, dst FROM ({FLOWS_SQL.format(count=10000, vertices='supplier', delay=4 * N.STRETCH)})),
 walk AS (SELECT src AS s, src AS v, 0 AS hops, CAST(0 AS BIGINT) AS delay, CAST(0 AS BIGINT) AS cost, [src] AS path FROM (SELECT DISTINCT src FROM pair)
   UNION ALL SELECT s, v, hops, delay, cost, path FROM (SELECT *, min(cost) OVER (PARTITION BY s, v, delay) AS level, min(cost) OVER (PARTITION BY s, v ORDER BY delay RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS less
     FROM (SELECT w.s, l.dst AS v, w.hops + 1 AS hops, w.delay + l.delay AS delay, w.cost + l.cost AS cost, list_append(w.path, l.dst) AS path FROM walk w JOIN n1 l ON l.src = w.v AND l.bw >= 1
       WHERE w.hops < 12 AND NOT list_contains(w.path, l.dst) AND w.delay + l.delay <= {4 * N.STRETCH} AND w.cost + l.cost <= 100)) WHERE cost = level AND (less IS NULL OR less > cost))
SELECT flow_id AS req_id, CAST(min(hops) AS BIGINT) AS hops FROM pair LEFT JOIN walk ON s = src AND v = dst GROUP BY flow_id"""


@register("w12_batch", _BATCH)
def w12_batch(spark, d):
    """Ten thousand requests from successive orders in one batch, as column generation asks for: fewest hops under low bounds."""
    asks = flows(spark, d, 10_000, 4.0).select(F.col("flow_id").alias("req_id"), "src", "dst", F.lit(1).cast("bigint").alias("bw"), "delay", F.lit(100).cast("bigint").alias("cost"))
    return K.search(N.n1_links(spark, d), asks, "ldp_prefix").select("req_id", "hops")


@register("w13_affected")
def w13_affected(spark, d):
    """Requests to be solved again after the last hour's events touched links."""
    from boundpath.streaming.linkstate import affected_requests, claims
    from boundpath.workloads.services import fixed_answers

    n1 = N.n1_links(spark, d).select("link_id", F.col("src").alias("a"), F.col("dst").alias("b"))
    late = claims(N.table(spark, d, "events"))
    newest = late.agg(F.max("ts").alias("top"))
    changed = late.crossJoin(F.broadcast(newest)).filter("ts > top - interval 1 hour").select(F.col("link_id").alias("a")).join(n1, "a").select("link_id")
    return affected_requests(path_links(fixed_answers(spark, d)).join(n1, ["a", "b"]), changed)


@register("w11_examples", "SELECT * FROM (VALUES ('all three bounds', '0>2>1>3', CAST(3 AS BIGINT), CAST(3 AS BIGINT), CAST(3 AS BIGINT)), ('no bandwidth bound', '0>2>3', 2, 2, 5)) t(bounds, path, hops, delay, cost)")
def w11_examples(spark, d):
    """The four-node example by the layered search: under all bounds, and without the bandwidth bound."""
    from boundpath.search.ldp import ldp_general

    links = N.example_links(spark)
    parts = []
    for label, bw in (("all three bounds", 5), ("no bandwidth bound", 0)):
        reqs = spark.createDataFrame([(0, 0, 3, bw, 5, 5)], "req_id bigint, src bigint, dst bigint, bw bigint, delay bigint, cost bigint")
        out = ldp_general(links, reqs).answers
        parts.append(({"bounds": label}, out.select(F.array_join("path", ">").alias("path"), "hops", "delay", "cost")))
    return P.as_pools(parts)


def timed(f):
    """(rows, seconds) of a query run to the end."""
    began = time.perf_counter()
    rows = f().count()
    return rows, time.perf_counter() - began
