"""Traffic engineering, allocation, embedding, chaining and measures on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from boundpath.baselines import kernels
from boundpath.baselines.exact import path_links
from boundpath.measures import measures as M
from boundpath.services import allocate as A
from boundpath.services import embed as E
from boundpath.services import te as T
from boundpath.topology import networks as N
from boundpath.topology import oracle as O
from boundpath.workloads import paths as P

QUERIES, ORACLES = {}, {}


def register(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


# kernels ---------------------------------------------------------------------------------------------------------------
def _kernel(method, severity, objective):
    def run(spark, d):
        return P.text(kernels.search(N.n1_links(spark, d), N.requests(spark, d, severity, 10), method, objective))

    return run


for _name, _method, _obj in (("edfs", "edfs", "cost"), ("edfs_hops", "edfs", "hops"), ("ldp_dfs", "dfs", "hops"), ("ldp_kshort_policy", "kshort", "cost"), ("kshort_exact", "kshort_exact", "cost")):
    register(_name, P._oracle("med", _obj))(_kernel(_method, "med", _obj))



@register("dfs_links", P._first_hop(None, "med"))
def dfs_links(spark, d):
    """Depth first with link bounds alone."""
    free = N.requests(spark, d, "med", 10).withColumns({"delay": F.lit(1 << 40), "cost": F.lit(1 << 40)})
    return kernels.search(N.n1_links(spark, d), free, "edfs", "hops").select("req_id", "status", "hops")


_FREE = P._ranked_sql("med", "cost, hops, delay, path", "r <= 3", 5).replace("AND w.delay + l.delay <= w.dmax AND w.cost + l.cost <= w.cmax", "")


@register("kshort", _FREE)
def kshort(spark, d):
    """Three shortest loop-free paths of at most five hops, path bounds ignored."""
    return P.text(kernels.k_shortest(N.n1_links(spark, d), N.requests(spark, d, "med", 10), 3, "cost", 5), "req_id", "status", "hops", "delay", "cost", "path", "rank")


_TESTBED = "req AS (SELECT r AS req_id, 100 + r AS src, 100 + (r + 2) % 5 AS dst, CAST(1 AS BIGINT) AS bw, CAST(5656 AS BIGINT) AS delay, CAST(50 AS BIGINT) AS cost FROM (SELECT unnest(range(5)) AS r))"


def testbed_requests(spark):
    r = spark.range(5).withColumnRenamed("id", "req_id")
    return r.select("req_id", (100 + F.col("req_id")).alias("src"), (100 + (F.col("req_id") + 2) % 5).alias("dst"), *[F.lit(v).cast("bigint").alias(c) for c, v in (("bw", 1), ("delay", 5656), ("cost", 50))])


@register("arc_ip_small", f"WITH RECURSIVE {O.n4()}, {_TESTBED}, {O.all_paths('n4')} SELECT q.req_id, CASE WHEN min(d.cost) IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, min(d.cost) AS cost FROM req q LEFT JOIN done d USING (req_id) GROUP BY q.req_id")
def arc_ip_small(spark, d):
    return kernels.search(N.n4_links(spark, d), testbed_requests(spark), "arc_ip", "cost").select("req_id", "status", "cost")


# fixed allocation and measures ----------------------------------------------------------------------------------------------
_PATHS = f"WITH RECURSIVE {O.n1()},\n {O.requests('low', '10')},\n {O.all_paths('n1', None, True)},\n ans AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY req_id ORDER BY hops, delay, cost, path) AS r FROM done) WHERE r = 1),\n hop AS (SELECT req_id, path[i] AS a, path[i + 1] AS b, i AS pos FROM ans, unnest(range(1, len(path))) t(i)),\n util AS (SELECT link_id, bw AS cap, CAST((SELECT count(*) FROM hop WHERE a = n1.src AND b = n1.dst) AS BIGINT) AS load FROM n1)\n"


def fixed_answers(spark, d):
    """Fewest-hop answers of the low pool, by the layered kernel."""
    return kernels.search(N.n1_links(spark, d), N.requests(spark, d, "low", 10), "ldp_prefix", "hops")


def fixed_loads(spark, d):
    n1 = N.n1_links(spark, d)
    return path_links(fixed_answers(spark, d)).join(n1.select("link_id", F.col("src").alias("a"), F.col("dst").alias("b")), ["a", "b"]).groupBy("link_id").agg(F.count("*").alias("load"))


@register("link_utilisation", _PATHS + "SELECT link_id, cap, load, round(load / cap, 6) AS u FROM util")
def link_utilisation(spark, d):
    return M.utilisation(N.n1_links(spark, d), fixed_loads(spark, d)).withColumn("u", F.round("u", 6))


@register("energy", _PATHS + "SELECT count(*) AS links, round(sum(0.3 * load / cap + 1.7), 6) AS watts, CAST(round(count(*) * 1.7, 6) AS DOUBLE) AS idle, round(100 * (sum(0.3 * load / cap + 1.7) / (count(*) * 1.7) - 1), 6) AS increase FROM util")
def energy(spark, d):
    return M.energy(M.utilisation(N.n1_links(spark, d), fixed_loads(spark, d)))


@register("hops_hist", _PATHS + "SELECT CAST(hops AS BIGINT) AS hops, count(*) AS paths FROM ans GROUP BY hops")
def hops_hist(spark, d):
    return M.hops_histogram(fixed_answers(spark, d))


@register("avg_hops", _PATHS + "SELECT count(*) AS paths, round(avg(hops), 6) AS mean_hops FROM ans")
def avg_hops(spark, d):
    return M.average_hops(fixed_answers(spark, d))


@register("confidence", _PATHS + "SELECT count(*) AS n, round(avg(hops), 6) AS mean, round(1.96 * stddev_samp(hops) / sqrt(count(*)), 6) AS half_width FROM ans")
def confidence(spark, d):
    return M.confidence95(fixed_answers(spark, d).filter("hops is not null"), "hops")


@register("alloc_ratio", f"WITH RECURSIVE {O.n1()}, {O.requests('med', '10')}, {O.all_paths('n1')} SELECT count(*) AS requested, count(*) FILTER (ok) AS accepted, round(avg(CASE WHEN ok THEN 1.0 ELSE 0.0 END), 6) AS ratio FROM (SELECT req_id IN (SELECT req_id FROM done) AS ok FROM req)")
def alloc_ratio(spark, d):
    found = kernels.search(N.n1_links(spark, d), N.requests(spark, d, "med", 10), "ldp_prefix", "hops")
    return M.allocation_ratio(found.select("req_id", (F.col("status") == "FOUND").cast("int").alias("accepted")))


@register("throughput_cdf", _PATHS.replace("util AS", "rate AS (SELECT req_id, min(bw) AS rate FROM hop JOIN n1 ON a = n1.src AND b = n1.dst GROUP BY req_id),\n util AS") + "SELECT rate, n, round(sum(n) OVER (ORDER BY rate) / (SELECT count(*) FROM rate), 6) AS share FROM (SELECT rate, count(*) AS n FROM rate GROUP BY rate)")
def throughput_cdf(spark, d):
    """Bottleneck rates of the low pool's paths."""
    n1 = N.n1_links(spark, d).select("bw", F.col("src").alias("a"), F.col("dst").alias("b"))
    return M.throughput_cdf(path_links(fixed_answers(spark, d)).join(n1, ["a", "b"]).groupBy("req_id").agg(F.min("bw").alias("rate")))


def _alloc_sql(count=10):
    """One request after the other, each on what the former ones left of every link: a table of rooms per request."""
    parts = [O.n1(), O.requests("med", str(count)), "left0 AS (SELECT * FROM n1)"]
    for i in range(count):
        walk = O.all_paths(f"left{i}").replace("walk", f"walk{i}").replace("done", f"done{i}").replace("FROM req", f"FROM (SELECT * FROM req WHERE req_id = {i})")
        parts.append(walk)
        parts.append(f"best{i} AS MATERIALIZED (SELECT req_id, hops, path, bw AS need FROM done{i} ORDER BY hops, delay, cost, path LIMIT 1)")
        parts.append(f"left{i + 1} AS MATERIALIZED (SELECT l.link_id, l.src, l.dst, l.bw - coalesce((SELECT max(need) FROM best{i} WHERE list_contains(list_zip(path[1:len(path) - 1], path[2:len(path)]), (l.src, l.dst))), 0) AS bw, l.delay, l.cost FROM left{i} l)")
    rows = " UNION ALL ".join(f"SELECT {i} AS req_id, * FROM (SELECT count(*) AS accepted, max(hops) AS hops, max(array_to_string(path, '>')) AS path FROM best{i})" for i in range(count))
    return "WITH RECURSIVE " + ",\n ".join(parts) + f"\nSELECT CAST(req_id AS BIGINT) AS req_id, CAST(accepted AS INTEGER) AS accepted, CAST(hops AS BIGINT) AS hops, path FROM ({rows})"


@register("alloc_strict", _alloc_sql())
def alloc_strict(spark, d):
    return A.allocate(N.n1_links(spark, d), N.requests(spark, d, "med", 10))[0].withColumn("path", F.array_join("path", ">"))


@register("alloc_first_commit")
def alloc_first_commit(spark, d):
    return A.allocate(N.n1_links(spark, d), N.requests(spark, d, "med", 10), "rounds")[0].withColumn("path", F.array_join("path", ">"))


# traffic engineering -----------------------------------------------------------------------------------------------------
#: Flows as SQL; fields: count, vertices, delay.
FLOWS_SQL = """SELECT flow_id, src, dst, CAST({delay} AS BIGINT) AS delay FROM (SELECT row_number() OVER (ORDER BY o_orderkey) - 1 AS flow_id, o_custkey % n AS src, lead(o_custkey) OVER (ORDER BY o_orderkey) % n AS dst
  FROM (SELECT o_orderkey, o_custkey FROM orders ORDER BY o_orderkey LIMIT {count} + 1), (SELECT least(count(*), 10000) AS n FROM {vertices})) WHERE src <> dst AND dst IS NOT NULL"""


def flows(spark, d, count=50, severity=4.0, vertices="supplier"):
    """Pairs of the customers of successive orders, the first ``count``, as vertices of a network (keys modulo their number; pairs of one vertex are left out);
    delay bound of ``severity`` stretches."""
    from pyspark.sql.window import Window

    n = min(N.table(spark, d, vertices).count(), 10000)
    first = N.table(spark, d, "orders").select("o_orderkey", "o_custkey").orderBy("o_orderkey").limit(count + 1)
    order = Window.orderBy("o_orderkey")  # of count + 1 rows
    f = first.select((F.row_number().over(order) - 1).cast("bigint").alias("flow_id"), (F.col("o_custkey") % n).alias("src"), (F.lead("o_custkey").over(order) % n).alias("dst"), F.lit(int(severity * N.STRETCH)).cast("bigint").alias("delay"))
    return f.filter("src != dst")


_ROUND1 = P._first_hop("delay", "low").replace(O.requests("low", "10"), f"req AS (SELECT flow_id AS req_id, src, dst, CAST(0 AS BIGINT) AS bw, delay FROM ({FLOWS_SQL.format(count=10, vertices='supplier', delay=4 * N.STRETCH)}))")


@register("te_greedy_round1", _ROUND1)
def te_greedy_round1(spark, d):
    """Best paths of the first filling round."""
    return T.FINDERS["ldp"](N.n1_links(spark, d), T.flow_requests(flows(spark, d, 10))).select("req_id", "status", "hops", "delay")


def _filled(finder):
    def run(spark, d):
        """Rates of ten flows filled greedily until none has a path, in memory; ``te_greedy_tables`` is the loop over tables."""
        from boundpath.services import pools

        fl = pools.as_pools([({"network": "n1", "degree": 4, "stretch": 4.0, "finder": finder}, flows(spark, d, 10))])
        done = pools.greedy_pools({"n1": N.n1_links(spark, d)}, fl, {finder: {"ldp": "ldp_prefix", "ext_dijkstra": "least_delay"}[finder]})
        return done.select("flow_id", "rate", F.round("hops", 6).alias("hops"), "paths")

    return run


register("te_greedy")(_filled("ldp"))
register("te_greedy_dijkstra")(_filled("ext_dijkstra"))


@register("te_greedy_tables")
def te_greedy_tables(spark, d):
    """The same filling as a loop over tables, the testbed's flows."""
    asks = testbed_requests(spark).select(F.col("req_id").alias("flow_id"), "src", "dst", "delay")
    return T.te_greedy(N.n4_links(spark, d), asks)[0].select("flow_id", (F.col("rate") / 1000).alias("rate"))


@register("te_lp_small")
def te_lp_small(spark, d):
    return T.te_lp(N.n1_links(spark, d), flows(spark, d, 12), 3, True).withColumn("rate", F.round("rate", 6))


@register("te_lp_kshort")
def te_lp_kshort(spark, d):
    return T.te_lp(N.n1_links(spark, d), flows(spark, d, 12), 3, False).withColumn("rate", F.round("rate", 6))


@register("te_arc_lp")
def te_arc_lp(spark, d):
    """The testbed's flows by the arc program."""
    return T.te_arc_lp(N.n4_links(spark, d), testbed_requests(spark).withColumnRenamed("req_id", "flow_id")).withColumn("rate", F.round("rate", 6))


def _path_rows(spark, d):
    """Links of the low pool's paths as (flow_id, path_no, rank, link_id)."""
    n1 = N.n1_links(spark, d).select("link_id", F.col("src").alias("a"), F.col("dst").alias("b"))
    return path_links(fixed_answers(spark, d)).join(n1, ["a", "b"]).select(F.col("req_id").alias("flow_id"), F.lit(1).alias("path_no"), F.lit(1).alias("rank"), "link_id")


@register("te_oblivious", _PATHS + "SELECT req_id AS flow_id, round((SELECT min(cap / load) FROM util WHERE load > 0), 6) AS rate FROM ans")
def te_oblivious(spark, d):
    return T.te_oblivious(N.n1_links(spark, d), _path_rows(spark, d)).withColumn("rate", F.round("rate", 6))


@register("te_scale")
def te_scale(spark, d):
    caps = N.n1_links(spark, d).select("link_id", F.col("bw").cast("double").alias("cap"))
    return T.te_scale(_path_rows(spark, d), caps, 6)


# embedding and chaining ---------------------------------------------------------------------------------------------------
_VN = """line AS (SELECT l_orderkey, l_linenumber, CAST(l_quantity AS BIGINT) AS qty, count(*) OVER (PARTITION BY l_orderkey) AS n,
  row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) - 1 AS pos FROM lineitem),
 vn AS (SELECT l_orderkey AS vn_id, pos, 1 + qty % 10 AS cpu, qty, CAST(l_linenumber AS BIGINT) AS line FROM line WHERE n >= 6 AND pos < 6
  AND l_orderkey IN (SELECT DISTINCT l_orderkey FROM line WHERE n >= 6 ORDER BY l_orderkey LIMIT 40))"""


register("vn_nodes", f"WITH {_VN} SELECT vn_id, pos, cpu, qty, line FROM vn")(E.vn_nodes)


@register("vn_links", f"WITH {_VN} SELECT x.vn_id, x.pos AS a, y.pos AS b, 1 + y.qty % 10 AS demand, (1 + y.line % 4) * {N.STRETCH} AS delay_max FROM vn x JOIN vn y ON x.vn_id = y.vn_id AND x.pos < y.pos AND y.pos - x.pos <= 3")
def vn_links(spark, d):
    return E.vn_links(E.vn_nodes(spark, d), 3)


@register("chain_links", f"WITH {_VN} SELECT x.vn_id, x.pos AS a, y.pos AS b, 1 + y.qty % 10 AS demand, CAST(floor((1 + y.line % 4) * {N.STRETCH} * 0.25) AS BIGINT) AS delay_max FROM vn x JOIN vn y ON x.vn_id = y.vn_id AND y.pos = x.pos + 1")
def chain_links(spark, d):
    return E.chain_links(E.vn_nodes(spark, d), 0.25)


def _embed(setting, wires, methods, finders, size=6, count=40):
    def run(spark, d):
        nodes = E.vn_nodes(spark, d, count, 6).filter(F.col("pos") < size)
        done = E.embed_pools(N.n3_nodes(spark, d), N.n3_links(spark, d), nodes, [(setting, wires(nodes), methods, finders)])
        return done.drop("setting", "used", "wires").withColumns({c: F.round(c, 6) for c in ("cost", "load", "hops")})

    return run


for _m in ("joint", "colgen", "auction"):
    register(f"embed_{_m}")(_embed("degree 2", lambda n: E.vn_links(n, 2), (_m,), ("dijkstra", "ldp")))
    register(f"chain_{_m}")(_embed("stretch 1/2", lambda n: E.chain_links(n, 0.5), (_m,), ("dijkstra", "ldp")))
register("embed_split")(_embed("degree 2", lambda n: E.vn_links(n, 2), ("colgen_split",), ("ldp",)))
register("embed_kpaths")(_embed("degree 2", lambda n: E.vn_links(n, 2), ("auction",), ("kpaths",)))
register("embed_opt")(_embed("mesh", lambda n: E.vn_links(n, 2), ("opt",), ("ldp",), 3, 10))


@register("embed_gap")
def embed_gap(spark, d):
    """By how much of the optimum the balanced cost exceeds it: ten virtual networks of three nodes in a full mesh, each on the whole substrate."""
    done = None
    nodes = E.vn_nodes(spark, d, 10, 6).filter("pos < 3")
    alone = [(str(i), E.vn_links(nodes, 2).filter(F.col("vn_id") == vn), ("opt", *("joint", "colgen", "auction")), ("ldp",)) for i, (vn,) in enumerate(nodes.select("vn_id").distinct().orderBy("vn_id").collect())]
    every = E.embed_pools(N.n3_nodes(spark, d), N.n3_links(spark, d), nodes, alone)
    best = every.filter("method = 'opt'")
    for m in ("joint", "colgen", "auction"):
        one = M.optimality_gap(every.filter(F.col("method") == m), best).select(F.lit(m).alias("method"), "vn_id", "gap")
        done = one if done is None else done.unionByName(one)
    return done


@register("embed_cost", f"WITH {_VN} SELECT vn_id, CAST(sum(cpu) AS BIGINT) AS cpu_cost FROM vn GROUP BY vn_id")
def embed_cost(spark, d):
    """The CPU share of the embedding objective."""
    return E.vn_nodes(spark, d).groupBy("vn_id").agg(F.sum("cpu").alias("cpu_cost"))


@register("load_cost", f"WITH {O.N3NODE}, {_VN}, sub AS (SELECT v, cpu, row_number() OVER (ORDER BY cpu DESC, v) - 1 AS r FROM n3node) SELECT vn_id, round(sum(vn.cpu / greatest(1, sub.cpu)), 6) AS load_cost FROM vn JOIN sub ON sub.r = vn.pos GROUP BY vn_id")
def load_cost(spark, d):
    """CPU share of the balanced objective when position i sits on the i-th largest vertex."""
    from pyspark.sql.window import Window

    sub = N.n3_nodes(spark, d).withColumn("r", F.row_number().over(Window.orderBy(F.desc("cpu"), "v")) - 1).select("r", F.col("cpu").alias("room"))
    return E.vn_nodes(spark, d).join(sub, F.col("pos") == F.col("r")).groupBy("vn_id").agg(F.round(F.sum(F.col("cpu") / F.greatest(F.lit(1), F.col("room"))), 6).alias("load_cost"))


@register(
    "auction_winners",
    f"WITH {O.N3NODE}, {_VN}, ranked AS (SELECT v, cpu, row_number() OVER (ORDER BY cpu DESC, v) AS r FROM n3node), turns AS (SELECT vn_id, cpu AS need, row_number() OVER (PARTITION BY vn_id ORDER BY cpu DESC, pos) AS turn FROM vn) SELECT vn_id, CAST(turn AS INTEGER) AS turn, v AS winner FROM turns JOIN ranked ON r = turn WHERE cpu >= need",
)
def auction_winners(spark, d):
    return E.auction_winners(N.n3_nodes(spark, d), N.n3_links(spark, d), E.vn_nodes(spark, d))
