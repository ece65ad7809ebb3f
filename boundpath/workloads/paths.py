"""Path methods and baselines on the supplier network (ten requests unless said otherwise)."""

from __future__ import annotations

from pyspark.sql import functions as F

from boundpath.baselines import exact
from boundpath.plans.plan import solve
from boundpath.search import ldp, single
from boundpath.topology import networks as N
from boundpath.topology import oracle as O

QUERIES, ORACLES = {}, {}


def register(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def text(df, *columns):
    """Answers with the path as text."""
    out = df.withColumn("path", F.array_join("path", ">"))
    return out.select(*columns) if columns else out.select("req_id", "status", "hops", "delay", "cost", "path")


def _ten(spark, d, severity):
    return N.requests(spark, d, severity, 10)


def _oracle(severity, objective, extra="", net=None, netname="n1", dominance=None):
    """Best paths of any length; all paths are listed, with low bounds and for the undirected network those that dominance leaves."""
    listed = O.all_paths(netname, None, severity == "low" if dominance is None else dominance)
    return "WITH RECURSIVE " + (net or O.n1()) + ",\n " + O.requests(severity, "10") + ",\n " + listed + extra + "\n" + O.best(objective)


def _levels(metric: str, bounded: bool, depth: int, exact_hops: bool, net: str = "n1", bw: bool = True, back: bool = False) -> str:
    """b0 .. b<depth>: least total of a metric per (request, vertex): of exactly k hops, or of up to k."""
    limit = f" AND b.d + {metric} <= q.{metric.split('.')[1]}" if bounded else ""
    link = "AND l.bw >= q.bw" if bw else ""
    parts = ["b0 AS (SELECT req_id, src AS v, CAST(0 AS BIGINT) AS d FROM req)"]
    for k in range(1, depth + 1):
        step = f"SELECT b.req_id, l.dst AS v, b.d + {metric} AS d FROM b{k - 1} b JOIN req q USING (req_id) JOIN {net} l ON l.src = b.v {link}{limit}"
        if not exact_hops:
            step = f"SELECT req_id, v, d FROM b{k - 1} UNION ALL " + step
        parts.append(f"b{k} AS (SELECT req_id, v, min(d) AS d FROM ({step}) GROUP BY req_id, v)")
    return ",\n ".join(parts)


def _least(metric: str, severity: str, out: str, bounded=False, bw=True, depth=20, where="true") -> str:
    return (
        f"WITH {O.n1()},\n {O.requests(severity, '10')},\n {_levels(metric, False, depth, False, bw=bw)}\n"
        f"SELECT q.req_id, CASE WHEN b.d IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, b.d AS {out} FROM req q LEFT JOIN b{depth} b ON b.req_id = q.req_id AND b.v = q.dst AND {where}"
    )


def _first_hop(metric: str | None, severity: str, depth: int = 16) -> str:
    m = f"l.{metric}" if metric else "l.one"
    net = "n1" if metric else "(SELECT *, 1 AS one FROM n1)"
    rows = " UNION ALL ".join(f"SELECT req_id, v, d, CAST({k} AS BIGINT) AS hops FROM b{k}" for k in range(depth + 1))
    return (
        f"WITH {O.n1()},\n {O.requests(severity, '10')},\n {_levels(m, bool(metric), depth, True, net)},\n"
        f" hit AS (SELECT q.req_id, hops, d, row_number() OVER (PARTITION BY q.req_id ORDER BY hops) AS r FROM ({rows}) b JOIN req q ON q.req_id = b.req_id AND q.dst = b.v)\n"
        f"SELECT q.req_id, CASE WHEN h.d IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, h.hops" + (f", h.d AS {metric}" if metric else "") + " FROM req q LEFT JOIN hit h ON h.req_id = q.req_id AND r = 1"
    )


# networks -----------------------------------------------------------------------------------------------------------
for _name, _make, _sql in (
    ("n1_links", N.n1_links, O.n1() + " SELECT * FROM n1"),
    ("n2_links", N.n2_links, O.n2() + " SELECT * FROM n2"),
    ("n3_links", N.n3_links, O.n3() + " SELECT * FROM n3"),
    ("n4_links", N.n4_links, O.n4() + " SELECT * FROM n4"),
    ("waxman_links", N.waxman_links, O.WAXMAN + " SELECT * FROM waxman"),
    ("attach_links", N.attach_links, O.ATTACH + " SELECT * FROM attach"),
):
    register(_name, ("WITH RECURSIVE " if _name == "attach_links" else "WITH ") + _sql)(_make)

register("n3_nodes", "WITH " + O.N3NODE + " SELECT v, x, y, CAST(cpu AS BIGINT) AS cpu FROM n3node")(N.n3_nodes)


@register("mean_degree", f"WITH {O.n1()} SELECT CAST(count(*) AS BIGINT) AS links, CAST(count(DISTINCT src) AS BIGINT) AS vertices, round(count(*) / count(DISTINCT src), 6) AS mean_degree FROM n1")
def mean_degree(spark, d):
    n1 = N.n1_links(spark, d)
    return n1.agg(F.count("*").alias("links"), F.countDistinct("src").alias("vertices")).withColumn("mean_degree", F.round(F.col("links") / F.col("vertices"), 6))


# passes -------------------------------------------------------------------------------------------------------------
@register("link_prune", f"WITH {O.n1()}, {O.requests('med', '10')} SELECT DISTINCT link_id, n1.src, n1.dst, n1.bw FROM n1 JOIN req ON n1.bw >= req.bw")
def link_prune(spark, d):
    reqs = ldp.with_classes(_ten(spark, d, "med"), ("delay", "cost"))
    return ldp.prune_links(N.n1_links(spark, d), reqs).select("link_id", "src", "dst", "bw").distinct()


def _layers_sql(hops: int, labels: bool) -> str:
    keep = "WHERE l.bw >= c.bw AND l.dst <> c.src"
    parts = [f"cls AS (SELECT min(req_id) AS class_id, src, bw, delay, cost FROM req GROUP BY src, bw, delay, cost)", "y0 AS (SELECT class_id, src AS v, CAST(0 AS BIGINT) AS bd, CAST(0 AS BIGINT) AS bc FROM cls)"]
    for k in range(1, hops + 1):
        having = "HAVING min(bd + l.delay) <= any_value(c.delay) AND min(bc + l.cost) <= any_value(c.cost)" if labels else ""
        parts.append(f"y{k} AS (SELECT y.class_id, l.dst AS v, min(bd + l.delay) AS bd, min(bc + l.cost) AS bc FROM y{k - 1} y JOIN cls c USING (class_id) JOIN n1 l ON l.src = y.v {keep} GROUP BY y.class_id, l.dst {having})")
    rows = " UNION ALL ".join(f"SELECT class_id, {k} AS k, v, bd, bc FROM y{k}" for k in range(hops + 1))
    return f"WITH {O.n1()}, {O.requests('med', '10')}, " + ",\n ".join(parts) + f"\nSELECT class_id, CAST(k AS INTEGER) AS k, v{', bd AS best_delay, bc AS best_cost' if labels else ''} FROM ({rows})"


@register("forward_layers", _layers_sql(5, False))
def forward_layers(spark, d):
    return ldp.forward_layers(N.n1_links(spark, d), _ten(spark, d, "med"), 5, labels=False).select("class_id", "k", "v")


@register("prefix_labels", _layers_sql(5, True))
def prefix_labels(spark, d):
    return ldp.forward_layers(N.n1_links(spark, d), _ten(spark, d, "med"), 5)


@register(
    "suffix_labels",
    f"WITH {O.n1()}, req AS (SELECT DISTINCT dst AS req_id, dst AS src FROM ({'WITH ' + O.requests('low', '10')} SELECT dst FROM req)), back AS (SELECT dst AS src, src AS dst, delay FROM n1),\n "
    + _levels("l.delay", False, 20, False, "back", bw=False)
    + "\nSELECT req_id AS dst, v, d AS least FROM b20",
)
def suffix_labels(spark, d):
    return single.suffix_labels(N.n1_links(spark, d), _ten(spark, d, "low").select("dst"), "delay")


@register("arrivals", _first_hop(None, "low", 8).replace("'NONE'", "'NONE'"))
def arrivals(spark, d):
    return single.ldp_links(N.n1_links(spark, d), _ten(spark, d, "low"), 8).select("req_id", "status", "hops")


# the layered search ----------------------------------------------------------------------------------------------------
def _ldp(severity, objective, prune=("dom", "prefix"), **more):
    def run(spark, d):
        q = ldp.PathQuery(objective=objective, prune=frozenset(prune), **more)
        return text(ldp.ldp_general(N.n1_links(spark, d), _ten(spark, d, severity), q).answers)

    return run


for _sev in ("low", "med", "tight"):
    for _obj in ("hops", "cost"):
        register(f"ldp_{_obj}_{_sev}", _oracle(_sev, _obj))(_ldp(_sev, _obj))
register("ldp_plain", _oracle("med", "hops"))(_ldp("med", "hops", ()))
register("ldp_dom", _oracle("med", "cost"))(_ldp("med", "cost", ("dom",)))
register("ldp_prefix", _oracle("med", "cost"))(_ldp("med", "cost", ("prefix",)))
register("ldp_dom_prefix", _oracle("med", "cost"))(_ldp("med", "cost"))
register("ldp_incumbents", _oracle("med", "cost"))(_ldp("med", "cost", ("prefix", "incumbents")))
register("ldp_bound", _oracle("med", "cost"))(_ldp("med", "cost", ("bound",)))


@register("ldp_undirected", _oracle("med", "hops", net=O.n1() + ",\n und AS (SELECT src, dst, bw, delay, cost FROM n1 UNION ALL SELECT dst, src, bw, delay, cost FROM n1)", netname="und", dominance=True))
def ldp_undirected(spark, d):
    """Every link both ways; links between the same ends stay apart, each with its own bandwidth, delay and cost."""
    return text(ldp.ldp_general(N.undirected(N.n1_links(spark, d)), _ten(spark, d, "med")).answers)


_LOSS = "lossy AS (SELECT n1.*, CAST(ceil(-ln(1 - ((src * 7 + dst * 13) % 50) / 1000.0) * 1000000) AS BIGINT) AS loss FROM n1)"


def lossy(n1):
    """Links with a loss share of up to 5 %, as additive micro-units rounded up."""
    share = ((F.col("src") * 7 + F.col("dst") * 13) % 50) / F.lit(1000.0)
    return n1.withColumn("loss", F.ceil(-F.log(1 - share) * 1000000).cast("bigint"))


def _three_sql(columns: str, loss: int) -> str:
    walk = O.all_paths("lossy").replace("cost AS cmax, 0 AS hops", f"cost AS cmax, CAST(0 AS BIGINT) AS loss, 0 AS hops").replace("w.cmax, w.hops + 1 AS hops", "w.cmax, w.loss + l.loss AS loss, w.hops + 1 AS hops").replace("AND w.cost + l.cost <= w.cmax", f"AND w.cost + l.cost <= w.cmax AND w.loss + l.loss <= {loss}")
    return f"WITH RECURSIVE {O.n1()}, {_LOSS}, {O.requests('low', '10')}, {walk}\nSELECT q.req_id, CASE WHEN d.hops IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, CAST(d.hops AS BIGINT) AS hops, {columns} array_to_string(d.path, '>') AS path FROM req q LEFT JOIN (SELECT *, row_number() OVER (PARTITION BY req_id ORDER BY hops, delay, cost, loss, path) AS r FROM done) d ON d.req_id = q.req_id AND d.r = 1"


@register("ldp_three_bounds", _three_sql("d.delay, d.cost, d.loss,", 90000))
def ldp_three_bounds(spark, d):
    reqs = _ten(spark, d, "low").withColumn("loss", F.lit(90000).cast("bigint"))
    out = ldp.ldp_general(lossy(N.n1_links(spark, d)), reqs, ldp.PathQuery(metrics=("delay", "cost", "loss"))).answers
    return text(out, "req_id", "status", "hops", "delay", "cost", "loss", "path")


@register("ldp_loss", _three_sql("d.loss,", 60000))
def ldp_loss(spark, d):
    reqs = _ten(spark, d, "low").withColumn("loss", F.lit(60000).cast("bigint"))
    out = ldp.ldp_general(lossy(N.n1_links(spark, d)), reqs, ldp.PathQuery(metrics=("delay", "cost", "loss"), prune=frozenset({"prefix"}))).answers
    return text(out, "req_id", "status", "hops", "loss", "path")


def _ranked_sql(severity, order, where="true", hops=None, done="done"):
    return f"WITH RECURSIVE {O.n1()}, {O.requests(severity, '10')}, {O.all_paths('n1', hops)}\nSELECT req_id, 'FOUND' AS status, CAST(hops AS BIGINT) AS hops, delay, cost, array_to_string(path, '>') AS path, CAST(r AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY req_id ORDER BY {order}) AS r FROM {done}) WHERE {where}"


@register("ldp_k3", _ranked_sql("med", "cost, hops, delay, path", "r <= 3"))
def ldp_k3(spark, d):
    return text(ldp.ldp_k(N.n1_links(spark, d), _ten(spark, d, "med"), 3), "req_id", "status", "hops", "delay", "cost", "path", "rank")


@register("ldp_all", _ranked_sql("med", "hops, delay, cost, path"))
def ldp_all(spark, d):
    return text(ldp.ldp_all(N.n1_links(spark, d), _ten(spark, d, "med")), "req_id", "status", "hops", "delay", "cost", "path", "rank")


@register("ldp_pareto", _ranked_sql("med", "hops, delay, cost, path", done="(SELECT * FROM done a WHERE NOT EXISTS (SELECT 1 FROM done b WHERE b.req_id = a.req_id AND b.delay <= a.delay AND b.cost <= a.cost AND (b.delay < a.delay OR b.cost < a.cost)))"))
def ldp_pareto(spark, d):
    return text(ldp.ldp_pareto(N.n1_links(spark, d), _ten(spark, d, "med")), "req_id", "status", "hops", "delay", "cost", "path", "rank")


@register("ldp_single", _first_hop("delay", "med"))
def ldp_single(spark, d):
    return single.ldp_single(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "hops", "delay")


@register(
    "ldp_single_status",
    "WITH " + O.n1() + ", " + O.requests("tight", "10") + ", " + _levels("l.delay", False, 30, False)
    + " SELECT q.req_id, CASE WHEN b.d <= q.delay THEN 'FOUND' WHEN b.d IS NULL THEN 'UNREACHABLE' ELSE 'INFEASIBLE' END AS status FROM req q LEFT JOIN b30 b ON b.req_id = q.req_id AND b.v = q.dst",
)
def ldp_single_status(spark, d):
    return single.ldp_single_status(N.n1_links(spark, d), _ten(spark, d, "tight"), N.table(spark, d, "supplier").count())


register("ldp_links", _first_hop(None, "med"))(lambda spark, d: single.ldp_links(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "hops"))
register("bfs_links", _first_hop(None, "med"))(lambda spark, d: solve(N.n1_links(spark, d), _ten(spark, d, "med"), ()).select("req_id", "status", "hops"))
register("ldp_links_cost", _least("l.cost", "med", "cost"))(lambda spark, d: single.ldp_links_cost(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "cost"))


# baselines ------------------------------------------------------------------------------------------------------------
register("dijkstra_cost", _least("l.cost", "low", "cost", bw=False))(lambda spark, d: exact.shortest_path(N.n1_links(spark, d), _ten(spark, d, "low")).select("req_id", "status", "cost"))
register("dijkstra_delay", _least("l.delay", "low", "delay", bw=False))(lambda spark, d: exact.shortest_path(N.n1_links(spark, d), _ten(spark, d, "low"), "delay").select("req_id", "status", "delay"))
register("ext_dijkstra_l", _least("l.cost", "med", "cost"))(lambda spark, d: exact.ext_dijkstra(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "cost"))
register("ext_dijkstra_l1", _least("l.delay", "med", "delay", where="b.d <= q.delay"))(lambda spark, d: exact.ext_dijkstra_bounded(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "delay"))
register("iter_bf", _first_hop("delay", "med"))(lambda spark, d: exact.iter_bellman_ford(N.n1_links(spark, d), _ten(spark, d, "med")).select("req_id", "status", "hops", "delay"))
register("ebfs", _oracle("med", "hops"))(lambda spark, d: text(exact.ebfs(N.n1_links(spark, d), _ten(spark, d, "med"))))
register("ebfs_dom", _oracle("med", "cost"))(lambda spark, d: text(exact.ebfs(N.n1_links(spark, d), _ten(spark, d, "med"), "cost", dominance=True)))
register("ebfs_suffix", _oracle("med", "cost"))(lambda spark, d: text(exact.ebfs(N.n1_links(spark, d), _ten(spark, d, "med"), "cost", dominance=True, suffix=True)))


@register("mixed_metric", _least("(l.delay + 50 * l.cost)", "med", "mixed"))
def mixed_metric(spark, d):
    """Least delay + 50 * cost; whether its path keeps the bounds is ``mixed_checked``."""
    return exact.mixed_metric(N.n1_links(spark, d), _ten(spark, d, "med"), {"delay": 1, "cost": 50}).select("req_id", F.when(F.col("mixed").isNull(), "NONE").otherwise("FOUND").alias("status"), "mixed")


@register("mixed_checked")
def mixed_checked(spark, d):
    """The mixed metric's paths with their bounds checked: FOUND where they keep them."""
    return text(exact.mixed_metric(N.n1_links(spark, d), _ten(spark, d, "med"), {"delay": 1, "cost": 50}))


register("lagrangian")(lambda spark, d: text(exact.lagrangian(N.n1_links(spark, d), _ten(spark, d, "med"))))


@register(
    "two_bound_dp",
    "WITH RECURSIVE " + O.n1() + ",\n " + O.requests("tight", "10") + ",\n " + O.all_paths("n1")
    + "\nSELECT q.req_id, CASE WHEN d.cost IS NULL THEN 'NONE' ELSE 'FOUND' END AS status, d.cost, d.delay FROM req q LEFT JOIN (SELECT *, row_number() OVER (PARTITION BY req_id ORDER BY cost, delay, path) AS r FROM done) d ON d.req_id = q.req_id AND d.r = 1",
)
def two_bound_dp(spark, d):
    return exact.two_bound_dp(N.n1_links(spark, d), _ten(spark, d, "tight"))


# counts ---------------------------------------------------------------------------------------------------------------
@register("count_ebfs", "WITH RECURSIVE " + O.n1() + ", " + O.requests("med", "10") + ", " + O.all_paths("n1") + " SELECT CAST(hops AS INTEGER) AS step, CAST(count(*) AS BIGINT) AS generated, CAST(count(*) FILTER (v = dst) AS BIGINT) AS completed FROM walk WHERE hops > 0 GROUP BY hops")
def count_ebfs(spark, d):
    _, log = exact.ebfs(N.n1_links(spark, d), _ten(spark, d, "med"), "cost", stats=True)
    return spark.createDataFrame([(k, g, c) for k, g, _, c in log if g], "step int, generated bigint, completed bigint")


COUNTED = 6


def _count_ldp(prune):
    def run(spark, d):
        """What each step of each length up to six makes and keeps."""
        q = ldp.PathQuery(objective="hops", prune=frozenset(prune), max_hops=COUNTED)
        log = ldp.ldp_general(N.n1_links(spark, d), _ten(spark, d, "med"), q, stats=True).stats
        return spark.createDataFrame([(n, k, made, kept + done) for n, k, made, kept, done in log], "length int, step int, generated bigint, kept bigint")

    return run


def _count_sql(labels: bool) -> str:
    """The same counts, a chain of tables for each length: what joins with the layer, and what dominance (and labels) keep of it."""
    parts = ["cls AS (SELECT min(req_id) AS class_id, src, bw, delay, cost FROM req GROUP BY src, bw, delay, cost)", "y0 AS (SELECT class_id, src AS v, CAST(0 AS BIGINT) AS bd, CAST(0 AS BIGINT) AS bc FROM cls)"]
    having = "HAVING min(bd + l.delay) <= any_value(c.delay) AND min(bc + l.cost) <= any_value(c.cost)" if labels else ""
    for k in range(1, COUNTED + 1):
        parts.append(f"y{k} AS MATERIALIZED (SELECT y.class_id, l.dst AS v, min(bd + l.delay) AS bd, min(bc + l.cost) AS bc FROM y{k - 1} y JOIN cls c USING (class_id) JOIN n1 l ON l.src = y.v AND l.bw >= c.bw AND l.dst <> c.src GROUP BY y.class_id, l.dst {having})")
    known, rows = "SELECT req_id FROM req WHERE false", []
    for n in range(1, COUNTED + 1):
        parts.append(f"h{n}_{n} AS MATERIALIZED (SELECT req_id, class_id, r.bw, r.delay AS md, r.cost AS mc, dst AS v, [dst] AS path, CAST(0 AS BIGINT) AS d, CAST(0 AS BIGINT) AS c FROM req r JOIN cls USING (src, bw, delay, cost) WHERE src <> dst AND req_id NOT IN ({known}) AND (class_id, dst) IN (SELECT class_id, v FROM y{n}))")
        for k in range(n, 0, -1):
            parts.append(f"m{n}_{k} AS MATERIALIZED (SELECT req_id, h.class_id, h.bw, md, mc, l.src AS v, list_prepend(l.src, path) AS path, d + l.delay AS d, c + l.cost AS c, bd, bc FROM h{n}_{k} h JOIN n1 l ON l.dst = h.v AND l.bw >= h.bw JOIN y{k - 1} y ON y.class_id = h.class_id AND y.v = l.src WHERE NOT list_contains(path, l.src))")
            kept = f"(SELECT * FROM m{n}_{k}{' WHERE d + bd <= md AND c + bc <= mc' if labels else ''})"
            parts.append(f"h{n}_{k - 1} AS MATERIALIZED (SELECT req_id, class_id, bw, md, mc, v, path, d, c FROM (SELECT *, min(c) OVER (PARTITION BY req_id, v, d) AS level, min(c) OVER (PARTITION BY req_id, v ORDER BY d RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS less FROM {kept}) WHERE c = level AND (less IS NULL OR less > c))")
            gone = "" if k == n else f" WHERE (SELECT count(*) FROM h{n}_{k}) > 0"
            rows.append(f"SELECT {n} AS length, {k} AS step, (SELECT count(*) FROM m{n}_{k}) AS generated, (SELECT count(*) FROM h{n}_{k - 1}) AS kept{gone}")
        rows.append(f"SELECT {n}, 0, 0, (SELECT count(*) FROM h{n}_0 WHERE d <= md AND c <= mc) WHERE (SELECT count(*) FROM h{n}_0) > 0")
        known += f" UNION SELECT req_id FROM h{n}_0 WHERE d <= md AND c <= mc"
    return f"WITH {O.n1()}, {O.requests('med', '10')}, " + ",\n ".join(parts) + "\n" + "\nUNION ALL ".join(rows)


register("count_ldp", _count_sql(False))(_count_ldp(("dom",)))
register("count_ldp_prefix", _count_sql(True))(_count_ldp(("dom", "prefix")))


_SIZES = f"arc AS (SELECT DISTINCT src, dst FROM ({O._SUCC}) WHERE dst IS NOT NULL AND src <> dst), size AS (SELECT (SELECT count(*) FROM (SELECT src FROM arc UNION SELECT dst FROM arc)) AS v, (SELECT count(*) FROM arc) AS e)"
_BOUND_ROWS = """('links, hops', 'layered', 'V+E*l', v + e), ('links, hops', 'exhaustive', 'V+E*l', v + e), ('one bound, hops', 'layered', 'V*E+E*l', v * e + e),
 ('one bound, hops', 'iterative relaxation', 'V*E+E*l', v * e + e), ('several bounds', 'layered', 'b^(V/2)*p+E*l', v / 2), ('several bounds', 'exhaustive', 'b^V*p+E*l', v)"""


@register("bounds_table", f"WITH {_SIZES} SELECT problem, method, v, e, formula, CAST(value AS DOUBLE) AS value FROM size, LATERAL (VALUES {_BOUND_ROWS}) t(problem, method, formula, value)")
def bounds_table(spark, d):
    """Worst-case work of each case on the suppliers' succession network, all arcs of it."""
    from boundpath.measures.measures import bounds

    lines = N.table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    arcs = N.succession(lines, "l_orderkey", "l_suppkey", ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]).select("src", "dst")
    ends = arcs.groupBy("src").agg(F.count("*").alias("e")).unionByName(arcs.select(F.col("dst").alias("src")).distinct().withColumn("e", F.lit(0).cast("bigint")))
    return bounds(ends.groupBy("src").agg(F.sum("e").alias("e")).agg(F.count("*").alias("v"), F.coalesce(F.sum("e"), F.lit(0)).cast("bigint").alias("e")))
