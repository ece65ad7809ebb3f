"""Operators that surround the path methods: scans, joins, aggregates, windows, sets, scalar functions, and the UDF surface."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.baselines.exact import path_links
from boundpath.baselines.kernels import search
from boundpath.functions.paths import path_pairs, path_udtf
from boundpath.operators.skyline import skyline
from boundpath.topology import networks as N
from boundpath.topology import oracle as O
from boundpath.workloads.services import _PATHS, fixed_answers, fixed_loads

QUERIES, ORACLES = {}, {}
NET = "WITH " + O.n1() + "\n"


def register(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def on_links(name, sql):
    """A query over the supplier network: f(links) against ``sql`` on n1."""

    def put(f):
        QUERIES[name] = lambda spark, d: f(N.n1_links(spark, d))
        ORACLES[name] = NET + sql
        return f

    return put


# scans and filters --------------------------------------------------------------------------------------------------------
on_links("scan_links", "SELECT src, dst, bw FROM n1")(lambda l: l.select("src", "dst", "bw"))


@register("scan_json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def scan_json_props(spark, d):
    return N.table(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


on_links("filter_bounds", "SELECT link_id, bw, cost FROM n1 WHERE bw BETWEEN 4 AND 8 AND cost IN (1, 3, 5, 7) AND bw IS NOT DISTINCT FROM bw")(
    lambda l: l.filter(F.col("bw").between(4, 8) & F.col("cost").isin(1, 3, 5, 7) & F.col("bw").eqNullSafe(F.col("bw"))).select("link_id", "bw", "cost")
)


@register("load_formats", NET + "SELECT f.fmt, n1.link_id, n1.bw, n1.cost FROM n1, (VALUES ('parquet'), ('json'), ('csv'), ('xml')) f(fmt)")
def load_formats(spark, d):
    """The network written and discovered again in every format."""
    import uuid

    from boundpath.loop import shared_dir
    from boundpath.sources.links import FORMATS, load_links, save_links

    base, out = f"{shared_dir(spark)}/formats-{uuid.uuid4().hex}", None
    for fmt in FORMATS:
        save_links(N.n1_links(spark, d), f"{base}/{fmt}", fmt)
        one = load_links(spark, f"{base}/{fmt}", fmt).select(F.lit(fmt).alias("fmt"), "link_id", "bw", "cost")
        out = one if out is None else out.unionByName(one)
    return out


# joins --------------------------------------------------------------------------------------------------------------------
@register("join_inner_ends", NET + "SELECT link_id, a.s_name AS from_name, b.s_name AS to_name FROM n1 JOIN supplier a ON a.s_suppkey = src JOIN supplier b ON b.s_suppkey = dst")
def join_inner_ends(spark, d):
    s = N.table(spark, d, "supplier").select("s_suppkey", "s_name")
    rows = N.n1_links(spark, d).join(s.withColumnsRenamed({"s_suppkey": "src", "s_name": "from_name"}), "src")
    return rows.join(s.withColumnsRenamed({"s_suppkey": "dst", "s_name": "to_name"}), "dst").select("link_id", "from_name", "to_name")


@register("join_left_unused", _PATHS + "SELECT link_id, load FROM util")
def join_left_unused(spark, d):
    return N.n1_links(spark, d).select("link_id").join(fixed_loads(spark, d), "link_id", "left").withColumn("load", F.coalesce("load", F.lit(0)))


@register("join_full_load", _PATHS + ", odd AS (SELECT link_id, load FROM util WHERE load > 0 UNION ALL SELECT CAST(-1 AS BIGINT), CAST(7 AS BIGINT)) SELECT coalesce(n1.link_id, odd.link_id) AS link_id, bw, load FROM n1 FULL OUTER JOIN odd ON n1.link_id = odd.link_id".replace(", odd", ", odd", 1))
def join_full_load(spark, d):
    odd = fixed_loads(spark, d).union(spark.createDataFrame([(-1, 7)], "link_id bigint, load bigint"))
    return N.n1_links(spark, d).select("link_id", "bw").join(odd, "link_id", "full")


on_links("join_semi_layer", "SELECT link_id FROM n1 WHERE src IN (SELECT dst FROM n1 WHERE src = 0)")(lambda l: l.join(l.filter("src = 0").select(F.col("dst").alias("src")), "src", "left_semi").select("link_id"))
on_links("join_anti_visited", "SELECT link_id FROM n1 WHERE NOT EXISTS (SELECT 1 FROM n1 m WHERE m.src = 0 AND m.dst = n1.dst)")(lambda l: l.join(l.filter("src = 0").select("dst"), "dst", "left_anti").select("link_id"))


@register("join_cross_assign", f"WITH {O.N3NODE} SELECT pos, need, v FROM (VALUES (CAST(0 AS BIGINT), CAST(10 AS BIGINT)), (1, 40), (2, 70)) t(pos, need) CROSS JOIN n3node WHERE cpu >= need")
def join_cross_assign(spark, d):
    """A stated request of three virtual nodes against all substrate vertices."""
    asked = spark.createDataFrame([(0, 10), (1, 40), (2, 70)], "pos bigint, need bigint")
    return N.n3_nodes(spark, d).crossJoin(F.broadcast(asked)).filter("cpu >= need").select("pos", "need", "v")


on_links("join_theta_dominance", "SELECT a.link_id AS better, b.link_id AS worse FROM n1 a JOIN n1 b ON a.src = b.src AND a.delay <= b.delay AND a.cost <= b.cost AND (a.delay < b.delay OR a.cost < b.cost)")(
    lambda l: l.alias("a").join(l.alias("b"), F.expr("a.src = b.src and a.delay <= b.delay and a.cost <= b.cost and (a.delay < b.delay or a.cost < b.cost)")).select(F.col("a.link_id").alias("better"), F.col("b.link_id").alias("worse"))
)
on_links("join_range_delay", "SELECT a.link_id AS one, b.link_id AS other FROM n1 a JOIN n1 b ON a.src = b.src AND b.delay BETWEEN a.delay - 10 AND a.delay + 10 AND a.link_id <> b.link_id")(
    lambda l: l.alias("a").join(l.alias("b"), F.expr("a.src = b.src and b.delay between a.delay - 10 and a.delay + 10 and a.link_id != b.link_id")).select(F.col("a.link_id").alias("one"), F.col("b.link_id").alias("other"))
)


@register("join_interval_state", "SELECT a.event_id AS event_id, count(b.event_id) AS earlier FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR GROUP BY a.event_id")
def join_interval_state(spark, d):
    """Events of the same link in the hour before: a range window, where a join would pair a hot link with itself."""
    e = N.table(spark, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    us = F.unix_micros("ts")
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, -1)
    return e.withColumn("us", us).select("event_id", F.count("*").over(w).alias("earlier"))


@register("join_asof_state", "SELECT event_id, (SELECT max(b.event_id) FROM events b WHERE b.event_type = 'purchase' AND b.user_id = a.user_id AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.event_type = 'purchase' AND c.user_id = a.user_id AND c.ts <= a.ts)) AS latest FROM events a")
def join_asof_state(spark, d):
    """The latest purchase at or before each event of its user (ties: largest id), as a running window."""
    e = N.table(spark, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    hit = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return e.select("event_id", F.max(hit).over(w)["event_id"].alias("latest"))


for _hint in ("broadcast", "merge", "shuffle_hash"):
    on_links(f"join_{_hint}_two_hop", "SELECT a.link_id AS first, b.link_id AS second FROM n1 a JOIN n1 b ON a.dst = b.src")(
        lambda l, h=_hint: l.alias("a").join(l.alias("b").hint(h), F.col("a.dst") == F.col("b.src")).select(F.col("a.link_id").alias("first"), F.col("b.link_id").alias("second"))
    )


# aggregates ---------------------------------------------------------------------------------------------------------------
on_links("agg_two_hop", "SELECT a.src AS v, count(DISTINCT b.dst) AS ends FROM n1 a JOIN n1 b ON a.dst = b.src GROUP BY a.src")(
    lambda l: l.select("src", F.col("dst").alias("m")).join(l.select(F.col("src").alias("m"), F.col("dst").alias("e")), "m").groupBy(F.col("src").alias("v")).agg(F.countDistinct("e").alias("ends"))
)


@register("agg_grouping_sets", NET + "SELECT bw, cost, count(*) AS n FROM n1 GROUP BY GROUPING SETS ((bw, cost), (bw), ())")
def agg_grouping_sets(spark, d):
    return N.n1_links(spark, d).groupingSets([["bw", "cost"], ["bw"], []], "bw", "cost").agg(F.count("*").alias("n"))


@register("util_rollup", NET + "SELECT r_name, n_name, sum(bw) AS bw FROM n1 JOIN supplier ON s_suppkey = src JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)".replace("sum(bw)", "CAST(sum(bw) AS BIGINT)"))
def util_rollup(spark, d):
    s, n, r = (N.table(spark, d, t) for t in ("supplier", "nation", "region"))
    rows = N.n1_links(spark, d).join(s, F.col("s_suppkey") == F.col("src")).join(F.broadcast(n), F.col("n_nationkey") == F.col("s_nationkey")).join(F.broadcast(r), F.col("r_regionkey") == F.col("n_regionkey"))
    return rows.rollup("r_name", "n_name").agg(F.sum("bw").alias("bw"))


@register("hops_cube", _PATHS + "SELECT CAST(hops AS BIGINT) AS hops, cost, count(*) AS n FROM ans GROUP BY CUBE (hops, cost)")
def hops_cube(spark, d):
    return fixed_answers(spark, d).filter("hops is not null").cube("hops", "cost").agg(F.count("*").alias("n"))


@register("reach_distinct", NET + "SELECT a.src AS v, count(DISTINCT c.dst) AS reach FROM n1 a JOIN n1 b ON a.dst = b.src JOIN n1 c ON b.dst = c.src GROUP BY a.src")
def reach_distinct(spark, d):
    l = N.n1_links(spark, d).select("src", "dst")
    two = l.join(l.select(F.col("src").alias("dst"), F.col("dst").alias("d2")), "dst").select("src", "d2").distinct()
    three = two.join(l.select(F.col("src").alias("d2"), F.col("dst").alias("d3")), "d2").select("src", "d3")
    return three.groupBy(F.col("src").alias("v")).agg(F.countDistinct("d3").alias("reach"))


register("reach_approx")(lambda spark, d: N.n1_links(spark, d).agg(F.approx_count_distinct("dst", 0.02).alias("reach"), F.percentile_approx("delay", 0.5, 1000).alias("median_delay")))
on_links("percentile_delay", "SELECT src, median(delay) AS median_delay FROM n1 GROUP BY src")(lambda l: l.groupBy("src").agg(F.median("delay").alias("median_delay")))


# windows ------------------------------------------------------------------------------------------------------------------
class _BY:
    """Windows over the links of one source; made when a session exists."""

    @staticmethod
    def orderBy(*columns):
        return Window.partitionBy("src").orderBy(*columns)


on_links("topd_links", "SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY bw DESC, cost, dst) AS r FROM n1) WHERE r <= 2")(lambda l: l.withColumn("r", F.row_number().over(_BY.orderBy(F.desc("bw"), "cost", "dst"))).filter("r <= 2").select("src", "dst"))
on_links("kbest_rank", "SELECT link_id, CAST(rank() OVER (PARTITION BY src ORDER BY cost) AS INTEGER) AS r FROM n1")(lambda l: l.select("link_id", F.rank().over(_BY.orderBy("cost")).alias("r")))
on_links("dense_rank_cost", "SELECT link_id, CAST(dense_rank() OVER (PARTITION BY src ORDER BY cost) AS INTEGER) AS r FROM n1")(lambda l: l.select("link_id", F.dense_rank().over(_BY.orderBy("cost")).alias("r")))
on_links("ntile_delay", "SELECT link_id, CAST(ntile(2) OVER (PARTITION BY src ORDER BY delay, dst) AS INTEGER) AS q FROM n1")(lambda l: l.select("link_id", F.ntile(2).over(_BY.orderBy("delay", "dst")).alias("q")))
on_links("lead_succession", "SELECT link_id, lead(dst) OVER (PARTITION BY src ORDER BY dst) AS following, lag(dst) OVER (PARTITION BY src ORDER BY dst) AS before FROM n1")(lambda l: l.select("link_id", F.lead("dst").over(_BY.orderBy("dst")).alias("following"), F.lag("dst").over(_BY.orderBy("dst")).alias("before")))
on_links("running_residual", "SELECT link_id, CAST(20 - sum(bw) OVER (PARTITION BY src ORDER BY dst ROWS UNBOUNDED PRECEDING) AS BIGINT) AS left_over FROM n1")(lambda l: l.select("link_id", (20 - F.sum("bw").over(_BY.orderBy("dst").rowsBetween(Window.unboundedPreceding, 0))).alias("left_over")))
on_links("moving_load_range", "SELECT link_id, CAST(sum(bw) OVER (PARTITION BY src ORDER BY delay RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS BIGINT) AS near_bw FROM n1")(lambda l: l.select("link_id", F.sum("bw").over(_BY.orderBy("delay").rangeBetween(-100, 0)).alias("near_bw")))
on_links("cume_dist_delay", "SELECT link_id, round(cume_dist() OVER (PARTITION BY src ORDER BY delay), 6) AS share FROM n1")(lambda l: l.select("link_id", F.round(F.cume_dist().over(_BY.orderBy("delay")), 6).alias("share")))
on_links("top_links", "SELECT link_id, bw, delay FROM n1 ORDER BY bw DESC, delay, link_id LIMIT 10")(lambda l: l.select("link_id", "bw", "delay").orderBy(F.desc("bw"), "delay", "link_id").limit(10))


# sets ---------------------------------------------------------------------------------------------------------------------
on_links("union_mirror", "SELECT src, dst FROM n1 UNION SELECT dst, src FROM n1")(lambda l: l.select("src", "dst").union(l.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
on_links("intersect_paths", "SELECT src, dst FROM n1 INTERSECT SELECT dst, src FROM n1")(lambda l: l.select("src", "dst").intersect(l.select(F.col("dst").alias("src"), F.col("src").alias("dst"))))
on_links("except_paths", "SELECT bw FROM n1 EXCEPT ALL SELECT cost FROM n1")(lambda l: l.select("bw").exceptAll(l.select(F.col("cost").alias("bw"))))


_BOTH = f"WITH RECURSIVE {O.n1()}, {O.requests('med', '10')}, {O.all_paths('n1')}, short AS ({O.best('hops')}), cheap AS ({O.best('cost')}) SELECT req_id, path FROM short"


def _found(spark, d, method, objective):
    links, reqs = N.n1_links(spark, d), N.requests(spark, d, "med", 10)
    return search(links, reqs, method, objective).select("req_id", F.array_join("path", ">").alias("path"))


@register("paths_common", _BOTH + " INTERSECT SELECT req_id, path FROM cheap")
def paths_common(spark, d):
    """Requests whose shortest path is the cheapest too."""
    return _found(spark, d, "dfs", "hops").intersect(_found(spark, d, "dfs", "cost"))


@register("paths_diff", _BOTH + " EXCEPT ALL SELECT req_id, path FROM cheap")
def paths_diff(spark, d):
    return _found(spark, d, "dfs", "hops").exceptAll(_found(spark, d, "edfs", "cost"))


# scalar functions ---------------------------------------------------------------------------------------------------------
@register("path_text", _PATHS + "SELECT req_id, array_to_string(path, '>') AS path FROM ans")
def path_text(spark, d):
    return fixed_answers(spark, d).filter("path is not null").select("req_id", F.array_join("path", ">").alias("path"))


@register("path_split", _PATHS + "SELECT req_id, CAST(string_split(array_to_string(path, '>'), '>')[2] AS BIGINT) AS second FROM ans")
def path_split(spark, d):
    return path_text(spark, d).select("req_id", F.split("path", ">")[1].cast("bigint").alias("second"))


@register("url_host", "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host FROM pages")
def url_host(spark, d):
    return N.table(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"))


@register("monthly_links", "SELECT strftime(l_shipdate, '%Y-%m') AS month, l_suppkey AS v, count(*) AS n FROM lineitem GROUP BY 1, 2")
def monthly_links(spark, d):
    return N.table(spark, d, "lineitem").groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month"), F.col("l_suppkey").alias("v")).agg(F.count("*").alias("n"))


@register("validity_days", "SELECT l_suppkey AS v, CAST(date_diff('day', CAST(min(l_shipdate) AS DATE), CAST(max(l_shipdate) AS DATE)) AS INTEGER) AS days FROM lineitem GROUP BY 1")
def validity_days(spark, d):
    return N.table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("v")).agg(F.datediff(F.max("l_shipdate"), F.min("l_shipdate")).alias("days"))


on_links("loss_additive", "SELECT link_id, CAST(ceil(-ln(1 - ((src * 7 + dst * 13) % 50) / 1000.0) * 1000000) AS BIGINT) AS loss FROM n1")(
    lambda l: l.select("link_id", F.ceil(-F.log(1 - ((F.col("src") * 7 + F.col("dst") * 13) % 50) / F.lit(1000.0)) * 1000000).cast("bigint").alias("loss"))
)
on_links("stretch_math", "SELECT link_id, round(delay / 1414.0, 6) AS stretch, CAST(floor(sqrt(delay)) AS BIGINT) AS root FROM n1")(lambda l: l.select("link_id", F.round(F.col("delay") / F.lit(1414.0).cast("double"), 6).alias("stretch"), F.floor(F.sqrt(F.col("delay").cast("double"))).alias("root")))


# arrays, maps, JSON --------------------------------------------------------------------------------------------------------
_HOPS = _PATHS + "SELECT req_id, CAST(pos - 1 AS INTEGER) AS pos, a, b FROM hop"


@register("path_to_links", _HOPS)
def path_to_links(spark, d):
    return path_links(fixed_answers(spark, d))


@register("path_to_links_udtf", _HOPS)
def path_to_links_udtf(spark, d):
    """The same by a table function in SQL."""
    spark.udtf.register("boundpath_steps", path_udtf())
    fixed_answers(spark, d).createOrReplaceTempView("boundpath_answers")
    return spark.sql("SELECT req_id, pos, a, b FROM boundpath_answers, LATERAL boundpath_steps(path)")


@register("path_to_links_arrow", _HOPS)
def path_to_links_arrow(spark, d):
    """The same by an Arrow-batched Python kernel."""
    return path_pairs(fixed_answers(spark, d).select("req_id", "path"))


@register("loop_check", _PATHS + "SELECT req_id, len(list_distinct(path)) = len(path) AS simple FROM ans")
def loop_check(spark, d):
    return fixed_answers(spark, d).filter("path is not null").select("req_id", (F.size(F.array_distinct("path")) == F.size("path")).alias("simple"))


on_links("vector_add", "SELECT link_id, delay + 1 AS delay, cost + 2 AS cost FROM n1")(
    lambda l: l.withColumn("w", F.zip_with(F.array("delay", "cost"), F.array(F.lit(1), F.lit(2)), lambda x, y: x + y)).select("link_id", F.get("w", F.lit(0)).alias("delay"), F.get("w", F.lit(1)).alias("cost"))
)


@register("array_slices", _PATHS + "SELECT req_id, array_to_string(path[2:len(path) - 1], '>') AS inner_part, path[1] AS head FROM ans")
def array_slices(spark, d):
    p = fixed_answers(spark, d).filter("path is not null")
    return p.select("req_id", F.array_join(F.slice("path", F.lit(2), F.greatest(F.size("path") - 2, F.lit(0))), ">").alias("inner_part"), F.get("path", F.lit(0)).alias("head"))


@register("bounds_map", f"SELECT l_suppkey AS req_id, 1 + CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) % 9 AS bw_bound, (1 + count(*) % 4) * {N.STRETCH} AS delay_bound FROM lineitem GROUP BY l_suppkey")
def bounds_map(spark, d):
    """A request for every supplier, its bounds in a map: bandwidth by what it delivers, delay by its number of lines."""
    each = N.table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("req_id")).agg((1 + F.sum(F.col("l_quantity").cast("bigint")) % 9).alias("bw"), ((1 + F.count("*") % 4) * N.STRETCH).alias("delay"))
    r = each.select("req_id", F.map_from_arrays(F.array(F.lit("bw"), F.lit("delay")), F.array("bw", "delay")).alias("m"))
    return r.select("req_id", F.element_at("m", "bw").alias("bw_bound"), F.element_at("m", "delay").alias("delay_bound"))


@register("answers_json", _PATHS + "SELECT req_id, CAST(hops AS BIGINT) AS hops, cost FROM ans")
def answers_json(spark, d):
    j = fixed_answers(spark, d).filter("hops is not null").select("req_id", F.to_json(F.struct("hops", "cost", "path")).alias("j"))
    return j.select("req_id", F.get_json_object("j", "$.hops").cast("bigint").alias("hops"), F.from_json("j", "cost bigint")["cost"].alias("cost"))


# SQL surface and UDFs ---------------------------------------------------------------------------------------------------------
@register("reach_rcte", "WITH RECURSIVE " + O.n1() + ", go AS (SELECT CAST(0 AS BIGINT) AS v, 0 AS k UNION ALL SELECT n1.dst, k + 1 FROM go JOIN n1 ON n1.src = go.v WHERE k < 4) SELECT v, CAST(min(k) AS INTEGER) AS k FROM go GROUP BY v")
def reach_rcte(spark, d):
    N.n1_links(spark, d).createOrReplaceTempView("boundpath_links")
    return spark.sql("WITH RECURSIVE go(v, k) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT l.dst, k + 1 FROM go JOIN boundpath_links l ON l.src = go.v WHERE k < 4) SELECT v, min(k) AS k FROM go GROUP BY v")


@register("lateral_best", NET + "SELECT s.v, b.dst, b.cost FROM (SELECT DISTINCT src AS v FROM n1) s, LATERAL (SELECT dst, cost FROM n1 WHERE n1.src = s.v ORDER BY cost, dst LIMIT 1) b")
def lateral_best(spark, d):
    N.n1_links(spark, d).createOrReplaceTempView("boundpath_links")
    return spark.sql("SELECT s.v, b.t.dst AS dst, b.t.cost AS cost FROM (SELECT DISTINCT src AS v FROM boundpath_links) s, LATERAL (SELECT min_by(struct(dst, cost), struct(cost, dst)) AS t FROM boundpath_links l WHERE l.src = s.v) b")


_SKY = "SELECT link_id FROM n1 a WHERE NOT EXISTS (SELECT 1 FROM n1 b WHERE b.src = a.src AND b.delay <= a.delay AND b.cost <= a.cost AND (b.delay < a.delay OR b.cost < a.cost))"
on_links("skyline_links", _SKY)(lambda l: skyline(l, ["src"], ["delay", "cost"]).select("link_id"))


@register("skyline_udaf", NET + _SKY)
def skyline_udaf(spark, d):
    """The same per group by pandas."""

    def best(f: pd.DataFrame) -> pd.DataFrame:
        w = f[["delay", "cost"]].to_numpy()
        beaten = [((w <= x).all(axis=1) & (w < x).any(axis=1)).any() for x in w]
        return f.loc[[not b for b in beaten], ["link_id"]]

    return N.n1_links(spark, d).groupBy("src").applyInPandas(best, "link_id bigint")


on_links("skyline_3d", "SELECT link_id FROM n1 a WHERE NOT EXISTS (SELECT 1 FROM n1 b WHERE b.src = a.src AND b.delay <= a.delay AND b.cost <= a.cost AND b.bw <= a.bw AND (b.delay < a.delay OR b.cost < a.cost OR b.bw < a.bw))")(lambda l: skyline(l, ["src"], ["delay", "cost", "bw"]).select("link_id"))
on_links("skyline_k2", "SELECT link_id FROM n1 a WHERE (SELECT count(*) FROM n1 b WHERE b.src = a.src AND b.delay <= a.delay AND b.cost <= a.cost AND (b.delay < a.delay OR b.cost < a.cost)) < 2")(lambda l: skyline(l, ["src"], ["delay", "cost"], 2).select("link_id"))


@register("mixed_udf", NET + "SELECT link_id, 2 * delay + 50 * cost AS mixed FROM n1")
def mixed_udf(spark, d):
    @F.pandas_udf("bigint")
    def mixed(delay: pd.Series, cost: pd.Series) -> pd.Series:
        return 2 * delay + 50 * cost

    return N.n1_links(spark, d).select("link_id", mixed("delay", "cost").alias("mixed"))
