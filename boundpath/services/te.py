"""Traffic engineering: greedy max-min filling, linear programs over given paths, demand-oblivious splitting."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.baselines.exact import ext_dijkstra_bounded, path_links
from boundpath.baselines.kernels import k_shortest, search
from boundpath.loop import empty, keep, small
from boundpath.search.single import ldp_single
from boundpath.services.lp import max_min, simplex

def _kernel(method: str):
    def find(links, requests):
        return search(links, requests.withColumn("cost", F.lit(1 << 40)), method, "hops")

    return find


#: Path finders: kernels over a broadcast graph of checked size, and the DataFrame loops for larger ones.
FINDERS = {"ldp": _kernel("ldp_prefix"), "ext_dijkstra": _kernel("least_delay"), "ldp_loop": ldp_single, "ext_dijkstra_loop": ext_dijkstra_bounded}


def flow_requests(flows: DataFrame) -> DataFrame:
    """flows (flow_id, src, dst, delay) as requests without bandwidth bound."""
    return flows.select(F.col("flow_id").alias("req_id"), "src", "dst", F.lit(0).cast("bigint").alias("bw"), "delay")


def te_greedy(links: DataFrame, flows: DataFrame, finder: str = "ldp", max_rounds: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(rates: flow_id, rate, hops; loads: link_id, load).  All active flows rise together on their best path until a link
    is full; full links go, flows over them look for their next path, flows without one stop.

    Rates are in thousandths of a unit, whole numbers, so that filling is exact; a link with less left than one unit for
    each of its flows counts as full.  Every round fills a link, so filling ends; flows left after ``max_rounds`` are an error."""
    rates = keep(flows.select("flow_id", F.lit(0).cast("bigint").alias("rate"), F.lit(0).cast("bigint").alias("weighted")))
    residual = keep(links.select("link_id", "src", "dst", "bw", "delay", "cost", (F.col("bw") * 1000).alias("left")))
    active, paths = flows, None
    for done in count():
        todo = flow_requests(active)
        if paths is not None:
            todo = todo.join(paths.select("req_id"), "req_id", "left_anti")
        open_links = residual.filter("left > 0")
        new = FINDERS[finder](open_links, todo).filter("status = 'FOUND' and hops > 0").select("req_id", "hops", "path")
        paths = keep(new if paths is None else paths.unionByName(new))
        if empty(paths):
            break
        if max_rounds is not None and done >= max_rounds:
            raise RuntimeError(f"flows still have paths after {max_rounds} rounds")
        active = keep(active.join(paths.select(F.col("req_id").alias("flow_id")), "flow_id", "left_semi"))
        over = path_links(paths).join(residual.select("link_id", F.col("src").alias("a"), F.col("dst").alias("b"), "left"), ["a", "b"])
        load = keep(over.groupBy("link_id").agg(F.count("*").alias("n"), F.first("left").alias("left")))
        step = load.agg(F.min(F.floor(F.col("left") / F.col("n")))).first()[0] or 0
        gain = paths.select(F.col("req_id").alias("flow_id"), F.lit(int(step)).alias("up"), F.col("hops").alias("h"))
        rates = keep(rates.join(gain, "flow_id", "left").select("flow_id", (F.col("rate") + F.coalesce("up", F.lit(0))).alias("rate"), (F.col("weighted") + F.coalesce(F.col("up") * F.col("h"), F.lit(0))).alias("weighted")))
        used = residual.join(load.select("link_id", "n"), "link_id", "left")
        left = F.col("left") - F.coalesce("n", F.lit(0)) * int(step)
        residual = keep(used.select("link_id", "src", "dst", "bw", "delay", "cost", F.when((F.col("n").isNotNull()) & (left < F.col("n")), 0).otherwise(left).cast("bigint").alias("left")))
        full = residual.filter("left = 0").select(F.col("src").alias("a"), F.col("dst").alias("b"))
        broken = path_links(paths).join(full, ["a", "b"], "left_semi").select("req_id").distinct()
        paths = keep(paths.join(broken, "req_id", "left_anti"))
    loads = residual.select("link_id", (F.col("bw") * 1000 - F.col("left")).alias("load"))
    return rates, loads


#: Flows of the largest exact program, and links of their paths.
LP_FLOWS, LP_LINKS = 200, 100_000


def te_lp(links: DataFrame, flows: DataFrame, k: int, bounded: bool, max_hops: int | None = None) -> DataFrame:
    """Max-min fair rates over k given paths each: flow_id, rate.  bounded: paths keep the flow's delay bound.

    One exact program on the driver, for tens of flows; ``te_scale`` is the distributed approximation."""
    asked = flows.select("flow_id").limit(LP_FLOWS + 1).collect()
    if len(asked) > LP_FLOWS:
        raise ValueError(f"the program is for at most {LP_FLOWS} flows: use te_scale")
    reqs = flow_requests(flows).withColumn("cost", F.lit(1 << 40))
    paths = k_shortest(links, reqs, k, "hops" if bounded else "cost", max_hops, bounded)
    paths = keep(paths.select("req_id", "rank", "hops", "path"))
    # the program has a row for each link of a path, whatever the size of the network
    used = path_links(paths).select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct()
    known = links.select("src", "dst", "bw").join(small(used), ["src", "dst"], "left_semi").limit(LP_LINKS + 1).collect()
    if len(known) > LP_LINKS:
        raise ValueError(f"the paths have more than {LP_LINKS} links: use te_scale")
    caps = {(r.src, r.dst): r.bw for r in known}
    held: dict[int, list] = {r.flow_id: [] for r in asked}
    for r in paths.orderBy("req_id", "rank").collect():
        if r.hops:
            held[r.req_id].append(list(zip(r.path, r.path[1:], strict=False)))
    ids = sorted(held)
    got = max_min([held[i] for i in ids], caps)
    return links.sparkSession.createDataFrame([(i, float(sum(x))) for i, x in zip(ids, got, strict=True)], "flow_id bigint, rate double")


#: Columns of the largest arc program that is built.
ARC_COLUMNS = 1000


def te_arc_lp(links: DataFrame, flows: DataFrame) -> DataFrame:
    """The largest rate that all flows can have at once, split over any links: flow_id, rate, links (how many it uses).

    One variable for each flow and link, so it is for small graphs; flows without a path make the rate 0."""
    arcs = [tuple(r) for r in links.select("src", "dst", "bw").limit(ARC_COLUMNS + 1).collect()]
    asks = sorted(tuple(r) for r in flows.select("flow_id", "src", "dst").limit(ARC_COLUMNS + 1).collect())
    n = len(arcs) * len(asks)
    if n + 1 > ARC_COLUMNS:
        raise ValueError(f"the arc program has {n + 1} columns, more than {ARC_COLUMNS}: use paths")
    eq, le = [], []
    for f, (_, src, dst) in enumerate(asks):
        for v in sorted({a[0] for a in arcs} | {a[1] for a in arcs} | {src}):
            if v == dst:
                continue
            row = [0.0] * (n + 1)
            for e, (a, b, _) in enumerate(arcs):
                row[f * len(arcs) + e] = float(a == v) - float(b == v)
            row[n] = -1.0 if v == src else 0.0
            eq.append((row, 0.0))
    for e, (_, _, cap) in enumerate(arcs):
        row = [0.0] * (n + 1)
        row[e:n:len(arcs)] = [1.0] * len(asks)
        le.append((row, float(cap)))
    x, _ = simplex([0.0] * n + [-1.0], eq, le)
    used = [sum(bool(x[f * len(arcs) + e] > 1e-9) for e in range(len(arcs))) for f in range(len(asks))]
    return links.sparkSession.createDataFrame([(i, float(x[n]), used[f]) for f, (i, _, _) in enumerate(asks)], "flow_id bigint, rate double, links int")


def te_scale(paths: DataFrame, caps: DataFrame, rounds: int = 20, eps: float = 0.3) -> DataFrame:
    """Approximate max-min by multiplicative weights: each round every flow sends one share over its lightest path, and the
    weights of its links grow.  paths: flow_id, rank, link_id rows; caps: link_id, cap.  (flow_id, rate)"""
    weight = keep(caps.select("link_id", "cap", F.lit(1.0).alias("w")))
    sent = None
    for _ in range(rounds):
        length = paths.join(weight, "link_id").groupBy("flow_id", "rank").agg(F.sum(F.col("w") / F.col("cap")).alias("len"))
        pick = length.groupBy("flow_id").agg(F.min(F.struct("len", "rank")).alias("t")).select("flow_id", F.col("t.rank").alias("rank"))
        used = keep(paths.join(pick, ["flow_id", "rank"]))
        load = used.groupBy("link_id").agg(F.count("*").alias("n"))
        weight = keep(weight.join(load, "link_id", "left").select("link_id", "cap", (F.col("w") * (1 + eps * F.coalesce("n", F.lit(0)) / F.col("cap"))).alias("w")))
        sent = used if sent is None else sent.unionByName(used)
    # every share is sized by its fullest link, so no link overflows
    load = sent.groupBy("link_id").agg(F.count("*").alias("n")).join(caps, "link_id").select("link_id", (F.col("cap") / F.col("n")).alias("unit"))
    least = sent.join(load, "link_id").groupBy("flow_id").agg(F.min("unit").alias("unit"))
    return least.select("flow_id", (F.col("unit") * rounds).alias("rate"))


def te_oblivious(links: DataFrame, paths: DataFrame) -> DataFrame:
    """Every flow splits evenly over its paths, demands unknown; all flows scaled alike so that no link overflows:
    flow_id, rate.  paths: flow_id, path_no, link_id."""
    count = paths.groupBy("flow_id").agg(F.countDistinct("path_no").alias("n"))
    load = paths.join(count, "flow_id").groupBy("link_id").agg(F.sum(1.0 / F.col("n")).alias("load"))
    scale = load.join(links.select("link_id", "bw"), "link_id").agg(F.min(F.col("bw") / F.col("load")).alias("rate"))
    return count.select("flow_id").crossJoin(F.broadcast(scale))
