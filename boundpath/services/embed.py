"""Virtual-network embedding and service chaining on a small substrate.

Virtual networks of one pool are embedded one after the other on what the former left; pools are independent row groups of one job.  The
substrate (a few dozen vertices) goes into each task.  Algorithms: ``joint`` (rank, place, route), ``colgen`` (``joint``'s
placement, its links routed by column generation), ``colgen_split`` (the same with links split over several paths), ``auction`` (consensus
placement, then routing) and ``opt`` (branch and bound over placements and paths together, for small requests).  Paths are found by ``dijkstra`` (least
cost, the virtual link's delay bound checked afterwards), ``ldp`` (least cost under the bound) or ``kpaths`` (the first that fits of a few
shortest paths computed beforehand).  Published formulations are only cited by the source, so these are reconstructions.
"""

from __future__ import annotations

from itertools import count
from types import SimpleNamespace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.baselines.kernels import Graph, layered, least_metric, next_shortest
from boundpath.loop import empty, keep, small
from boundpath.services.lp import simplex
from boundpath.topology.networks import STRETCH, table

#: Paths of each pair that ``kpaths`` computes beforehand.
K_PATHS = 4
RESULT = "vn_id bigint, accepted int, cost double, load double, paths int, hops double, cpu bigint"
POOL = f"setting string, method string, finder string, {RESULT}, used double, wires int"
#: Most links of a substrate.
SUBSTRATE = 100_000


def vn_nodes(spark: SparkSession, sf_dir: str, count: int = 40, size: int = 6) -> DataFrame:
    """vn_id, pos, cpu, qty, line: the first lines of the first orders that have enough."""
    lines = table(spark, sf_dir, "lineitem")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    placed = lines.withColumns({"pos": F.row_number().over(order) - 1, "n": F.count("*").over(Window.partitionBy("l_orderkey"))}).filter((F.col("n") >= size) & (F.col("pos") < size))
    first = placed.filter("pos = 0").select("l_orderkey").orderBy("l_orderkey").limit(count)
    qty = F.col("l_quantity").cast("bigint")
    return placed.join(F.broadcast(first), "l_orderkey").select(F.col("l_orderkey").alias("vn_id"), F.col("pos").cast("bigint").alias("pos"), (1 + qty % 10).alias("cpu"), qty.alias("qty"), F.col("l_linenumber").cast("bigint").alias("line"))


def vn_links(nodes: DataFrame, degree: int = 1, latency: float | None = 1.0) -> DataFrame:
    """vn_id, a, b, demand, delay_max: positions at most ``degree`` apart are linked; latency scales the bound, None: no bound."""
    x, y = nodes.alias("x"), nodes.alias("y")
    pairs = x.join(y, (F.col("x.vn_id") == F.col("y.vn_id")) & (F.col("x.pos") < F.col("y.pos")) & (F.col("y.pos") - F.col("x.pos") <= degree))
    bound = F.lit(1 << 40) if latency is None else F.floor((1 + F.col("y.line") % 4) * STRETCH * latency)
    return pairs.select(F.col("x.vn_id").alias("vn_id"), F.col("x.pos").alias("a"), F.col("y.pos").alias("b"), (1 + F.col("y.qty") % 10).alias("demand"), bound.cast("bigint").alias("delay_max"))


def chain_links(nodes: DataFrame, latency: float | None = 1.0) -> DataFrame:
    """Linear requests: each function is linked with the next one."""
    w = Window.partitionBy("vn_id").orderBy("pos")
    nxt = nodes.select("vn_id", F.col("pos").alias("a"), F.lead("pos").over(w).alias("b"), F.lead("qty").over(w).alias("q"), F.lead("line").over(w).alias("l")).filter("b is not null")
    bound = F.lit(1 << 40) if latency is None else F.floor((1 + F.col("l") % 4) * STRETCH * latency)
    return nxt.select("vn_id", "a", "b", (1 + F.col("q") % 10).alias("demand"), bound.cast("bigint").alias("delay_max"))


class Substrate:
    def __init__(self, cpu: dict, arcs: list[tuple]):
        self.cpu, self.bw = dict(cpu), {(s, d): b for s, d, b, _, _ in arcs}
        self.delay = {(s, d): x for s, d, _, x, _ in arcs}
        self.cost = {(s, d): c for s, d, _, _, c in arcs}
        self.first, self.known = self.graph(), {}

    def graph(self, extra: dict | None = None, scale: int = 1) -> Graph:
        return Graph((s, d, b, self.delay[s, d], self.cost[s, d] * scale + round(scale * (extra or {}).get((s, d), 0.0))) for (s, d), b in self.bw.items())

    def route(self, s: int, t: int, demand: int, bound: int, finder: str, graph: Graph | None = None) -> tuple | None:
        """A path with room for the demand that keeps the delay bound; ldp searches under the bound, dijkstra checks it after, kpaths
        takes the first that will do of those known from the start."""
        if s == t:
            return (s,)
        if finder == "kpaths":
            if (s, t) not in self.known:
                r = SimpleNamespace(src=s, dst=t, bw=0, delay=1 << 50, cost=1 << 50)
                found = zip(range(K_PATHS), next_shortest(self.first, r, "cost", len(self.cpu), False), strict=False)
                self.known[s, t] = [(key[2], key[3]) for _, (key, _) in found]
            fits = lambda path: all(self.bw[e] >= demand for e in zip(path, path[1:], strict=False))
            return next((path for delay, path in self.known[s, t] if delay <= bound and fits(path)), None)
        r = SimpleNamespace(src=s, dst=t, bw=demand, delay=bound, cost=1 << 50)
        if finder == "dijkstra":
            key, _ = least_metric(graph or self.graph(), r, "cost", len(self.cpu), 3)
        else:
            key, _ = layered(graph or self.graph(), r, "cost", len(self.cpu), "kshort")
        return key and key[3]

    def take(self, placed: dict, nodes: dict, routes: dict, demands: dict) -> None:
        for pos, v in placed.items():
            self.cpu[v] -= nodes[pos]
        for link, path, share in flat(routes):
            for e in zip(path, path[1:], strict=False):
                self.bw[e] -= demands[link] * share

    def fits(self, routes: dict, demands: dict) -> bool:
        load: dict = {}
        for link, path in routes.items():
            for e in zip(path, path[1:], strict=False):
                load[e] = load.get(e, 0) + demands[link]
        return all(self.bw.get(e, 0) >= x for e, x in load.items())


def flat(routes: dict) -> list[tuple]:
    """(link, path, share) of routes whose values are paths, or lists of (path, share)."""
    return [(link, path, share) for link, found in routes.items() for path, share in (found if isinstance(found, list) else [(found, 1)])]


def embedding_cost(sub: Substrate, placed: dict, nodes: dict, routes: dict, demands: dict, balanced: bool = False) -> float:
    """Bandwidth cost over all links of all paths plus CPU; balanced: each share divided by what is available."""
    total = 0.0
    for pos, v in placed.items():
        total += nodes[pos] / max(1, sub.cpu[v]) if balanced else nodes[pos]
    for link, path, share in flat(routes):
        for e in zip(path, path[1:], strict=False):
            total += share * (demands[link] * sub.cost[e] / max(1, sub.bw[e]) if balanced else demands[link] * sub.cost[e])
    return total


def place_joint(sub: Substrate, nodes: dict) -> dict | None:
    """Largest demand to the vertex of most CPU times bandwidth around it, each vertex once."""
    near: dict = {}
    for (s, d), b in sub.bw.items():
        near[s] = near.get(s, 0) + b
        near[d] = near.get(d, 0) + b
    ranked = sorted(sub.cpu, key=lambda v: (-sub.cpu[v] * near.get(v, 0), v))
    placed: dict = {}
    for pos in sorted(nodes, key=lambda p: (-nodes[p], p)):
        v = next((v for v in ranked if v not in placed.values() and sub.cpu[v] >= nodes[pos]), None)
        if v is None:
            return None
        placed[pos] = v
    return placed


def place_auction(sub: Substrate, nodes: dict) -> tuple[dict | None, int]:
    """Consensus: every vertex bids its CPU for the virtual node at hand and passes on the best bid it knows to its neighbours
    until all agree; the winner takes no further one.  Also the number of exchanges."""
    near: dict = {}
    for s, d in sub.bw:
        near.setdefault(s, set()).add(d)
        near.setdefault(d, set()).add(s)
    placed, rounds = {}, 0
    for pos in sorted(nodes, key=lambda p: (-nodes[p], p)):
        known = {v: (sub.cpu[v], -v) if v not in placed.values() and sub.cpu[v] >= nodes[pos] else (-1, 0) for v in near}
        while True:
            rounds += 1
            heard = {v: max([known[v], *(known[u] for u in near[v])]) for v in near}
            if heard == known:
                break
            known = heard
        bid, who = max(known.values())
        if bid < 0:
            return None, rounds
        placed[pos] = -who
    return placed, rounds


def route_all(sub: Substrate, placed: dict, vlinks: list[tuple], finder: str) -> dict | None:
    """Every virtual link in turn on what the former ones left (large demands first)."""
    rest = Substrate(sub.cpu, [(s, d, b, sub.delay[s, d], sub.cost[s, d]) for (s, d), b in sub.bw.items()])
    rest.first, rest.known = sub.first, sub.known
    routes = {}
    for a, b, demand, bound in sorted(vlinks, key=lambda l: (-l[2], l[:2])):
        path = rest.route(placed[a], placed[b], demand, bound, finder)
        if path is None:
            return None
        routes[a, b] = path
        for e in zip(path, path[1:], strict=False):
            rest.bw[e] -= demand
    return routes


def route_colgen(sub: Substrate, placed: dict, vlinks: list[tuple], finder: str, split: bool = False) -> dict | None:
    """Column generation: a master program over known paths, and for every virtual link the path of least cost plus link
    prices; stops when no path is cheaper than what its link pays.  The largest share of each link becomes its path; split: links keep all their shares."""
    pool: dict = {}
    base = sub.graph()
    for a, b, demand, bound in vlinks:
        path = sub.route(placed[a], placed[b], demand, bound, finder, base)
        if path is None:
            return None
        pool[a, b] = [path]
    while True:
        shares, pay, price, over = _master(sub, vlinks, pool)
        graph, more = sub.graph(price, 1000), False
        for a, b, demand, bound in vlinks:
            path = sub.route(placed[a], placed[b], demand, bound, finder, graph)
            if path is None or path in pool[a, b]:
                continue
            cost = sum(demand * (sub.cost[e] + price.get(e, 0.0)) for e in zip(path, path[1:], strict=False))
            if cost < pay[a, b] - 1e-6:
                pool[a, b].append(path)
                more = True
        if not more:
            break
    if split:
        return None if over > 1e-6 else {(a, b): [(p, shares[a, b, p]) for p in pool[a, b] if shares[a, b, p] > 1e-9] for a, b, _, _ in vlinks}
    routes, demands = {}, {(a, b): d for a, b, d, _ in vlinks}
    for a, b, demand, _ in sorted(vlinks, key=lambda l: (-l[2], l[:2])):
        for path in sorted(pool[a, b], key=lambda p: (-shares[a, b, p], p)):
            if sub.fits({**routes, (a, b): path}, demands):
                routes[a, b] = path
                break
        else:
            return None
    return routes


def _master(sub: Substrate, vlinks: list[tuple], pool: dict):
    """Shares of known paths, what each virtual link pays, link prices, and the overload.  Overload is allowed at a high price, so the
    program always has a solution; prices come from the dual program."""
    columns = [(a, b, d, p) for a, b, d, _ in vlinks for p in pool[a, b]]
    used = sorted({e for *_, p in columns for e in zip(p, p[1:], strict=False)})
    n, m, big = len(columns), len(used), 1e4
    place = {e: i for i, e in enumerate(used)}
    load = np.zeros((m, n))
    cost = np.zeros(n)
    for j, (_, _, d, p) in enumerate(columns):
        for e in zip(p, p[1:], strict=False):
            load[place[e], j] = d
            cost[j] += d * sub.cost[e]
    keys = [(a, b) for a, b, _, _ in vlinks]
    member = np.array([[1.0 * ((a, b) == k) for a, b, _, _ in columns] for k in keys])
    eq = [([*row, *[0.0] * m], 1.0) for row in member]
    le = [([*load[i], *[-1.0 * (i == j) for j in range(m)]], float(sub.bw[e])) for i, e in enumerate(used)]
    x, _ = simplex([*cost, *[big] * m], eq, le)
    # dual: max sum(pay) - cap * price with pay_k - load * price <= cost, 0 <= price <= big; pay = plus - minus
    k = len(keys)
    caps = [float(sub.bw[e]) for e in used]
    rows = [([*member[:, j], *-member[:, j], *-load[:, j]], float(cost[j])) for j in range(n)]
    rows += [([0.0] * (2 * k) + [1.0 * (i == j) for j in range(m)], big) for i in range(m)]
    y, _ = simplex([*[-1.0] * k, *[1.0] * k, *caps], [], rows)
    pay = {key: y[i] - y[k + i] for i, key in enumerate(keys)}
    price = {e: float(y[2 * k + i]) for i, e in enumerate(used)}
    return {(a, b, p): float(x[j]) for j, (a, b, _, p) in enumerate(columns)}, pay, price, float(sum(x[n:]))


def place_opt(sub: Substrate, nodes: dict, vlinks: list[tuple], finder: str) -> tuple | None:
    """Placement and paths of least balanced cost, by branch and bound: virtual nodes are placed one by one, then their links routed
    one by one over all feasible paths; what is left costs at least the cheapest rest, every link on its own."""
    scale = 10**9
    weight = {e: round(scale * sub.cost[e] / max(1, b)) for e, b in sub.bw.items()}
    graph = Graph((s, d, b, sub.delay[s, d], weight[s, d]) for (s, d), b in sub.bw.items())
    at_least = {demand: {v: graph.least(v, demand, 3, False) for v in sub.cpu} for demand in {w[2] for w in vlinks}}
    order = sorted(nodes, key=lambda p: (-sum(p in w[:2] for w in vlinks), p))
    cpu_cost = {(p, v): scale * nodes[p] / max(1, sub.cpu[v]) for p in order for v in sub.cpu}
    cheapest = {p: min(cpu_cost[p, v] for v in sub.cpu) for p in order}
    best = [float("inf"), None]
    known: dict = {}

    def options(s, t, demand, bound):
        """Feasible paths of a pair, cheapest first, made as they are asked for."""
        if (s, t, demand, bound) not in known:
            r = SimpleNamespace(src=s, dst=t, bw=demand, delay=bound, cost=1 << 60)
            known[s, t, demand, bound] = ([], next_shortest(graph, r, "cost", len(sub.cpu), True))
        made, more = known[s, t, demand, bound]
        for i in count():
            if i == len(made):
                found = next(more, None)
                if found is None:
                    return
                made.append((found[0][0], found[0][3]))
            yield made[i]

    def floor(placed, link):
        a, b, demand, _ = link
        return demand * at_least[demand][placed[a]].get(placed[b], float("inf")) if a in placed and b in placed else 0.0

    def route(placed, links, routes, load, spent):
        if spent + sum(floor(placed, w) for w in links) >= best[0]:
            return
        if not links:
            best[:] = [spent, (dict(placed), dict(routes))]
            return
        a, b, demand, bound = links[0]
        rest = sum(floor(placed, w) for w in links[1:])
        for unit, path in options(placed[a], placed[b], demand, bound):
            if spent + demand * unit + rest >= best[0]:
                return
            steps = list(zip(path, path[1:], strict=False))
            if all(load.get(e, 0) + demand <= sub.bw[e] for e in steps):
                for e in steps:
                    load[e] = load.get(e, 0) + demand
                routes[a, b] = path
                route(placed, links[1:], routes, load, spent + demand * unit)
                del routes[a, b]
                for e in steps:
                    load[e] -= demand
            if finder == "dijkstra":
                return  # the cheapest path or none

    def place(i, placed, spent):
        if spent + sum(cheapest[p] for p in order[i:]) + sum(floor(placed, w) for w in vlinks) >= best[0]:
            return
        if i == len(order):
            route(placed, sorted(vlinks, key=lambda w: (-w[2], w[:2])), {}, {}, spent)
            return
        p, tried = order[i], []
        for v in sub.cpu:
            if v not in placed.values() and sub.cpu[v] >= nodes[p]:
                placed[p] = v
                tried.append((spent + cpu_cost[p, v] + sum(floor(placed, w) for w in vlinks), v))
                del placed[p]
        for _, v in sorted(tried):
            place(i + 1, {**placed, p: v}, spent + cpu_cost[p, v])

    place(0, {}, 0.0)
    return best[1]


def embed_one(sub: Substrate, nodes: dict, vlinks: list[tuple], method: str, finder: str):
    """(placement, routes) or None."""
    if method == "opt":
        return place_opt(sub, nodes, vlinks, finder)
    placed = place_auction(sub, nodes)[0] if method == "auction" else place_joint(sub, nodes)
    if placed is None:
        return None
    routes = route_colgen(sub, placed, vlinks, finder, method == "colgen_split") if method.startswith("colgen") else route_all(sub, placed, vlinks, finder)
    return None if routes is None else (placed, routes)


def embed_pool(sub: Substrate, requests, method: str, finder: str) -> list[tuple]:
    """Virtual networks (vn_id, nodes, links) in order, each on what the former ones left."""
    out = []
    for r in requests:
        own = {int(x["pos"]): int(x["cpu"]) for x in r.nodes}
        wires = [(int(x["a"]), int(x["b"]), int(x["demand"]), int(x["delay_max"])) for x in r.links]
        got = embed_one(sub, own, wires, method, finder)
        if got is None:
            out.append((int(r.vn_id), 0, None, None, 0, 0.0, 0))
            continue
        placed, routes = got
        demands = {(a, b): d for a, b, d, _ in wires}
        cost = embedding_cost(sub, placed, own, routes, demands)
        load = embedding_cost(sub, placed, own, routes, demands, True)
        sub.take(placed, own, routes, demands)
        out.append((int(r.vn_id), 1, float(cost), float(load), len(flat(routes)), float(sum((len(p) - 1) * share for _, p, share in flat(routes))), sum(own.values())))
    return out


def embed_pools(substrate_nodes: DataFrame, links: DataFrame, nodes: DataFrame, pools: list[tuple]) -> DataFrame:
    """RESULT of every pool, behind its setting, method and finder; used: summed link utilisation at the pool's end, wires: links of the substrate.

    pools: (setting, virtual links, methods, finders); one job with a row group for each combination.  The substrate is collected: at most
    SUBSTRATE links, or an error."""
    spark = links.sparkSession
    cpu = {r.v: r.cpu for r in substrate_nodes.select("v", "cpu").collect()}
    arcs = [tuple(r) for r in links.select("src", "dst", "bw", "delay", "cost").limit(SUBSTRATE + 1).collect()]
    if len(arcs) > SUBSTRATE:
        raise ValueError(f"the substrate has more than {SUBSTRATE} links")
    own = nodes.groupBy("vn_id").agg(F.collect_list(F.struct("pos", "cpu")).alias("nodes"))
    every = None
    for setting, wires, methods, finders in pools:
        packed = own.join(wires.groupBy("vn_id").agg(F.collect_list(F.struct("a", "b", "demand", "delay_max")).alias("links")), "vn_id")
        combos = spark.createDataFrame([(setting, m, f) for m in methods for f in finders], "setting string, method string, finder string")
        one = packed.join(F.broadcast(combos), F.lit(True))
        every = one if every is None else every.unionByName(one)

    def run(f: pd.DataFrame) -> pd.DataFrame:
        label = [f[c].iloc[0] for c in ("setting", "method", "finder")]
        sub = Substrate(cpu, arcs)
        rows = embed_pool(sub, f.sort_values("vn_id").itertuples(index=False), *label[1:])
        used = sum(1 - sub.bw[s, d] / b for s, d, b, _, _ in arcs if b)
        return pd.DataFrame([(*label, *row, float(used), len(arcs)) for row in rows], columns=[c.split()[0] for c in POOL.split(", ")])

    return every.groupBy("setting", "method", "finder").applyInPandas(run, POOL)


def embed(substrate_nodes: DataFrame, links: DataFrame, nodes: DataFrame, vlinks: DataFrame, method: str = "joint", finder: str = "ldp") -> DataFrame:
    """vn_id, accepted, cost, load (the balanced cost), paths, hops, cpu of every virtual network of one pool, in order of vn_id."""
    return embed_pools(substrate_nodes, links, nodes, [("", vlinks, [method], [finder])]).select(*[c.split()[0] for c in RESULT.split(", ")])


def auction_winners(substrate_nodes: DataFrame, links: DataFrame, nodes: DataFrame) -> DataFrame:
    """The consensus auction as a DataFrame loop over all virtual networks at once (each on the whole substrate): vn_id,
    turn, winner.  Virtual nodes come by falling CPU; an exchange joins what vertices know with their neighbours'."""
    both = links.select("src", "dst").union(links.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    turn = F.row_number().over(Window.partitionBy("vn_id").orderBy(F.desc("cpu"), "pos"))
    asked = keep(nodes.withColumn("turn", turn).select("vn_id", "turn", F.col("cpu").alias("need")))
    last = asked.agg(F.max("turn")).first()[0] or 0
    hosts = small(substrate_nodes.select("v", "cpu"))
    won = None
    for t in range(1, last + 1):
        now = asked.filter(F.col("turn") == t).crossJoin(hosts)
        if won is not None:
            now = now.join(won.select("vn_id", F.col("winner").alias("v"), F.lit(1).alias("gone")), ["vn_id", "v"], "left")
        else:
            now = now.withColumn("gone", F.lit(None).cast("int"))
        bid = F.when(F.col("gone").isNull() & (F.col("cpu") >= F.col("need")), F.struct(F.col("cpu").alias("bid"), (-F.col("v")).alias("who")))
        known = keep(now.select("vn_id", "v", bid.alias("best")))
        while True:
            heard = known.select("vn_id", F.col("v").alias("src"), "best").join(both, "src").select("vn_id", F.col("dst").alias("v"), "best").unionByName(known)
            heard = keep(heard.groupBy("vn_id", "v").agg(F.max("best").alias("best")))
            if empty(heard.exceptAll(known)):
                break
            known = heard
        chosen = keep(known.groupBy("vn_id").agg(F.max("best").alias("b")).filter("b is not null").select("vn_id", F.lit(t).alias("turn"), (-F.col("b.who")).alias("winner")))
        won = chosen if won is None else won.unionByName(chosen)
    return won
