"""Exhaustive baselines and relaxations, as DataFrame loops."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.loop import empty, keep, keep_counted, small
from boundpath.operators.skyline import skyline
from boundpath.search.ldp import PathQuery, _answers, best_of
from boundpath.search.single import ldp_links_cost, relax, suffix_labels, trace, _finish


def ebfs(links: DataFrame, requests: DataFrame, objective: str = "hops", max_hops: int | None = None, dominance: bool = False, suffix: bool = False, metrics=("delay", "cost"), stats: bool = False):
    """Exhaustive breadth-first search from the source: all loop-free paths within the bounds, level by level, until there are none.

    dominance: one skyline per (request, vertex) and level; suffix: partial paths that can't meet a bound with the least
    rest to the destination are dropped.  Partial paths dearer than the best answer so far are dropped with dominance (its one-dimensional form)."""
    q = PathQuery(metrics=metrics, objective=objective, prune=frozenset(), max_hops=max_hops)
    head = requests.select("req_id", "dst", F.col("bw").alias("bw_min"), *[F.col(x).alias(f"max_{x}") for x in metrics], F.col("src").alias("v"), F.array("src").alias("path"), *[F.lit(0).cast("bigint").alias(x) for x in metrics])
    arcs = links.select(F.col("src").alias("u"), F.col("dst").alias("to"), "bw", *[F.col(x).alias(f"w_{x}") for x in metrics])
    rest = None
    if suffix:
        for x in metrics:
            one = keep(suffix_labels(links, requests.select("dst").distinct(), x).select(F.col("dst").alias("s_dst"), F.col("v").alias("s_v"), F.col("least").alias(f"rest_{x}")))
            rest = one if rest is None else rest.join(one, ["s_dst", "s_v"])
        rest = keep(rest)
    log, undecided = [], None
    found = keep(requests.filter("src = dst").select("req_id", F.lit(0).alias("hops"), *[F.lit(0).cast("bigint").alias(x) for x in metrics], F.array("src").alias("path")))
    head = head.filter("v != dst")
    for k in count(1):
        if objective == "hops":
            head = head.join(found.select("req_id"), "req_id", "left_anti")
        if max_hops is not None and k > max_hops:
            undecided = head.select("req_id").distinct()
            break
        step = head.join(arcs, F.col("v") == F.col("u")).filter("bw >= bw_min").filter(~F.array_contains("path", F.col("to")))
        step = step.withColumns({x: F.col(x) + F.col(f"w_{x}") for x in metrics})
        step = step.filter(" and ".join(f"(max_{x} is null or {x} <= max_{x})" for x in metrics))
        kept = step.select("req_id", "dst", "bw_min", *[f"max_{x}" for x in metrics], F.col("to").alias("v"), F.concat("path", F.array("to")).alias("path"), *metrics)
        if stats:
            kept, made = keep_counted(kept)
        if suffix:
            kept = kept.join(rest, (F.col("dst") == F.col("s_dst")) & (F.col("v") == F.col("s_v"))).filter(" and ".join(f"(max_{x} is null or {x} + rest_{x} <= max_{x})" for x in metrics)).drop("s_dst", "s_v", *[f"rest_{x}" for x in metrics])
        if dominance:
            if objective != "hops":
                kept = kept.join(small(found.select("req_id", F.col(objective).alias("__inc"))), "req_id", "left").filter(f"__inc is null or {objective} <= __inc").drop("__inc")
            kept = skyline(kept, ["req_id", "v"], list(metrics))
        if suffix or dominance or not stats:
            kept, seen = keep_counted(kept, "paths", complete=F.sum((F.col("v") == F.col("dst")).cast("bigint")))
        else:
            seen = {"rows": made["rows"], "complete": kept.filter("v = dst").count()}
        if stats:
            log.append((k, made["rows"], seen["rows"], seen["complete"] or 0))
        if not seen["rows"]:
            break
        if seen["complete"]:
            found = keep(best_of(found.unionByName(kept.filter("v = dst").select("req_id", F.lit(k).alias("hops"), *metrics, "path")), q))
        head = kept.filter("v != dst")
    answers = _answers(requests, found, q, undecided)
    return (answers, log) if stats else answers


def shortest_path(links: DataFrame, requests: DataFrame, metric: str = "cost") -> DataFrame:
    """Least total of one metric, all bounds ignored: req_id, status, hops, metric, path."""
    return ldp_links_cost(links, requests.withColumn("bw", F.lit(0).cast("bigint")), metric)


def ext_dijkstra(links: DataFrame, requests: DataFrame, metric: str = "cost") -> DataFrame:
    """Links below the bandwidth bound removed, then the least total of one metric."""
    return ldp_links_cost(links, requests, metric)


def ext_dijkstra_bounded(links: DataFrame, requests: DataFrame, metric: str = "delay") -> DataFrame:
    """With one path bound: minimise the bounded metric itself; feasible where anything is, not of fewest hops."""
    found = ldp_links_cost(links, requests, metric).join(requests.select("req_id", F.col(metric).alias("limit")), "req_id")
    ok = F.col(metric) <= F.col("limit")
    return found.select("req_id", F.when(ok, "FOUND").otherwise("NONE").alias("status"), F.when(ok, F.col("hops")).alias("hops"), F.when(ok, F.col(metric)).alias(metric), F.when(ok, F.col("path")).alias("path"))


def iter_bellman_ford(links: DataFrame, requests: DataFrame, metric: str = "delay", max_hops: int | None = None) -> DataFrame:
    """Least distance for each exact number of hops; the first number of hops whose distance keeps the bound wins."""
    layers, arrived, _ = relax(links, requests, metric, True, max_hops, "first", improve=False)
    return _finish(requests, trace(layers, requests, keep(arrived)), metric)


def mixed_metric(links: DataFrame, requests: DataFrame, weights: dict[str, int], metrics=("delay", "cost")) -> DataFrame:
    """One shortest path on a weighted sum of the metrics, its bounds checked afterwards."""
    total = None
    for name, w in weights.items():
        part = F.col(name) * w
        total = part if total is None else total + part
    mixed = links.withColumn("mixed", total)
    found = keep(ldp_links_cost(mixed, requests, "mixed"))
    return check_paths(found.select("req_id", "path", "mixed"), links, requests, metrics).join(found.select("req_id", "mixed"), "req_id")


def check_paths(paths: DataFrame, links: DataFrame, requests: DataFrame, metrics=("delay", "cost")) -> DataFrame:
    """req_id, status, hops and metrics of given paths; FOUND where they keep the path bounds, else NONE."""
    hop = path_links(paths.select("req_id", "path")).join(links.select(F.col("src").alias("a"), F.col("dst").alias("b"), *metrics), ["a", "b"])
    sums = hop.groupBy("req_id").agg(F.count("*").alias("hops"), *[F.sum(x).alias(f"s_{x}") for x in metrics])
    all_ = requests.select("req_id", *metrics).join(sums, "req_id", "left").join(paths.select("req_id", "path"), "req_id", "left")
    ok = F.col("hops").isNotNull()
    for x in metrics:
        ok = ok & (F.col(x).isNull() | (F.col(f"s_{x}") <= F.col(x)))
    return all_.select("req_id", F.when(ok, "FOUND").otherwise("NONE").alias("status"), F.when(ok, F.col("hops")).alias("hops"), *[F.when(ok, F.col(f"s_{x}")).alias(x) for x in metrics], F.when(ok, F.col("path")).alias("path"))


def path_links(paths: DataFrame) -> DataFrame:
    """One row for each link of each path: req_id, pos, a, b."""
    pairs = F.arrays_zip(F.slice("path", F.lit(1), F.size("path") - 1).alias("a"), F.slice("path", F.lit(2), F.size("path") - 1).alias("b"))
    return paths.filter("path is not null and size(path) > 1").select("req_id", F.posexplode(pairs).alias("pos", "l")).select("req_id", "pos", F.col("l.a").alias("a"), F.col("l.b").alias("b"))


def lagrangian(links: DataFrame, requests: DataFrame, scale: int = 16) -> DataFrame:
    """Lagrangian relaxation of the delay bound: least scale * cost + multiplier * delay.  Every request tries the multipliers
    0, 1, 2, 4, ... to 16 * scale at once, each as a request of its own in one relaxation; the best feasible path met is the answer (an upper bound).

    Multiplier 0 is the least-cost path, the largest leans to the least-delay path."""
    from pyspark.sql.window import Window

    powers = [0] + [1 << i for i in range((16 * scale).bit_length())]
    tries = requests.select("req_id", "src", "dst", "bw", "delay", "cost", F.posexplode(F.array(*[F.lit(p).cast("bigint") for p in powers])).alias("no", "lam"))
    tries = tries.withColumnRenamed("req_id", "ask").withColumn("req_id", F.col("ask") * len(powers) + F.col("no"))
    tries = keep(tries)
    mixed = _relax_mixed(links, tries, scale)
    met = check_paths(mixed, links, tries).filter("status = 'FOUND'").join(tries.select("req_id", "ask"), "req_id")
    order = Window.partitionBy("ask").orderBy("cost", "hops", "delay", "path")
    top = met.withColumn("r", F.row_number().over(order)).filter("r = 1").select(F.col("ask").alias("req_id"), "hops", "delay", "cost", "path")
    return requests.select("req_id").join(top, "req_id", "left").select("req_id", F.when(F.col("hops").isNull(), "NONE").otherwise("FOUND").alias("status"), "hops", "delay", "cost", "path")


def _relax_mixed(links: DataFrame, tries: DataFrame, scale: int) -> DataFrame:
    """(req_id, path): least scale * cost + lam * delay of every try, whose multiplier is a column of its own."""
    few = small(tries.select("req_id", "bw", "lam"))
    arcs = links.select(F.col("src").alias("v"), F.col("dst").alias("to"), F.col("bw").alias("room"), "delay", "cost")
    best = keep(tries.select("req_id", F.col("src").alias("v"), F.lit(0).cast("bigint").alias("total"), F.array("src").alias("path"), F.lit(True).alias("fresh")))
    while True:
        step = best.filter("fresh").select("req_id", "v", "total", "path").join(few, "req_id").join(arcs, "v").filter("room >= bw")
        step = step.select("req_id", F.col("to").alias("v"), (F.col("total") + scale * F.col("cost") + F.col("lam") * F.col("delay")).alias("total"), F.concat("path", F.array("to")).alias("path"), F.lit(True).alias("fresh"))
        both = best.withColumn("fresh", F.lit(False)).unionByName(step)
        top = both.groupBy("req_id", "v").agg(F.min(F.struct("total", F.size("path").alias("n"), "path", "fresh")).alias("t"))
        best, seen = keep_counted(top.select("req_id", "v", "t.total", "t.path", "t.fresh"), "mixed", fresh=F.sum(F.col("fresh").cast("bigint")))
        if not seen["fresh"]:
            return best.join(tries.select("req_id", F.col("dst").alias("v")), ["req_id", "v"]).select("req_id", "path")


def two_bound_dp(links: DataFrame, requests: DataFrame, first: str = "cost", second: str = "delay", max_hops: int | None = None) -> DataFrame:
    """Pseudo-polynomial table over (vertex, total of ``first``): the least ``second`` of each state, to a fixpoint.

    Answer: the least total of ``first`` that keeps both bounds: req_id, status, first, second."""
    reqs = keep(requests.select("req_id", "src", "dst", F.col("bw").alias("bw_min"), F.col(first).alias("m1"), F.col(second).alias("m2")))
    few = small(reqs)
    state = keep(reqs.select("req_id", F.col("src").alias("v"), F.lit(0).cast("bigint").alias("a"), F.lit(0).cast("bigint").alias("b")))
    front = state
    arcs = links.select(F.col("src").alias("v"), F.col("dst").alias("to"), "bw", F.col(first).alias("wa"), F.col(second).alias("wb"))
    for _ in count() if max_hops is None else range(max_hops):
        step = front.join(few, "req_id").join(arcs, "v").filter("bw >= bw_min and a + wa <= m1 and b + wb <= m2")
        new = step.groupBy("req_id", F.col("to").alias("v"), (F.col("a") + F.col("wa")).alias("a")).agg(F.min(F.col("b") + F.col("wb")).alias("nb"))
        better = new.join(state, ["req_id", "v", "a"], "left").filter("b is null or nb < b").select("req_id", "v", "a", F.col("nb").alias("b"))
        # a state that a cheaper one of its vertex already beats leads nowhere new
        front = keep(skyline(better, ["req_id", "v"], ["a", "b"]))
        if empty(front):
            break
        state = keep(state.unionByName(front).groupBy("req_id", "v", "a").agg(F.min("b").alias("b")))
    goal = state.join(reqs.select("req_id", F.col("dst").alias("v")), ["req_id", "v"]).groupBy("req_id").agg(F.min(F.struct("a", "b")).alias("t"))
    return reqs.select("req_id").join(goal, "req_id", "left").select("req_id", F.when(F.col("t").isNull(), "NONE").otherwise("FOUND").alias("status"), F.col("t.a").alias(first), F.col("t.b").alias(second))
