"""The polynomial cases: one path bound (layered relaxation), link bounds alone (breadth first, or least cost).

``relax`` is their common loop: per class a running best distance per vertex, layer by layer; a vertex enters the next layer
with its least (distance, predecessor) if that improves its best and keeps the bound.  Answers are traced back through the
layers, one join each.
"""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.loop import empty, keep, keep_counted, small


def relax(links: DataFrame, requests: DataFrame, metric: str | None, bounded: bool, max_hops: int | None, stop: str, improve: bool = True) -> tuple[DataFrame, DataFrame, bool]:
    """(layers, arrivals, still growing).  layers: cls, k, v, pred, dist; a class is a request.

    metric None counts hops.  stop ``first``: a request leaves when its destination is in a layer; ``end``: all layers until
    none improves.  max_hops None: until no layer grows (weights not negative).  improve False keeps every layer's least distances, also those that don't improve (exact hop counts); a
    class whose layer improves nothing is at its end, since a longer walk can only arrive later and be no shorter."""
    bound = F.col(metric).cast("bigint") if bounded else F.lit(None).cast("bigint")
    reqs = requests.select(F.col("req_id").alias("cls"), "src", "dst", F.col("bw").alias("bw_min"), bound.alias("limit"))
    reqs = keep(reqs)
    few = small(reqs)
    layer = keep(reqs.select("cls", F.lit(0).alias("k"), F.col("src").alias("v"), F.lit(None).cast("bigint").alias("pred"), F.lit(0).cast("bigint").alias("dist")))
    layers, best = layer, layer.select("cls", "v", F.col("dist").alias("least"))
    arrived = keep(reqs.filter("src = dst").select("cls", F.lit(0).alias("k"), F.lit(0).cast("bigint").alias("dist")))
    weight = F.col(metric) if metric else F.lit(1)
    arcs = links.select(F.col("src").alias("u"), F.col("dst").alias("to"), "bw", weight.cast("bigint").alias("w"))
    growing = False
    for k in count(1) if max_hops is None else range(1, max_hops + 1):
        f = layer.select("cls", F.col("v").alias("u"), "dist")
        if stop == "first":
            f = f.join(arrived.select("cls"), "cls", "left_anti")
        f = f.join(few, "cls")
        step = f.join(arcs, "u").filter("bw >= bw_min").withColumn("dist", F.col("dist") + F.col("w")).filter("limit is null or dist <= limit")
        top = F.min(F.struct("dist", F.col("u").alias("pred"))).alias("t")
        cand = step.filter("to != src").groupBy("cls", F.col("to").alias("v")).agg(top) if improve else step.groupBy("cls", F.col("to").alias("v")).agg(top)
        cand = cand.select("cls", F.lit(k).alias("k"), "v", F.col("t.pred").alias("pred"), F.col("t.dist").alias("dist"))
        met = cand.join(best, ["cls", "v"], "left").withColumn("better", F.col("least").isNull() | (F.col("dist") < F.col("least"))).drop("least")
        layer, seen = keep_counted(met.filter("better") if improve else met, "layer", better=F.sum(F.col("better").cast("bigint")))
        growing = bool(seen["better"])
        if not growing:
            break
        if not improve:
            layer = layer.join(layer.filter("better").select("cls").distinct(), "cls", "left_semi")
        layers = layers.unionByName(layer.drop("better"))
        best = keep(best.unionByName(layer.filter("better").select("cls", "v", F.col("dist").alias("least"))).groupBy("cls", "v").agg(F.min("least").alias("least")))
        goal = layer.join(reqs.select("cls", F.col("dst").alias("v")), ["cls", "v"]).select("cls", "k", "dist")
        arrived = arrived.unionByName(goal)
        if k % 8 == 0:
            arrived = keep(arrived)
        if stop == "first" and not improve and empty(layer.join(arrived.select("cls"), "cls", "left_anti")):
            growing = False
            break
    return layers, arrived, growing


def trace(layers: DataFrame, requests: DataFrame, ends: DataFrame) -> DataFrame:
    """Paths of ends (cls, k, dist) by predecessors: req_id, hops, dist, path."""
    at = ends.join(requests.select(F.col("req_id").alias("cls"), "dst"), "cls").select("cls", "k", "dist", F.col("k").alias("left"), F.col("dst").alias("v"), F.array("dst").alias("path"))
    steps = layers.select("cls", F.col("k").alias("lk"), F.col("v").alias("lv"), F.col("pred").alias("lp"))
    most = ends.agg(F.max("k")).first()[0] or 0
    for _ in range(most):
        met = at.join(steps, (at["cls"] == steps["cls"]) & (at["left"] == steps["lk"]) & (at["v"] == steps["lv"]), "left").select(at["*"], "lp")
        more = F.col("left") > 0
        at = met.select(
            "cls", "k", "dist", F.when(more, F.col("left") - 1).otherwise(0).alias("left"), F.when(more, F.col("lp")).otherwise(F.col("v")).alias("v"),
            F.when(more, F.concat(F.array("lp"), "path")).otherwise(F.col("path")).alias("path"),
        )
    return at.select(F.col("cls").alias("req_id"), F.col("k").cast("bigint").alias("hops"), "dist", "path")


def _finish(requests: DataFrame, paths: DataFrame, name: str) -> DataFrame:
    out = requests.select("req_id").join(paths, "req_id", "left")
    return out.select("req_id", F.when(F.col("hops").isNull(), "NONE").otherwise("FOUND").alias("status"), "hops", F.col("dist").alias(name), "path")


def ldp_single(links: DataFrame, requests: DataFrame, metric: str = "delay", max_hops: int | None = None) -> DataFrame:
    """Fewest hops under link bounds and one path bound; of these, least (distance, predecessor) layer by layer."""
    layers, arrived, _ = relax(links, requests, metric, True, max_hops, "first")
    return _finish(requests, trace(layers, requests, keep(arrived)), metric)


def ldp_links(links: DataFrame, requests: DataFrame, max_hops: int | None = None) -> DataFrame:
    """Fewest hops under link bounds alone: every vertex enters one layer (improvement of the hop count)."""
    layers, arrived, _ = relax(links, requests, None, False, max_hops, "first")
    return _finish(requests, trace(layers, requests, keep(arrived)), "dist")


def ldp_links_cost(links: DataFrame, requests: DataFrame, metric: str = "cost", max_hops: int | None = None) -> DataFrame:
    """Least total of a metric under link bounds alone, run until no distance improves."""
    layers, arrived, _ = relax(links, requests, metric, False, max_hops, "end")
    last = arrived.groupBy("cls").agg(F.min(F.struct("dist", "k")).alias("t")).select("cls", F.col("t.k").alias("k"), F.col("t.dist").alias("dist"))
    return _finish(requests, trace(layers, requests, keep(last)), metric)


def ldp_single_status(links: DataFrame, requests: DataFrame, vertices: int, metric: str = "delay") -> DataFrame:
    """req_id, status: FOUND, UNREACHABLE (no path under the link bounds), INFEASIBLE (only paths beyond the bound) or
    NEGATIVE_CYCLE (the layers still grow after as many steps as there are vertices)."""
    layers, arrived, growing = relax(links, requests, metric, True, vertices, "first")
    _, reach, _ = relax(links, requests, None, False, vertices, "first")
    out = requests.select("req_id").join(arrived.select(F.col("cls").alias("req_id"), F.lit(1).alias("ok")), "req_id", "left")
    out = out.join(reach.select(F.col("cls").alias("req_id"), F.lit(1).alias("near")), "req_id", "left")
    if growing:
        last = layers.groupBy("cls").agg(F.max("k").alias("kmax")).filter(F.col("kmax") >= vertices).select(F.col("cls").alias("req_id"), F.lit(1).alias("cycle"))
        out = out.join(last, "req_id", "left")
    else:
        out = out.withColumn("cycle", F.lit(None).cast("int"))
    status = F.when(F.col("ok").isNotNull(), "FOUND").when(F.col("cycle").isNotNull(), "NEGATIVE_CYCLE").when(F.col("near").isNotNull(), "INFEASIBLE").otherwise("UNREACHABLE")
    return out.select("req_id", status.alias("status"))


def suffix_labels(links: DataFrame, targets: DataFrame, metric: str, max_hops: int | None = None) -> DataFrame:
    """dst, v, least: the least total of ``metric`` from v to dst over any number of hops.  targets: dst."""
    back = links.select("link_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "bw", F.col(metric))
    reqs = targets.select(F.col("dst").alias("req_id"), F.col("dst").alias("src"), F.lit(-1).cast("bigint").alias("dst"), F.lit(0).cast("bigint").alias("bw")).distinct()
    layers, _, _ = relax(back, reqs, metric, False, max_hops, "end")
    return layers.groupBy(F.col("cls").alias("dst"), "v").agg(F.min("dist").alias("least"))
