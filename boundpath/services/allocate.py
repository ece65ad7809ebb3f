"""Allocation of requests to residual capacity, and the ledger."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.baselines.exact import path_links
from boundpath.baselines.kernels import search
from boundpath.loop import empty, keep


def allocate(links: DataFrame, requests: DataFrame, mode: str = "strict", method: str = "ldp_prefix", max_hops: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(decisions: req_id, accepted, hops, path; loads: link_id, load).  A request takes its bw from every link of its path.

    strict: as if one request came after the other.  All pending are solved on one snapshot, the longest prefix (by
    req_id) whose paths fit together is committed, and the rest is solved anew; capacity only shrinks, so a snapshot's best
    path that still fits is still best.  rounds: every request that fits behind its predecessors of the round is committed.

    Every round decides the first request that is pending, so all requests get a decision."""
    residual = keep(links)
    pending, done = keep(requests), None
    for turn in count(1):
        found = keep(search(residual, pending, method, max_hops=max_hops))
        answered = found.join(pending.select("req_id", F.col("bw").alias("need")), "req_id")
        hop = path_links(answered.select("req_id", "path")).join(answered.select("req_id", "need"), "req_id")
        hop = hop.join(residual.select("link_id", F.col("src").alias("a"), F.col("dst").alias("b"), "bw"), ["a", "b"])
        run = Window.partitionBy("link_id").orderBy("req_id").rowsBetween(Window.unboundedPreceding, 0)
        over = hop.withColumn("run", F.sum("need").over(run)).filter("run > bw")
        late = over.select("req_id").distinct()
        if mode == "strict":
            first = late.agg(F.min("req_id")).first()[0]
            commit = answered if first is None else answered.filter(F.col("req_id") < first)
        else:
            commit = answered.join(late, "req_id", "left_anti")
        commit = keep(commit.select("req_id", (F.col("status") == "FOUND").cast("int").alias("accepted"), "hops", "path", "need"))
        used = path_links(commit.select("req_id", "path")).join(commit.select("req_id", "need"), "req_id").groupBy("a", "b").agg(F.sum("need").alias("used"))
        residual = keep(residual.join(used, (F.col("src") == F.col("a")) & (F.col("dst") == F.col("b")), "left").withColumn("bw", F.col("bw") - F.coalesce("used", F.lit(0))).drop("a", "b", "used"))
        if empty(commit) and not empty(pending):
            raise RuntimeError("a round decided no request: req_id isn't unique")
        done = commit if done is None else done.unionByName(commit)
        if turn % 16 == 0:
            done = keep(done)
        pending = keep(pending.join(commit.select("req_id"), "req_id", "left_anti"))
        if empty(pending):
            break
    loads = links.select("link_id", F.col("bw").alias("cap")).join(residual.select("link_id", F.col("bw").alias("left")), "link_id").select("link_id", (F.col("cap") - F.col("left")).alias("load"))
    return done.select("req_id", "accepted", "hops", "path"), loads


def running_residual(claims: DataFrame) -> DataFrame:
    """Adds what a link has left after each claim, in order.  claims: link_id, seq, amount, cap."""
    run = Window.partitionBy("link_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    return claims.withColumn("left", F.col("cap") - F.sum("amount").over(run))
