"""Measures: utilisation, energy, throughput, hops, confidence, and complexity bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Watts of a link interface at full load and idle (gigabit), fixed values.
BUSY_W, IDLE_W = 2.0, 1.7


def bounds_rows(v: int, e: int, l: int) -> list[tuple]:
    """Worst-case work of each case for a network; for several bounds the exponent of the mean degree."""
    return [
        ("links, hops", "layered", v, e, "V+E*l", float(v + e * l)),
        ("links, hops", "exhaustive", v, e, "V+E*l", float(v + e * l)),
        ("one bound, hops", "layered", v, e, "V*E+E*l", float(v * e + e * l)),
        ("one bound, hops", "iterative relaxation", v, e, "V*E+E*l", float(v * e + e * l)),
        ("several bounds", "layered", v, e, "b^(V/2)*p+E*l", v / 2),
        ("several bounds", "exhaustive", v, e, "b^V*p+E*l", float(v)),
    ]


def bounds(size: DataFrame) -> DataFrame:
    """``bounds_rows`` of a network of one bound: problem, method, v, e, formula, value.  size: one row v, e."""
    v, e = F.col("v"), F.col("e")
    values = {"V+E*l": v + e, "V*E+E*l": v * e + e, "b^(V/2)*p+E*l": v / 2, "b^V*p+E*l": v}
    cases = [F.struct(F.lit(p).alias("problem"), F.lit(m).alias("method"), F.lit(f).alias("formula"), values[f].cast("double").alias("value")) for p, m, _, _, f, _ in bounds_rows(0, 0, 0)]
    return size.select("v", "e", F.explode(F.array(*cases)).alias("t")).select("t.problem", "t.method", "v", "e", "t.formula", "t.value")


def utilisation(links: DataFrame, loads: DataFrame) -> DataFrame:
    """link_id, cap, load, u for every link, unused ones at 0.  loads: link_id, load."""
    all_ = links.select("link_id", F.col("bw").alias("cap")).join(loads, "link_id", "left").withColumn("load", F.coalesce("load", F.lit(0)).cast("bigint"))
    return all_.withColumn("u", F.when(F.col("cap") > 0, F.col("load") / F.col("cap")).otherwise(0.0))


def energy(util: DataFrame) -> DataFrame:
    """links, watts, idle watts and the increase over idle in per cent (at most 17.65)."""
    watts = F.sum((BUSY_W - IDLE_W) * F.col("u") + IDLE_W)
    return util.agg(F.count("*").alias("links"), F.round(watts, 6).alias("watts"), F.round(F.count("*") * IDLE_W, 6).alias("idle"), F.round(100 * (watts / (F.count("*") * IDLE_W) - 1), 6).alias("increase"))


def allocation_ratio(decisions: DataFrame) -> DataFrame:
    """requested, accepted, ratio.  decisions: req_id, accepted (0/1)."""
    return decisions.agg(F.count("*").alias("requested"), F.sum("accepted").cast("bigint").alias("accepted"), F.round(F.avg("accepted"), 6).alias("ratio"))


def hops_histogram(answers: DataFrame) -> DataFrame:
    return answers.filter("hops is not null").groupBy("hops").agg(F.count("*").alias("paths"))


def average_hops(answers: DataFrame) -> DataFrame:
    return answers.filter("hops is not null").agg(F.count("*").alias("paths"), F.round(F.avg("hops"), 6).alias("mean_hops"))


def throughput_cdf(flows: DataFrame) -> DataFrame:
    """rate and its cumulative share, over all flows: exact, by counts per distinct rate (no single-task window over flows)."""
    per = flows.groupBy("rate").agg(F.count("*").alias("n"))
    total = per.agg(F.sum("n").alias("all"))
    run = per.withColumn("upto", F.sum("n").over(Window.orderBy("rate").rowsBetween(Window.unboundedPreceding, 0)))
    return run.crossJoin(F.broadcast(total)).select("rate", "n", F.round(F.col("upto") / F.col("all"), 6).alias("share"))


def confidence95(samples: DataFrame, column: str) -> DataFrame:
    """Mean and half-width of the 95 % interval."""
    half = 1.96 * F.stddev(column) / F.sqrt(F.count("*"))
    return samples.agg(F.count("*").alias("n"), F.round(F.avg(column), 6).alias("mean"), F.round(half, 6).alias("half_width"))


def optimality_gap(found: DataFrame, optimum: DataFrame) -> DataFrame:
    """vn_id, gap: by how much of the optimum the balanced cost (load) exceeds it, for requests that both accepted."""
    best = optimum.filter("accepted = 1").select("vn_id", F.col("load").alias("best"))
    return found.filter("accepted = 1").join(best, "vn_id").select("vn_id", F.round((F.col("load") - F.col("best")) / F.col("best"), 6).alias("gap"))
