"""Networks and requests derived from the given tables, as DataFrames.

A links table has link_id, src, dst, bw, delay, cost (bigint).  ``oracle.py`` has the same recipes as DuckDB SQL.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.loop import empty, keep, once, small

STRETCH = 1414  # delay across the diagonal of the 1000 x 1000 area
#: Requested bounds (bandwidth, delay, cost) of the workloads.
SEVERITY = {"low": (1, 4 * STRETCH, 100), "med": (4, 5 * STRETCH // 2, 50), "tight": (4, STRETCH, 15)}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _cents(column: str) -> F.Column:
    return F.round(F.col(column) * 100).cast("bigint")


def supplier_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """v, x, y of suppliers."""
    return table(spark, sf_dir, "supplier").select(
        F.col("s_suppkey").alias("v"),
        ((F.col("s_suppkey") * 7919 + F.col("s_nationkey").cast("bigint") * 104729) % 1000).alias("x"),
        ((F.col("s_suppkey") * 6101 + _cents("s_acctbal") + 1000000) % 1000).alias("y"),
    )


def customer_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").select(
        F.col("c_custkey").alias("v"),
        ((F.col("c_custkey") * 7919 + F.col("c_nationkey").cast("bigint") * 104729) % 1000).alias("x"),
        ((F.col("c_custkey") * 6101 + _cents("c_acctbal") + 1000000) % 1000).alias("y"),
    )


def _distance(a: str, b: str) -> F.Column:
    dx, dy = F.col(f"{a}.x") - F.col(f"{b}.x"), F.col(f"{a}.y") - F.col(f"{b}.y")
    return (F.floor(F.sqrt((dx * dx + dy * dy).cast("double"))) + 1).cast("bigint")


def strongest(arcs: DataFrame, degree: int) -> DataFrame:
    """The ``degree`` successors of most arcs (then quantity, then number) of each source.  arcs: src, dst, n, qty."""
    order = Window.partitionBy("src").orderBy(F.desc("n"), F.desc("qty"), "dst")
    return arcs.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= degree).drop("r")


def _placed(arcs: DataFrame, nodes: DataFrame, bw: F.Column) -> DataFrame:
    rows = arcs.join(nodes.alias("a"), F.col("src") == F.col("a.v")).join(nodes.alias("b"), F.col("dst") == F.col("b.v"))
    rows = rows.select("src", "dst", bw.alias("bw"), _distance("a", "b").alias("delay"), (1 + (7 * F.col("qty") + 3 * F.col("src") + 5 * F.col("dst")) % 10).alias("cost"))
    return numbered(rows)


def numbered(rows: DataFrame) -> DataFrame:
    """link_id from the ends alone: no global sort, and the same number in every run."""
    return rows.select((F.col("src") * 1000000 + F.col("dst")).alias("link_id"), "src", "dst", "bw", "delay", "cost")


def succession(lines: DataFrame, group: str, item: str, order: list) -> DataFrame:
    """Arcs between consecutive different items of a group: src, dst, n, qty."""
    after = lines.withColumn("dst", F.lead(item).over(Window.partitionBy(group).orderBy(*order)))
    arcs = after.filter(F.col("dst").isNotNull() & (F.col("dst") != F.col(item)))
    return arcs.groupBy(F.col(item).alias("src"), "dst").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))


def n1_links(spark: SparkSession, sf_dir: str, degree: int = 4) -> DataFrame:
    """Supplier succession inside orders, the four strongest successors each."""

    def make():
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
        arcs = succession(lines, "l_orderkey", "l_suppkey", ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"])
        return strongest(arcs, most)

    def place():
        # ranked once for all degrees, by far the largest part of the work
        arcs = once(spark, ("n1-arcs", sf_dir, most), make)
        return _placed(strongest(arcs, degree), supplier_nodes(spark, sf_dir), 1 + F.col("qty") % 9)

    most = max(degree, 8)
    return once(spark, ("n1", sf_dir, degree), place)


def n2_links(spark: SparkSession, sf_dir: str, degree: int = 4, most: int | None = 10000) -> DataFrame:
    """Customer succession at suppliers, customers below ``most`` (None: all of them)."""

    def make():
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity", "l_shipdate", "l_linenumber")
        orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
        rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        arcs = succession(rows, "l_suppkey", "o_custkey", ["l_shipdate", "l_orderkey", "o_custkey", "l_linenumber", "l_quantity"])
        if most is not None:
            arcs = arcs.filter((F.col("src") < most) & (F.col("dst") < most))
        return _placed(strongest(arcs, degree), customer_nodes(spark, sf_dir), 1 + F.col("qty") % 10)

    return once(spark, ("n2", sf_dir, degree, most), make)


def n3_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """v, x, y, cpu of the 20 nations below key 20."""
    people = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").cast("bigint").alias("v")).agg(F.count("*").alias("n"))
    nation = table(spark, sf_dir, "nation").filter("n_nationkey < 20").select(F.col("n_nationkey").cast("bigint").alias("v"), F.col("n_regionkey").cast("bigint").alias("region"))
    joined = nation.join(people, "v", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return joined.select("v", ((F.col("v") * 397) % 1000).alias("x"), ((F.col("v") * 613 + F.col("region") * 200) % 1000).alias("y"), ((7 * F.col("n") + 13 * F.col("v")) % 101).alias("cpu"))


def n3_links(spark: SparkSession, sf_dir: str, degree: int = 8) -> DataFrame:
    """Trade between nations: supplier's to customer's."""

    def make():
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
        orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
        supplier = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("bigint").alias("src"))
        customer = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("bigint").alias("dst"))
        rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
        arcs = rows.filter("src < 20 and dst < 20 and src != dst").groupBy("src", "dst").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))
        return _placed(strongest(arcs, degree), n3_nodes(spark, sf_dir), F.col("qty") % 101)

    return once(spark, ("n3", sf_dir, degree), make)


def n4_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten switches and five hosts (100 to 104), each host on the switch of twice its number."""

    def make():
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
        arcs = succession(lines, "l_orderkey", "l_suppkey", ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"])
        core = _placed(strongest(arcs.filter("src < 10 and dst < 10"), 4), supplier_nodes(spark, sf_dir), 1 + F.col("qty") % 9)
        hosts = table(spark, sf_dir, "region").select((F.col("r_regionkey").cast("bigint") + 100).alias("h"), (F.col("r_regionkey").cast("bigint") * 2).alias("s"))
        ends = hosts.select(F.col("h").alias("src"), F.col("s").alias("dst")).union(hosts.select(F.col("s").alias("src"), F.col("h").alias("dst")))
        return core.unionByName(numbered(ends.select("src", "dst", F.lit(10).cast("bigint").alias("bw"), F.lit(1).cast("bigint").alias("delay"), F.lit(0).cast("bigint").alias("cost"))))

    return once(spark, ("n4", sf_dir), make)


def _likely_pairs(nodes: DataFrame, count: int, below: int) -> DataFrame:
    """Pairs (a, b) of vertices, b of the larger number, with all whose hash (``waxman_links``) is less than ``below``.

    For a vertex, a hash and what the other vertex leaves by 1009, that one's rest by 10007 is known.  So where less than ``below`` is rare, pairs are found by a join
    on both rests, in 1009 * below rows a vertex, instead of asking all pairs."""
    above = F.col("a.v") < F.col("b.v")
    dealt = nodes.repartition(4 * nodes.sparkSession.sparkContext.defaultParallelism)  # a small file, but long work on each row
    if 2 * 1009 * below >= count or not empty(nodes.filter("v < 0")):
        return dealt.alias("a").join(small(nodes).alias("b"), above)
    rows = dealt.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(1008)))).withColumn("u", F.explode(F.sequence(F.lit(0), F.lit(below - 1))))
    rest = F.pmod(F.pmod(F.col("u") - F.col("v") * 7919 - 31 * (F.col("v") * F.col("c") % 1009), F.lit(10007)) * pow(104729, -1, 10007), F.lit(10007))
    asked = rows.select("v", "x", "y", (F.col("c") * 10007 + rest).alias("rests")).alias("a")
    held = small(nodes.withColumn("rests", F.col("v") % 1009 * 10007 + F.col("v") % 10007)).alias("b")
    return asked.join(held, (F.col("a.rests") == F.col("b.rests")) & above)


def waxman_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance-random network over suppliers: near pairs are kept more often.  Its definition asks every pair of vertices; pairs that no distance
    keeps are left out by their hash where vertices are many."""

    def make():
        nodes = supplier_nodes(spark, sf_dir)
        count = nodes.count()
        beta = F.lit(26.0) / F.lit(float(count))
        pairs = _likely_pairs(nodes, count, min(10007, 10007 * 26 // max(count, 1) + 1))
        d = F.sqrt(((F.col("a.x") - F.col("b.x")) ** 2 + (F.col("a.y") - F.col("b.y")) ** 2).cast("double"))
        u = (F.col("a.v") * 7919 + F.col("b.v") * 104729 + 31 * ((F.col("a.v") * F.col("b.v")) % 1009)) % 10007
        kept = pairs.filter(u < F.floor(F.lit(10007.0) * F.least(F.lit(1.0), beta) * F.exp(-d / 200)))
        qty = F.col("a.v") + F.col("b.v")
        half = kept.select(F.col("a.v").alias("src"), F.col("b.v").alias("dst"), (1 + qty % 9).alias("bw"), (F.floor(d) + 1).cast("bigint").alias("delay"), (1 + (7 * qty + 3) % 10).alias("cost"))
        return numbered(half.unionByName(half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "bw", "delay", "cost")))

    return once(spark, ("n5", sf_dir), make)


def attach_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Preferential attachment by slot copying.  Vertex i makes two links, slots 4i to 4i+3 hold their ends; the far end
    copies an earlier slot (hash of the slot), and chains of copies are resolved by pointer jumping in O(log V) joins."""

    def make():
        keys = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("i"))
        ends = keys.filter("i > 0").select("i", F.explode(F.array(F.lit(0), F.lit(1))).alias("e")).select("i", "e", (F.col("i") * 4 + F.col("e") * 2).alias("near"))
        near = ends.select(F.col("near").alias("slot"), F.col("near").alias("to"), F.col("i").alias("v"))
        far = ends.select((F.col("near") + 1).alias("slot"), (4 + (F.col("near") * 7919 + 104729 * F.col("e") + 13) % F.greatest(F.col("i") * 4 - 4, F.lit(1))).alias("to"), F.col("i")).withColumn("first", F.col("i") == 1)
        far = far.select("slot", F.when(F.col("first"), F.lit(-1)).otherwise(F.col("to")).alias("to"), F.lit(None).cast("bigint").alias("v"))
        slots = near.union(far)
        for jump in range(12):
            nxt = slots.select(F.col("slot").alias("s2"), F.col("to").alias("t2"))
            slots = slots.join(nxt, F.col("to") == F.col("s2"), "left").select("slot", F.coalesce("t2", "to").alias("to"), "v")
            if jump % 4 == 3:
                slots = keep(slots, "slots")
        owner = near.select(F.col("slot").alias("to"), F.col("v").alias("end"))
        ends_far = slots.filter("v is null").join(owner, "to", "left").select(F.floor((F.col("slot") - 1) / 4).cast("bigint").alias("src"), F.coalesce("end", F.lit(0)).alias("dst"))
        pairs = ends_far.filter("src != dst").distinct()
        qty = F.col("src") + F.col("dst")
        half = pairs.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct()
        half = half.select("src", "dst", (1 + qty % 9).alias("bw"), (1 + (qty * 37) % 1000).alias("delay"), (1 + (7 * qty + 3) % 10).alias("cost"))
        return numbered(half.unionByName(half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "bw", "delay", "cost")))

    return once(spark, ("n6", sf_dir), make)


def undirected(links: DataFrame) -> DataFrame:
    """Both arcs of every link, sharing its link_id (one capacity)."""
    return links.unionByName(links.select("link_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "bw", "delay", "cost"))


def requests(spark: SparkSession, sf_dir: str, severity: str = "low", count: int | None = None, vertices: str = "supplier") -> DataFrame:
    """req_id, src, dst, bw, delay, cost (the bounds): V/10 pairs, ten at least, spread over the vertices by steps."""
    n = table(spark, sf_dir, vertices).count()
    many = count or max(10, n // 10)
    bw, delay, cost = SEVERITY[severity]
    r = spark.range(many).withColumnRenamed("id", "req_id")
    r = r.withColumn("src", (37 * F.col("req_id")) % n).withColumn("dst", (53 * F.col("req_id") + 11) % n)
    r = r.withColumn("dst", F.when(F.col("src") == F.col("dst"), (F.col("dst") + 1) % n).otherwise(F.col("dst")))
    return r.select("req_id", "src", "dst", F.lit(bw).cast("bigint").alias("bw"), F.lit(delay).cast("bigint").alias("delay"), F.lit(cost).cast("bigint").alias("cost"))


def example_links(spark: SparkSession) -> DataFrame:
    """The four-node example: X=0, A=1, B=2, Y=3, undirected."""
    half = [(0, 1, 5, 5, 4), (1, 3, 5, 1, 1), (0, 2, 5, 1, 1), (2, 3, 4, 1, 4), (2, 1, 5, 1, 1)]
    both = [(a * 1000000 + b, s, t, *m) for a, b, *m in half for s, t in ((a, b), (b, a))]
    return spark.createDataFrame(both, "link_id bigint, src bigint, dst bigint, bw bigint, delay bigint, cost bigint")
