"""Mixing sources to target weights by Pareto order sampling, in DataFrame functions alone.

Targets: all words are shared out by the sources' weights; a source stops at ``most`` times its own size and the excess
is shared again by weight.  Documents of a source may be preferred by a weight of their own; the expected copies of a document are its weight
times a factor of the source, ``most`` at most, and the factor is such that they add up to the target.  The whole part of
the expected copies is taken for certain, the fraction is the inclusion probability p.  Documents are ranked by random
odds u/(1-u) divided by inclusion odds p/(1-p), u being a hash of the document, and the least are taken until
the source has its words.  The cut is found by histograms: each source's ranks are dealt over fine bins, bins below the
cut are taken whole, and the order inside the one bin at the cut alone decides the rest, so no source, however large,
passes through one task.

Nothing comes to the driver.  One row for each source is sorted in one task (it can spill); weights of documents are rounded down to sixteen levels an octave, so a source's
factor follows from a few rows.

Defined cases: null or blank text has size 0 and adds no words; null source is a source, ordered last; sources of size 0
have target 0; a null weight counts as 1, one of 0 or below is never taken; repeated rows are taken separately; reruns agree, since u depends on doc_id, text and seed alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.llm.shared import count_words, materialise, read_table

WEIGHTS = (5, 2, 1)
MOST = 3
BINS = 1024
LEVELS = 16
#: Most rows of targets or cuts that are broadcast; with more, Spark chooses the join.
BROADCAST_ROWS = 1_000_000


def _few(df: DataFrame, rows: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most BROADCAST_ROWS; rows: a bound on its size."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def water_unit(rows: DataFrame, keys: list[str], cap: str, weight: str, total: Column) -> DataFrame:
    """(keys, unit): shares of unit * weight, each at most its cap, add up to ``total`` (a column of the rows, equal in a
    group).  Infinite where all caps together don't reach it.  cap and weight: above 0.

    Rows reach their caps in the order of cap / weight.  If the first i of them are at their caps, the others' unit follows; it is right where the next
    row's cap bears it, and too small beyond, so the right one is the largest of those that are borne."""
    order = Window.partitionBy(*keys).orderBy(F.col(cap) / F.col(weight), F.col(cap))
    full = F.coalesce(F.sum(F.col(cap)).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    open_ = F.sum(F.col(weight)).over(order.rowsBetween(0, Window.unboundedFollowing))
    units = rows.withColumn("__unit", (total - full) / open_)
    borne = F.max(F.when(F.col("__unit") <= F.col(cap) / F.col(weight), F.col("__unit")))
    return units.groupBy(*keys).agg(F.coalesce(borne, F.lit(float("inf"))).alias("unit"))


def source_targets(sized: DataFrame, weights=WEIGHTS, most: float = MOST, share: float = 1.0) -> DataFrame:
    """(source, source_size, target): a row per source.  Sources come in code point order, null last, and take the
    weights in turn."""
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    turn = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (place % len(weights) + 1).cast("int"))
    known = materialise(sums.withColumns({"w": turn, "cap": F.col("source_size") * F.lit(float(most))}), "sources")
    total = known.agg((F.sum("source_size") * share).alias("total"))
    live = known.filter("source_size > 0").crossJoin(F.broadcast(total))
    unit = water_unit(live, [], "cap", "w", F.col("total"))
    target = F.when(F.col("source_size") > 0, F.least(F.col("cap"), F.col("unit") * F.col("w"))).otherwise(0.0)
    return known.crossJoin(F.broadcast(unit)).select("source", "source_size", target.alias("target"))


def _unit(seed: int, *columns) -> F.Column:
    """A number in (0, 1) from a hash."""
    return (F.shiftrightunsigned(F.xxhash64(*columns, F.lit(seed)), 12).cast("double") + 0.5) / F.lit(float(1 << 52))


def length_weight(size: Column) -> Column:
    """Long texts are preferred, by a factor of two at most."""
    return 1.0 + size / (size + 100.0)


def mix(docs: DataFrame, weights=WEIGHTS, most: int = MOST, share: float = 1.0, weight: Column | None = None, seed: int = 11, bins: int = BINS) -> DataFrame:
    """doc_id, source, text_key, size, source_size, target, copies: how often the mix takes each row of ``docs``.

    weight: by which documents of one source are preferred, over the columns of ``docs``; length_weight where it isn't given."""
    text = F.col("text").cast("string")
    own = F.coalesce(weight.cast("double"), F.lit(1.0)) if weight is not None else F.lit(None).cast("double")
    sized = docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), F.xxhash64(text).alias("text_key"), count_words(text).alias("size"), own.alias("own"))
    level = F.when(F.col("own") > 0, F.pow(F.lit(2.0), F.floor(F.log2("own") * LEVELS) / LEVELS)).otherwise(0.0)
    if weight is None:
        sized = sized.withColumn("own", length_weight(F.col("size")))
    sized = materialise(sized.withColumn("weight", level).drop("own"), "sized")
    aims = materialise(source_targets(sized, weights, most, share).withColumnRenamed("source", "aim"), "targets")
    n_sources = aims.count()
    levels = sized.filter("size > 0 and weight > 0").groupBy("source", "weight").agg(F.sum("size").alias("words"))
    levels = levels.join(_few(aims, n_sources), F.col("source").eqNullSafe(F.col("aim"))).select("aim", "target", (F.col("words") * F.lit(float(most))).alias("cap"), (F.col("words") * F.col("weight")).alias("pull"))
    factor = water_unit(levels, ["aim"], "cap", "pull", F.col("target")).select(F.col("aim").alias("f_aim"), "unit")
    aims = materialise(aims.join(factor, F.col("aim").eqNullSafe(F.col("f_aim")), "left").drop("f_aim"), "targets")
    df = sized.join(_few(aims, n_sources), F.col("source").eqNullSafe(F.col("aim"))).drop("aim")
    expected = F.when((F.col("weight") > 0) & (F.col("unit") > 0), F.least(F.col("unit") * F.col("weight"), F.lit(float(most)))).otherwise(0.0)
    df = df.withColumn("expected", expected)
    df = df.withColumn("whole", F.floor(F.col("expected") + 1e-12).cast("bigint"))
    df = df.withColumn("p", F.greatest(F.col("expected") - F.col("whole"), F.lit(0.0)))
    u = _unit(seed, "doc_id", "text_key")
    odds = (u / (1 - u)) / (F.col("p") / (1 - F.col("p")))
    df = df.withColumn("rank", F.when((F.col("p") > 1e-9) & (F.col("size") > 0), odds))
    # the bin grows with the rank: odds q map to q / (1 + q) in (0, 1)
    df = df.withColumn("bin", F.floor(F.col("rank") / (1 + F.col("rank")) * bins).cast("int"))
    certain = df.groupBy("source").agg(F.sum(F.col("whole") * F.col("size")).alias("sure"))
    ranked = df.filter("rank is not null").groupBy("source", "bin").agg(F.sum("size").alias("words"))
    upto = Window.partitionBy("source").orderBy("bin")
    edges = ranked.select("source", "bin", "words", F.sum("words").over(upto).alias("upto"))
    edges = edges.withColumnsRenamed({"source": "e_source", "bin": "e_bin"})
    certain = certain.join(aims.select("aim", "target"), F.col("source").eqNullSafe(F.col("aim"))).select(F.col("aim").alias("c_source"), (F.col("target") - F.col("sure")).alias("want"))
    cut = edges.join(certain, F.col("e_source").eqNullSafe(F.col("c_source"))).select("e_source", "e_bin", "want", (F.col("upto") - F.col("words")).alias("from"), "upto")
    df = df.join(_few(cut, n_sources * bins), F.col("source").eqNullSafe(F.col("e_source")) & (F.col("bin") == F.col("e_bin")), "left")
    inside = (F.col("from") < F.col("want")) & (F.col("upto") > F.col("want"))
    plain = df.filter(~F.coalesce(inside, F.lit(False))).withColumn("extra", F.when(F.col("upto") <= F.col("want"), 1).otherwise(0))
    order = Window.partitionBy("source").orderBy("rank", "doc_id", "text_key").rowsBetween(Window.unboundedPreceding, 0)
    edge = df.filter(inside).withColumn("run", F.sum("size").over(order) + F.col("from"))
    # the document at the cut is taken if that comes nearer to the target
    edge = edge.withColumn("extra", F.when(F.col("run") - F.col("size") / 2 <= F.col("want"), 1).otherwise(0)).drop("run")
    both = plain.unionByName(edge)
    return both.select("doc_id", "source", "text_key", "size", "source_size", "target", (F.col("whole") + F.col("extra")).cast("bigint").alias("copies"))


def op9_mixing(spark, sf_dir: str) -> DataFrame:
    out = mix(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


QUERIES = {"op9_mixing": op9_mixing}
