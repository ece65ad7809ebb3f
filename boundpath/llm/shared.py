"""Helpers that the training-data operators share: stored intermediate tables, words, ranks and skewed joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.loop import drop as drop_materialised
from boundpath.loop import fresh_path, remove, shared_dir
from boundpath.loop import keep as materialise
from boundpath.loop import small

__all__ = ["drop_materialised", "fresh_path", "materialise", "remove", "shared_dir", "small"]

#: White space that separates words: a fixed value of the contracts (ASCII space and 0x09 to 0x0D).
BLANKS = " \t\n\x0b\x0c\r"
BLANK_RUN = r"[\x20\x09-\x0D]+"
#: A key with more than one row in so many is heavy; there are at most as many heavy keys, so they may be broadcast.
HEAVY_SHARE = 4096


def trimmed(text: Column) -> Column:
    return F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANKS))


def split_words(text: Column) -> Column:
    """The words of a text as an array; none for null or blank text."""
    body = trimmed(text)
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, BLANK_RUN))


def count_words(text: Column) -> Column:
    """Number of words: one more than the runs of blanks between them."""
    body = trimmed(text)
    return F.when(body == "", F.lit(0).cast("bigint")).otherwise(F.regexp_count(body, F.lit(BLANK_RUN)).cast("bigint") + 1)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def join_keyed(rows: DataFrame, keyed: DataFrame, key: str, rows_of: str, total: int, how: str = "inner") -> DataFrame:
    """``rows`` joined with ``keyed`` (one row for each non-null ``key``; column ``rows_of`` says how many of ``rows`` have it).

    Heavy keys, of which there are at most HEAVY_SHARE, are broadcast, so that no task gets all rows of one; the others
    are left to Spark.  ``rows_of`` is dropped.  how: ``inner``, or ``left``, where keys may be missing from ``keyed``."""
    limit = total // HEAVY_SHARE
    heavy = F.broadcast(keyed.filter(F.col(rows_of) > limit).drop(rows_of).withColumn("__heavy", F.lit(True)))
    light = keyed.filter(F.col(rows_of) <= limit).drop(rows_of)
    marked = rows.join(heavy, key, "left")
    columns = [*rows.columns, *[c for c in light.columns if c != key]]
    by_heavy = marked.filter("__heavy").select(*columns)
    rest = marked.filter("__heavy is null").select(*rows.columns)
    return by_heavy.unionByName(rest.join(light, key, how).select(*columns))


def gapless(rows: DataFrame, keys: list[str], order: list[str], out: str, buckets: int = 64) -> DataFrame:
    """Adds ``out``: 0, 1, 2, ... within each combination of ``keys``.

    Rows are dealt over buckets by a hash of the ordering columns; counts per bucket give each bucket its first number,
    so no task has to hold a whole group.  keys: not null."""
    dealt = rows.withColumn("__bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    counts = dealt.groupBy(*keys, "__bucket").agg(F.count("*").alias("__n"))
    before = Window.partitionBy(*keys).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*keys, "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__from"))
    within = Window.partitionBy(*keys, "__bucket").orderBy(*order)
    numbered = dealt.withColumn("__row", F.row_number().over(within)).join(offsets, [*keys, "__bucket"])
    return numbered.withColumn(out, F.col("__from") + F.col("__row") - 1).drop("__bucket", "__row", "__from")
