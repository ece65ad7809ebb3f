"""Corpus pipeline: quality rules, near-duplicate removal, decontamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept.  All but the last return the columns
of ``documents``; the last adds where each row goes.

Defined cases, in every stage: rows with a null ``doc_id`` are judged by their text like any other and carried on; null, empty and blank
texts are rejected by the first stage (and pass the others, if they meet them, as texts without words: they are no duplicates, repeat nothing, are never mixed in, and
weigh only their overhead in a shard); very long texts are judged whole; of rows equal in every column near-duplicate removal keeps one, and mixing takes equal rows
equally often, give or take one; an empty table stays empty; other columns, whatever their names, are carried on unchanged.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.llm.decontaminate import drop_contaminated
from boundpath.llm.mixing import mix
from boundpath.llm.neardup import near_duplicates
from boundpath.llm.quality import filter_quality
from boundpath.llm.shared import materialise, read_table, small
from boundpath.llm.sharding import gapless_slots, shard_groups, text_size

SHARDS = 40


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects."""
    return filter_quality(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group (five-word shingles, similarity 0.8): the one of the smallest id.

    Rows without an id, and those whose id stands beside several texts, get a number above all ids from id and text for this stage, so
    a different text is never dropped for its id; rows equal in id and text leave one row."""
    columns = docs.columns
    text, doc_id = F.col("text").cast("string"), F.col("doc_id").cast("bigint")
    several = docs.groupBy(doc_id.alias("__bp_doc")).agg(F.min(F.xxhash64(text)).alias("lo"), F.max(F.xxhash64(text)).alias("hi"))
    several = materialise(several.filter("lo != hi and __bp_doc is not null").select("__bp_doc", F.lit(True).alias("__bp_several")), "several")
    # few ids go to the texts, so that these are not moved for them
    rows = docs.join(small(several), doc_id == F.col("__bp_doc"), "left")
    number = F.shiftrightunsigned(F.xxhash64(doc_id, text), 2) + F.lit(1 << 62)
    rows = rows.withColumn("__bp_id", F.when(doc_id.isNull() | F.col("__bp_several"), number).otherwise(doc_id)).drop("__bp_doc", "__bp_several")
    judged = materialise(near_duplicates(rows.select(F.col("__bp_id").alias("doc_id"), "text"), k=5), "judged")
    # ids whose rows all go (0), and those of which one of several rows stays
    verdicts = judged.groupBy(F.col("doc_id").alias("__bp_id")).agg(F.count("*").alias("__bp_rows"), F.min("kept").alias("__bp_kept"))
    verdicts = verdicts.filter("not __bp_kept or __bp_rows > 1").withColumn("__bp_rows", F.when(F.col("__bp_kept"), F.col("__bp_rows")).otherwise(0)).drop("__bp_kept")
    left = rows.join(small(materialise(verdicts, "verdicts")), "__bp_id", "left")
    single = left.filter("__bp_rows is null")
    first = Window.partitionBy("__bp_id").orderBy(F.xxhash64(*[F.col(f"`{c}`") for c in columns]))
    equal = left.filter("__bp_rows > 1").withColumn("__bp_row", F.row_number().over(first)).filter("__bp_row = 1").drop("__bp_row")
    return single.unionByName(equal).select(*[F.col(f"`{c}`") for c in columns])


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that repeat no benchmark item, judged where they are read."""
    return drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it: not at all, or up to three rows."""
    columns = docs.columns
    taken = mix(docs).groupBy("doc_id", "source", "text_key").agg(F.sum("copies").alias("__bp_copies"), F.count("*").alias("__bp_rows"))
    taken = taken.filter("__bp_copies > 0").withColumnsRenamed({"doc_id": "__bp_doc", "source": "__bp_source", "text_key": "__bp_text"})
    keys = docs.withColumns({"__bp_key": F.xxhash64(F.col("text").cast("string")), "__bp_src": F.col("source").cast("string")})
    met = keys.join(taken, (F.col("__bp_key") == F.col("__bp_text")) & F.col("doc_id").eqNullSafe(F.col("__bp_doc")) & F.col("__bp_src").eqNullSafe(F.col("__bp_source")))
    one = met.filter("__bp_rows = 1").withColumn("__bp_n", F.col("__bp_copies"))
    # rows of one id, source and text share their copies evenly; a fixed order over all columns says who takes what is over
    place = Window.partitionBy("__bp_doc", "__bp_source", "__bp_text").orderBy(F.xxhash64(*[F.col(f"`{c}`") for c in columns]))
    many = met.filter("__bp_rows > 1").withColumn("__bp_at", F.row_number().over(place))
    share = F.floor(F.col("__bp_copies") / F.col("__bp_rows")) + F.when(F.col("__bp_at") <= F.col("__bp_copies") % F.col("__bp_rows"), 1).otherwise(0)
    both = one.unionByName(many.withColumn("__bp_n", share.cast("bigint")).drop("__bp_at")).filter("__bp_n > 0")
    return both.select(*[F.col(f"`{c}`") for c in columns], F.explode(F.sequence(F.lit(1), F.col("__bp_n").cast("int"))).alias("__bp_copy")).drop("__bp_copy")


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, lang, size, text_crc32, shard, slot of every row: 40 shards of nearly equal bytes."""
    text = F.col("text").cast("string")
    rows = docs.select(
        "doc_id",
        "source",
        "lang",
        text_size(text).alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).cast("bigint").alias("text_crc32"),
        F.when(text.isNull(), F.lit(0)).otherwise(F.xxhash64(text)).alias("group_key"),
    )
    placed = materialise(shard_groups(materialise(rows, "sizes"), SHARDS), "placed")
    return gapless_slots(placed, ["doc_id", "text_crc32"]).select("doc_id", "source", "lang", "size", "text_crc32", "shard", "slot")


STAGES = [("quality_rules", quality), ("near_dedup", near_dedup), ("decontamination", decontaminate), ("mixing", mix_sources), ("sharding", shard)]

#: Hashes and component search have no counterpart in SQL: tests/llm compares the pipeline with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, name)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
