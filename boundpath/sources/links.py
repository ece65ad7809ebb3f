"""Graph discovery from configuration files, and sinks for answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LINK_SCHEMA = "link_id bigint, src bigint, dst bigint, bw bigint, delay bigint, cost bigint"
FORMATS = ("parquet", "json", "csv", "xml")


def load_links(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Links from files of one format, by a set schema (nothing is inferred); rows without both ends fail the load."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format {fmt!r}")
    reader = spark.read.schema(LINK_SCHEMA).option("mode", "FAILFAST")
    if fmt == "csv":
        reader = reader.option("header", True)
    if fmt == "xml":
        reader = reader.option("rowTag", "link")
    links = reader.format(fmt).load(path)
    ends = F.col("src").isNotNull() & F.col("dst").isNotNull()
    return links.withColumn("src", F.when(ends, F.col("src")).otherwise(F.raise_error(F.lit("a link needs both ends"))))


def save_links(links: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = links.select(*[c.split()[0] for c in LINK_SCHEMA.split(", ")]).write.mode("overwrite").format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    if fmt == "xml":
        writer = writer.option("rowTag", "link").option("rootTag", "links")
    writer.save(path)


def save_answers(answers: DataFrame, path: str) -> None:
    """Answers as JSON lines, one folder for each status."""
    answers.write.mode("overwrite").partitionBy("status").json(path)
