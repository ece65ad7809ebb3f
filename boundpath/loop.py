"""Materialised steps of driver loops: lineage is cut by tables in the shared folder, never by executor-local copies."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: Tables of at most this many rows may be broadcast.
SMALL_ROWS = 1_000_000

_written: list[str] = []
_fallback: list[str] = []
_tables: dict[tuple, DataFrame] = {}


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session.  Where it is unset, a temporary folder on one machine (a local master,
    as in tests) and an error on a cluster, whose executors would not see that folder."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        place = known.get() if known.isDefined() else None
    if not place:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise ValueError(f"spark.checkpoint.dir is not set: {master} needs a folder that all executors share")
        if not _fallback:
            _fallback.append("file://" + tempfile.mkdtemp(prefix="boundpath-"))
        place = _fallback[0]
    return place.rstrip("/")


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder; what lies there is removed when the program ends."""
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    if not _written:
        atexit.register(_sweep, spark)
    _written.append(path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    try:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended: a leftover is no harm to results
        pass
    if path in _written:
        _written.remove(path)


def keep(df: DataFrame, tag: str = "step") -> DataFrame:
    """Write ``df`` once and read it back; later steps start from the table."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._boundpath_path = path
    return out


def keep_counted(df: DataFrame, tag: str = "step", **sums) -> tuple[DataFrame, dict]:
    """``keep`` and, from the same job, ``rows`` and any further aggregates."""
    seen = Observation()
    out = keep(df.observe(seen, F.count(F.lit(1)).alias("rows"), *[c.alias(n) for n, c in sums.items()]), tag)
    return out, seen.get


def drop(df: DataFrame) -> None:
    """Remove a table that ``keep`` wrote."""
    path = getattr(df, "_boundpath_path", None)
    if path:
        remove(df.sparkSession, path)


def once(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A table that many queries of one session start from (a network), made once."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _tables:
        _tables[full] = keep(make(), "-".join(str(k).replace("/", "_") for k in key)[-60:])
    return _tables[full]


def small(df: DataFrame) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``SMALL_ROWS`` rows; beyond, Spark chooses the join."""
    return F.broadcast(df) if df.limit(SMALL_ROWS + 1).count() <= SMALL_ROWS else df


def empty(df: DataFrame) -> bool:
    return not df.take(1)


def _sweep(spark: SparkSession) -> None:
    for path in list(_written):
        remove(spark, path)
