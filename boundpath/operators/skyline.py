"""Rows of a group that few or no others dominate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.loop import keep


def skyline(df: DataFrame, keys: list[str], dims: list[str], k: int = 1) -> DataFrame:
    """Rows that fewer than k others of their keys dominate (no coordinate larger, one smaller); equal rows stay.

    One or two dimensions: one sort per key with running minima.  More, or k > 1: an anti join within the keys."""
    if k == 1 and len(dims) == 1:
        w = Window.partitionBy(*keys)
        return df.withColumn("__m", F.min(dims[0]).over(w)).filter(F.col(dims[0]) == F.col("__m")).drop("__m")
    if k == 1 and len(dims) == 2:
        a, b = dims
        before = Window.partitionBy(*keys).orderBy(a).rangeBetween(Window.unboundedPreceding, -1)
        level = Window.partitionBy(*keys).orderBy(a).rangeBetween(Window.currentRow, Window.currentRow)
        marked = df.withColumns({"__m": F.min(b).over(before), "__s": F.min(b).over(level)})
        return marked.filter(((F.col("__m").isNull()) | (F.col("__m") > F.col(b))) & (F.col("__s") == F.col(b))).drop("__m", "__s")
    other = df.select(*[F.col(c).alias(f"o_{c}") for c in (*keys, *dims)])
    worse = None
    for c in keys:
        test = F.col(c) == F.col(f"o_{c}")
        worse = test if worse is None else worse & test
    some = None
    for d in dims:
        worse = worse & (F.col(f"o_{d}") <= F.col(d))
        less = F.col(f"o_{d}") < F.col(d)
        some = less if some is None else some | less
    if k == 1:
        return df.join(other.distinct(), worse & some, "left_anti")
    rows = df.withColumn("__id", F.monotonically_increasing_id())
    rows = keep(rows)
    other = rows.select(*[F.col(c).alias(f"o_{c}") for c in (*keys, *dims)])
    beaten = rows.join(other, worse & some).groupBy("__id").count().filter(F.col("count") >= k).select("__id")
    return rows.join(beaten, "__id", "left_anti").drop("__id")


def beaten_by_older(rows: DataFrame, older: DataFrame | None, keys: list[str], dims: list[str], strict: bool = False) -> DataFrame:
    """The skyline of ``rows`` without those that a row of ``older`` (keys, dims) equals or dominates; strict: only dominates."""
    if older is None:
        return skyline(rows, keys, dims)
    if len(dims) > 2:
        test, less = None, F.lit(not strict)
        o = older.select(*[F.col(c).alias(f"o_{c}") for c in (*keys, *dims)])
        for c in keys:
            test = F.col(c) == F.col(f"o_{c}") if test is None else test & (F.col(c) == F.col(f"o_{c}"))
        for d in dims:
            test = test & (F.col(f"o_{d}") <= F.col(d))
            less = less | (F.col(f"o_{d}") < F.col(d))
        return skyline(rows.join(o, test & less, "left_anti"), keys, dims)
    a, b = dims[0], dims[-1]
    extra = [F.lit(None).cast(t).alias(c) for c, t in rows.dtypes if c not in {*keys, *dims}]
    both = rows.withColumn("__old", F.lit(False)).unionByName(older.select(*keys, *dict.fromkeys(dims), *extra, F.lit(True).alias("__old")))
    order = Window.partitionBy(*keys).orderBy(a)
    marked = both.withColumns(
        {
            "__m": F.min(b).over(order.rangeBetween(Window.unboundedPreceding, -1)) if len(dims) > 1 else F.lit(None).cast("bigint"),
            "__s": F.min(b).over(order.rangeBetween(Window.currentRow, Window.currentRow)) if len(dims) > 1 else F.min(a).over(Window.partitionBy(*keys)),
            "__o": F.min(F.when(F.col("__old"), F.col(b))).over(order.rangeBetween(Window.unboundedPreceding, Window.currentRow)),
        }
    )
    kept = marked.filter(~F.col("__old")).filter((F.col("__m").isNull() | (F.col("__m") > F.col(b))) & (F.col("__s") == F.col(b)))
    if not strict:
        kept = kept.filter(F.col("__o").isNull() | (F.col("__o") > F.col(b)))
    return kept.drop("__m", "__s", "__o", "__old")
