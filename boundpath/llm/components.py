"""Connected components of an edge table, wholly in Spark.

Edges are first reduced by a union-find inside each partition (memory: that partition's edges), then by alternating
star contractions: large-star hangs all larger neighbours of a vertex on its smallest neighbour, small-star does
so for the smaller ones.  Both are a ``min`` aggregate (partial sums before the shuffle, so hubs do no harm) and a join.
"""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import drop_materialised, materialise


def _union_find(batches):
    parent: dict[int, int] = {}

    def root(x):
        top = x
        while parent.setdefault(top, top) != top:
            top = parent[top]
        while parent[x] != top:
            parent[x], x = top, parent[x]
        return top

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            x, y = root(a), root(b)
            if x != y:
                parent[max(x, y)] = min(x, y)
    pairs = [(v, r) for v in parent if (r := root(v)) != v]
    if pairs:
        yield pa.RecordBatch.from_pandas(pd.DataFrame(pairs, columns=["u", "v"]), preserve_index=False)


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """edges: (u, v) with u > v."""
    if large:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        hung = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        hung = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return hung.filter("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()


def connected_components(edges: DataFrame, left: str = "u", right: str = "v", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of an edge; component is the smallest node it is connected with.

    Null ends and loops are ignored; an empty edge table gives an empty result."""
    now = edges.select(F.col(left).cast("bigint").alias("u"), F.col(right).cast("bigint").alias("v"))
    now = now.filter("u is not null and v is not null and u != v").mapInArrow(_union_find, "u bigint, v bigint")
    now = materialise(now, "cc")
    for _ in range(max_rounds):
        seen = _shape(now)
        if not seen[0]:
            break
        after = materialise(_star(_star(now, True), False), "cc")
        drop_materialised(now)
        now = after
        if _shape(now) == seen and _is_forest(now):
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )


def _shape(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.hash("u", "v").cast("bigint"))).first())


def _is_forest(edges: DataFrame) -> bool:
    return not edges.select("u").intersect(edges.select("v")).head(1)
