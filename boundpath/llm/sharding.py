"""Sharding by best-fit-decreasing bin packing of indivisible groups.

Sizes are summed per group in Spark, and groups of equal size are interchangeable: the packer works on the histogram of sizes
(size, number of groups), in falling order of size.  Every group enters the bin whose remaining capacity is
tightest, found in a balanced tree; a bin that takes one group of a size stays the tightest for the next of that size, so it takes as
many of them as fit in one step.  That is best-fit-decreasing over all groups, whatever their number.  Groups get their
places by their rank among those of their size.

The histogram is packed in a task (``applyInPandas``), never on the driver.  All sizes together are the table, so sizes that
differ number at most the square root of twice its bytes: 14 million at 100 TB.  With a fixed capacity the bins grow with the table; above
``MOST_BINS`` of them, groups are dealt by hash into parts that are packed apart, which may leave one bin a part
less full than it could be.

Defined cases: null text has size 0 plus the overhead and is a group of its own kind (all nulls together); equal
texts share a shard; a group larger than a fair share, or than the capacity, has a shard of its own; repeated rows take one slot each; an
empty table gives an empty result.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.llm.shared import gapless, join_keyed, materialise, read_table

OVERHEAD = 16
MOST_BINS = 1_000_000
PLACE_SCHEMA = "part int, size bigint, first_rank bigint, end_rank bigint, bin bigint, bins bigint"


class _Node:
    __slots__ = ("key", "left", "right", "height")

    def __init__(self, key):
        self.key, self.left, self.right, self.height = key, None, None, 1


def _height(node) -> int:
    return node.height if node else 0


def _turn(node: _Node, right: bool) -> _Node:
    top = node.left if right else node.right
    if right:
        node.left, top.right = top.right, node
    else:
        node.right, top.left = top.left, node
    node.height = 1 + max(_height(node.left), _height(node.right))
    top.height = 1 + max(_height(top.left), _height(top.right))
    return top


def _even(node: _Node) -> _Node:
    """The subtree with its two sides' heights at most one apart."""
    lean = _height(node.left) - _height(node.right)
    if lean > 1:
        if _height(node.left.left) < _height(node.left.right):
            node.left = _turn(node.left, False)
        return _turn(node, True)
    if lean < -1:
        if _height(node.right.right) < _height(node.right.left):
            node.right = _turn(node.right, True)
        return _turn(node, False)
    node.height = 1 + max(_height(node.left), _height(node.right))
    return node


class RemainingTree:
    """Bins by remaining capacity: a height-balanced search tree of (remaining, bin)."""

    def __init__(self):
        self._root = None

    def add(self, remaining: int, bin_id: int) -> None:
        def put(node):
            if node is None:
                return _Node((remaining, bin_id))
            if (remaining, bin_id) < node.key:
                node.left = put(node.left)
            else:
                node.right = put(node.right)
            return _even(node)

        self._root = put(self._root)

    def take_tightest(self, size: int) -> tuple[int, int] | None:
        """Remove and return the least (remaining, bin) with remaining >= size; None where nothing fits."""
        found, node = None, self._root
        while node:
            if node.key[0] >= size:
                found, node = node.key, node.left
            else:
                node = node.right
        if found is not None:
            self._root = self._without(self._root, found)
        return found

    def _without(self, node: _Node, key):
        if key < node.key:
            node.left = self._without(node.left, key)
        elif key > node.key:
            node.right = self._without(node.right, key)
        else:
            if node.left is None or node.right is None:
                return node.left or node.right
            after = node.right
            while after.left:
                after = after.left
            node.key, node.right = after.key, self._without(node.right, after.key)
        return _even(node)


def best_fit_decreasing(histogram: list[tuple[int, int]], capacity: int, most: int | None = None) -> tuple[list[tuple], int] | None:
    """Best-fit-decreasing of groups of given sizes into bins of one capacity.

    histogram: (size, number of groups), sizes falling and different.  Result: (size, bin, number of groups) in order of
    packing, and the number of bins.  None if a group exceeds the capacity or more than ``most`` bins would be needed.
    Ties: the bin opened first."""
    tree, runs, opened = RemainingTree(), [], 0
    for size, left in histogram:
        if size > capacity:
            return None
        while left:
            found = tree.take_tightest(size)
            if found is None:
                if most is not None and opened >= most:
                    return None
                found, opened = (capacity, opened), opened + 1
            taken = min(left, found[0] // size) if size else left
            runs.append((size, found[1], taken))
            tree.add(found[0] - taken * size, found[1])
            left -= taken
    return runs, opened


def pack_equal(histogram: list[tuple[int, int]], bins: int) -> list[tuple]:
    """(size, bin, number of groups) in ``bins`` bins of nearly equal load: groups above a fair share stand alone, the rest is packed
    under the least capacity found (first by growing steps, then by bisection) at which best-fit-decreasing needs no
    more than the bins left."""
    out, left, alone, rest = [], sum(s * n for s, n in histogram), 0, [list(h) for h in histogram]
    while rest and alone < bins - 1 and rest[0][0] * (bins - alone) > left:
        out.append((rest[0][0], alone, 1))
        left -= rest[0][0]
        alone += 1
        rest[0][1] -= 1
        if not rest[0][1]:
            rest.pop(0)
    if not rest:
        return out
    part, free = [tuple(h) for h in rest], bins - alone
    low = max(part[0][0], -(-left // free))
    step, high = max(1, low // 10**7), low
    while (found := best_fit_decreasing(part, high, free)) is None:
        low, high, step = high + 1, high + step, step * 4
    best = found
    while high - low > max(0, high // 10**6):
        middle = (low + high) // 2
        found = best_fit_decreasing(part, middle, free)
        if found is None:
            low = middle + 1
        else:
            best, high = found, middle
    return out + [(s, alone + b, n) for s, b, n in best[0]]


def pack_capacity(histogram: list[tuple[int, int]], capacity: int) -> list[tuple]:
    """(size, bin, number of groups) in as few bins of one capacity as best-fit-decreasing needs; a larger group has a bin of its own."""
    out, opened = [], 0
    for size, n in histogram:
        if size > capacity:
            out += [(size, opened + i, 1) for i in range(n)]
            opened += n
    runs, _ = best_fit_decreasing([h for h in histogram if h[0] <= capacity], capacity)
    return out + [(s, opened + b, n) for s, b, n in runs]


def _packer(shards: int | None, capacity: int | None):
    def run(frame: pd.DataFrame) -> pd.DataFrame:
        sizes = frame.sort_values("size", ascending=False)
        histogram = list(zip(sizes["size"].astype(int).tolist(), sizes["n"].astype(int).tolist(), strict=True))
        runs = pack_capacity(histogram, capacity) if capacity else pack_equal(histogram, shards)
        seen, rows = {}, []
        for size, place, n in runs:
            first = seen.get(size, 0)
            rows.append((size, first, first + n, place))
            seen[size] = first + n
        out = pd.DataFrame(rows, columns=["size", "first_rank", "end_rank", "bin"])
        out.insert(0, "part", int(frame["part"].iloc[0]))
        return out.assign(bins=shards or (int(out["bin"].max()) + 1))

    return run


def text_size(text: Column) -> Column:
    return (F.coalesce(F.octet_length(text), F.lit(0)) + OVERHEAD).cast("bigint")


def place_groups(groups: DataFrame, shards: int | None = None, capacity: int | None = None, most_bins: int = MOST_BINS) -> DataFrame:
    """(group_key, shard) of groups (group_key, size), one row each."""
    total = groups.agg(F.sum("size")).first()[0] or 0
    parts = max(1, -(-total // (capacity * most_bins))) if capacity else 1
    dealt = groups.select("group_key", "size", F.pmod(F.xxhash64("group_key", F.lit(5)), F.lit(parts)).cast("int").alias("part"))
    histogram = dealt.groupBy("part", "size").agg(F.count("*").alias("n"))
    runs = materialise(histogram.groupBy("part").applyInPandas(_packer(shards, capacity), PLACE_SCHEMA), "runs")
    if parts > 1:  # bins of a part are numbered behind those of the parts before
        each = runs.groupBy("part").agg(F.max("bins").alias("bins"))
        before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
        base = each.select("part", F.coalesce(F.sum("bins").over(before), F.lit(0)).alias("base"))
        runs = runs.join(F.broadcast(base), "part").withColumn("bin", F.col("bin") + F.col("base"))
    ranked = gapless(dealt, ["part", "size"], ["group_key"], "rank")
    inside = (F.col("rank") >= F.col("first_rank")) & (F.col("rank") < F.col("end_rank"))
    runs = runs.select(F.col("part").alias("r_part"), F.col("size").alias("r_size"), "first_rank", "end_rank", F.col("bin").cast("int").alias("shard"))
    return ranked.join(runs, (F.col("part") == F.col("r_part")) & (F.col("size") == F.col("r_size")) & inside).select("group_key", "shard")


def shard_groups(rows: DataFrame, shards: int | None = None, capacity: int | None = None, most_bins: int = MOST_BINS) -> DataFrame:
    """Adds ``shard`` to rows with columns ``group_key`` (bigint, not null) and ``size``.

    With ``shards`` the loads are made nearly equal; with ``capacity`` as few shards of that size are opened as
    best-fit-decreasing needs (a larger group has one of its own)."""
    groups = materialise(rows.groupBy("group_key").agg(F.sum("size").alias("size"), F.count("*").alias("rows_of")), "groups")
    total = groups.agg(F.sum("rows_of")).first()[0] or 0
    placed = place_groups(groups, shards, capacity, most_bins)
    placed = materialise(placed.join(groups.select("group_key", "rows_of"), "group_key"), "places")
    return join_keyed(rows, placed, "group_key", "rows_of", total)


def gapless_slots(rows: DataFrame, order: list[str]) -> DataFrame:
    """Adds ``slot``: 0, 1, 2, ... within each shard."""
    return gapless(rows, ["shard"], order, "slot")


def shard_documents(docs: DataFrame, shards: int | None = 40, capacity: int | None = None, most_bins: int = MOST_BINS) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot for every row of ``docs`` (doc_id, text)."""
    text = F.col("text").cast("string")
    rows = docs.select(
        "doc_id",
        text_size(text).alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).cast("bigint").alias("text_crc32"),
        F.when(text.isNull(), F.lit(0)).otherwise(F.xxhash64(text)).alias("group_key"),
    )
    rows = materialise(rows, "sizes")
    placed = materialise(shard_groups(rows, shards, capacity, most_bins), "placed")
    return gapless_slots(placed, ["doc_id", "text_crc32"]).select("doc_id", "size", "text_crc32", "shard", "slot")


def op4_sharding(spark, sf_dir: str) -> DataFrame:
    out = shard_documents(read_table(spark, sf_dir, "documents"), 40)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


QUERIES = {"op4_sharding": op4_sharding}
