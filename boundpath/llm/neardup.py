"""Near-duplicate documents by SuperMinHash, banding, exact verification and component grouping.

Signatures of 128 places in 32 bands of 4: a pair of similarity 0.8 shares no band with probability 5e-8.  Documents
with equal shingle sets form one class first, so copies never meet each other.  Within a band's bucket no pairs are
listed.  Instead:

1. every bucket member is compared with the bucket's *hub*, the member that sits in the fullest buckets (the original
   of a group of near copies); links are verified on full shingle sets and contracted to components;
2. members of buckets that still hold several components are compared by an exact prefix join over their rarest
   shingles (with size and position bounds), which finds every remaining link without meeting pairs that cannot
   reach the similarity.  A verified link between different components merges them.

A class is known by the smallest ``doc_id`` of its rows; where rows of one ``doc_id`` differ, each text still has a class, a set and links of its
own (its further classes get numbers from 2^62 on, above any ``doc_id`` in use).  A shingle of very many documents is dealt over a square of tasks by hashes of both sides, so that no task gets all of them.

Defined cases: null or blank text has no shingles and no links; fewer words than the shingle size make one shingle of
the whole sequence; equal sets are linked; rows that share a ``doc_id`` count as one document, linked with whatever one of them is; rows without
``doc_id`` belong to the class of their set, and where no member of it has an id their component is null and they are kept.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.llm.components import connected_components
from boundpath.llm.shared import drop_materialised, join_keyed, materialise, read_table, small
from boundpath.llm.superminhash import band_keys, signatures
from boundpath.llm.textkernel import distinct, mix, segment_sum, shingles, words

PLACES, BAND_ROWS = 128, 4
#: Bytes of text that a Python worker takes at once: its arrays take many times as much, beside those of the executor's other workers.
CHUNK = 500_000
#: Rows of one shingle that a task of the prefix join takes from each side.
CELL = 1000


def _sign(k: int, places: int, rows: int):
    bands = places // rows

    def run(batches):
        for batch in batches:
            ids, rkey, texts = batch.column(0), batch.column(1), batch.column(2)
            for w in words(texts, limit=CHUNK):
                doc, _, hashed = shingles(w, k)
                owner, element, count = distinct(doc, hashed, w.n_docs)
                hi = segment_sum(mix(element, 11), count).view(np.int64)
                lo = segment_sum(mix(element, 12), count).view(np.int64)
                keys = band_keys(signatures(owner, element, w.n_docs, places), rows)
                yield pa.RecordBatch.from_arrays(
                    [
                        ids.slice(w.first, w.n_docs).cast(pa.int64()),
                        rkey.slice(w.first, w.n_docs),
                        pa.array(count.astype(np.int64)),
                        pa.array(hi),
                        pa.array(lo),
                        pa.ListArray.from_arrays(pa.array(np.arange(w.n_docs + 1, dtype=np.int32) * bands), pa.array(keys.reshape(-1))),
                    ],
                    names=["doc_id", "rkey", "n_shingles", "set_hi", "set_lo", "bands"],
                )

    return run


def _sets(k: int):
    """(doc_id, shingle) rows of documents, distinct."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            for w in words(batch.column(1), limit=CHUNK):
                doc, _, hashed = shingles(w, k)
                owner, element, _ = distinct(doc, hashed, w.n_docs)
                yield pa.RecordBatch.from_arrays([ids.slice(w.first, w.n_docs).take(pa.array(owner)), pa.array(element.view(np.int64))], names=["doc_id", "shingle"])

    return run


def _verify(k: int, num: int, den: int):
    """Pairs (a, b, text_a, text_b) whose full sets are similar enough.  The set of a side that repeats is kept."""

    def run(batches):
        kept: dict[int, np.ndarray] = {}
        size = 0
        for batch in batches:
            a, b = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            sides = []
            for ids, texts in ((a, batch.column(2)), (b, batch.column(3))):
                new = [i for i, x in enumerate(ids) if x not in kept]
                new = list({ids[i]: i for i in new}.values())
                if new:
                    for w in words(texts.take(pa.array(new)), limit=CHUNK):
                        doc, _, hashed = shingles(w, k)
                        _, element, count = distinct(doc, hashed, w.n_docs)
                        for i, part in enumerate(np.split(element, np.cumsum(count)[:-1])):
                            kept[ids[new[w.first + i]]] = part
                            size += len(part)
                sides.append(ids)
            good = []
            for i, (x, y) in enumerate(zip(a, b, strict=True)):
                p, q = kept[x], kept[y]
                if min(len(p), len(q)) * den >= max(len(p), len(q)) * num:
                    both = len(np.intersect1d(p, q, assume_unique=True))
                    if both and den * both >= num * (len(p) + len(q) - both):
                        good.append(i)
            yield batch.select([0, 1]).take(pa.array(good, pa.int64()))
            if size > 4_000_000:
                kept, size = {}, 0

    return run


def verified(pairs: DataFrame, texts: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """The pairs (a, b) with similarity num/den at least on full shingle sets; texts: (doc_id, text)."""
    side = texts.select("doc_id", "text")
    rows = pairs.join(side.withColumnsRenamed({"doc_id": "b", "text": "text_b"}), "b").join(side.withColumnsRenamed({"doc_id": "a", "text": "text_a"}), "a")
    return rows.select("a", "b", "text_a", "text_b").mapInArrow(_verify(k, num, den), "a bigint, b bigint")


def _bucket_members(classes: DataFrame) -> DataFrame:
    """(key, id, n, fill) of the buckets with at least two classes."""
    rows = classes.select("id", "n", F.explode("bands").alias("key"))
    full = rows.groupBy("key").agg(F.count("*").alias("fill")).filter("fill > 1")
    return rows.join(full, "key")


def _hub_pairs(members: DataFrame) -> DataFrame:
    score = members.groupBy("id").agg(F.sum("fill").alias("score"))
    scored = members.select("key", "id").join(score, "id")
    hub = scored.groupBy("key").agg(F.max(F.struct("score", (-F.col("id")).alias("minus"))).alias("top"))
    hub = hub.select("key", (-F.col("top.minus")).alias("hub"))
    return members.select("key", "id").join(hub, "key").filter("id != hub").select(F.col("hub").alias("a"), F.col("id").alias("b")).distinct()


def _prefix_pairs(texts: DataFrame, loose: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """Pairs of different components that can reach the similarity: they share a shingle within their prefixes.

    Shingles are ordered by the number of loose documents that hold them, rarest first; those of one document only
    match nothing and count for positions alone.  loose: (id, n, component)."""
    rows = texts.join(loose.select(F.col("id").alias("doc_id")), "doc_id").select("doc_id", "text")
    rows = materialise(rows.mapInArrow(_sets(k), "doc_id bigint, shingle bigint").select(F.col("doc_id").alias("id"), "shingle"), "sets")
    held = rows.groupBy("shingle").agg(F.count("*").alias("df"), F.min("id").alias("one")).filter("df > 1").select("shingle", "df")
    common = rows.join(held, "shingle").join(loose, "id")
    per_doc = Window.partitionBy("id")
    placed = (
        common.withColumn("shared", F.count("*").over(per_doc))
        .filter(f"shared * {den} >= n * {num}")
        .withColumn("pos", F.row_number().over(per_doc.orderBy("df", "shingle")) + F.col("n") - F.col("shared"))
    )
    probe = placed.filter(f"{den} * (pos - 1) <= n * ({den} - {num})")
    probe = materialise(probe.select("shingle", "id", "component", F.col("n").cast("bigint").alias("n"), F.col("pos").cast("bigint").alias("pos")), "prefix")
    mixed = probe.groupBy("shingle").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("met")).filter("lo != hi")
    probe = probe.join(mixed.select("shingle", F.ceil(F.col("met") / CELL).cast("int").alias("cells")), "shingle")
    # every pair meets in the one cell of its two hashes
    own = F.pmod(F.xxhash64("id"), F.col("cells")).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.col("cells") - 1))
    x = probe.withColumn("row", own).withColumn("column", every).alias("x")
    y = probe.withColumn("column", own).withColumn("row", every).alias("y")
    # overlap needed: num/(num+den) of the sum of sizes; overlap possible after first meeting at these positions
    need = F.col("x.n") * num + F.col("y.n") * num
    possible = (F.least(F.col("x.n") - F.col("x.pos"), F.col("y.n") - F.col("y.pos")) + 1) * (num + den)
    size_order = (F.col("x.n") > F.col("y.n")) | ((F.col("x.n") == F.col("y.n")) & (F.col("x.id") > F.col("y.id")))
    cell = (F.col("x.shingle") == F.col("y.shingle")) & (F.col("x.row") == F.col("y.row")) & (F.col("x.column") == F.col("y.column"))
    met = x.join(y, cell & (F.col("x.component") != F.col("y.component")) & size_order & (F.col("y.n") * den >= F.col("x.n") * num) & (possible >= need))
    return met.select(F.col("x.id").alias("a"), F.col("y.id").alias("b")).distinct()


def near_duplicates(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, places: int = PLACES, band_rows: int = BAND_ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of ``docs`` (doc_id, text; other columns are ignored)."""
    text = F.col("text").cast("string")
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.xxhash64(F.col("doc_id").cast("bigint"), text).alias("rkey"), text.alias("text"))
    signed = materialise(own.mapInArrow(_sign(k, places, band_rows), "doc_id bigint, rkey bigint, n_shingles bigint, set_hi bigint, set_lo bigint, bands array<bigint>"), "signed")
    total = signed.count()
    worded = signed.filter("n_shingles > 0 and doc_id is not null")
    classes = worded.groupBy("set_hi", "set_lo").agg(
        F.min(F.struct("doc_id", "rkey")).alias("one"), F.first("n_shingles").alias("n"), F.first("bands").alias("bands"), F.count("*").alias("rows_of")
    )
    classes = materialise(classes.select("set_hi", "set_lo", F.col("one.doc_id").alias("doc_id"), F.col("one.rkey").alias("rkey"), "n", "bands", "rows_of"), "classes")
    # a doc_id whose texts differ is the smallest of several classes: all but one take a number of their own
    times = classes.groupBy("doc_id").agg(F.count("*").alias("times"), F.min("rkey").alias("first")).filter("times > 1").select("doc_id", "first")
    number = F.when(F.col("first").isNull() | (F.col("first") == F.col("rkey")), F.col("doc_id")).otherwise(F.shiftrightunsigned(F.xxhash64("set_hi", "set_lo"), 2) + F.lit(1 << 62))
    classes = classes.join(times, "doc_id", "left").withColumn("id", number).drop("first")
    members = materialise(_bucket_members(classes), "members")
    ids = members.select("id", "n").distinct()
    texts = materialise(_texts(own, signed, classes.join(ids.select("id"), "id", "left_semi").select("id", "rkey")), "texts")
    links = materialise(verified(_hub_pairs(members), texts, k, num, den), "links")
    # rows of one doc_id count as one document: its classes are united, by the id of each
    again = worded.groupBy("doc_id").agg(F.min("set_hi").alias("x"), F.max("set_hi").alias("y"), F.min("set_lo").alias("z"), F.max("set_lo").alias("t")).filter("x != y or z != t").select("doc_id")
    shared = worded.join(again, "doc_id", "left_semi").select("doc_id", "set_hi", "set_lo").distinct()
    shared = shared.join(classes.select("set_hi", "set_lo", "id"), ["set_hi", "set_lo"])
    united = shared.join(shared.groupBy("doc_id").agg(F.min("id").alias("least")), "doc_id").filter("id != least").select(F.col("least").alias("a"), F.col("id").alias("b"))
    links = links.union(united)
    first = connected_components(links, "a", "b")

    located = members.join(first.withColumnRenamed("node", "id"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    mixed = located.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo != hi").select("key")
    loose = materialise(located.join(mixed, "key", "left_semi").select("id", "n", "component").distinct(), "loose")
    more = materialise(verified(_prefix_pairs(texts, loose, k, num, den), texts, k, num, den), "links")
    merged = connected_components(links.union(more), "a", "b") if more.head(1) else first
    drop_materialised(texts)

    found = classes.select("set_hi", "set_lo", "rows_of", "id").join(merged.withColumnRenamed("node", "id"), "id", "left")
    key = F.struct("set_hi", "set_lo").alias("set")
    final = materialise(found.select(key, "rows_of", F.coalesce("component", "id").alias("component_id")), "components")
    out = join_keyed(signed.filter("n_shingles > 0").select("doc_id", "n_shingles", key), final, "set", "rows_of", total, "left").drop("set")
    alone = signed.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()))


def _texts(own: DataFrame, signed: DataFrame, wanted: DataFrame) -> DataFrame:
    """(doc_id, text) with the ids of classes, one row each.  wanted: (id, rkey); equal rows have one rkey."""
    repeated = signed.groupBy("rkey").agg(F.count("*").alias("times")).filter("times > 1").select("rkey", F.lit(True).alias("again"))
    wanted = materialise(wanted.select("rkey", F.col("id").alias("class")).join(repeated, "rkey", "left"), "wanted")
    met = own.join(small(wanted), "rkey")  # few classes go to the texts, so that these are not moved
    once = met.filter("again is null").select(F.col("class").alias("doc_id"), "text")
    often = met.filter("again").groupBy(F.col("class").alias("doc_id")).agg(F.first("text").alias("text"))
    return once.unionByName(often)


def op7_near_duplicates(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"), k=4)


QUERIES = {"op7_near_duplicates": op7_near_duplicates}
#: All pairs of documents that share a shingle, and the closure of their links: for small tables.
ORACLES = {
    "op7_near_duplicates": r"""
WITH RECURSIVE parts AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
 shingle AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 3], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM parts WHERE len(w) > 0)),
 held AS (SELECT doc_id, count(*) AS n FROM shingle GROUP BY doc_id),
 met AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM shingle x JOIN shingle y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY x.doc_id, y.doc_id),
 link AS (SELECT a, b FROM met JOIN held p ON p.doc_id = a JOIN held q ON q.doc_id = b WHERE 100 * shared >= 80 * (p.n + q.n - shared)),
 reach(a, b) AS (SELECT doc_id, doc_id FROM parts UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a),
 least AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a)
SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM parts LEFT JOIN held USING (doc_id) JOIN least ON a = doc_id"""
}
