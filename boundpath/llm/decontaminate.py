"""Benchmark decontamination by SimHash windows and multi-index Hamming search.

Each benchmark item of n words has a 64-bit SimHash over its word shingles; windows of exactly n words slide over the
documents.  The fingerprints of items are indexed by four 16-bit blocks: two fingerprints within 19 bits differ by at
most 4 bits in some block.  Both sides look up all values within 2 bits of their block, so blocks within 4 bits
meet, and all pairs within the radius are found.  Candidates
are then compared exactly by weighted (multiset) shingle similarity.  At similarity 0.8 fingerprints differ by 9.7 bits on
average (deviation 2.9), so a radius of 19 loses one such window in some 2000, and neighbouring windows remain.

Windows that share no shingle with an item of their size have similarity 0 and are not fingerprinted; that saves most
of the work and changes no result.  The benchmark is broadcast in blocks of a set number of items and bytes, a pass over
the documents for each block; up to ``ITEMS_PER_PASS`` items of ``BYTES_PER_PASS`` bytes together need one.

Words: runs of ASCII letters, digits and non-ASCII characters, lower-cased.  Defined cases: null and blank items match
nothing; an item of n words, fewer than a shingle has, is one shingle of n words and matches where a document has
just these words in a row; a document shorter than an item
is one window; null documents have no windows;
repeated items and documents are reported each.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import combinations
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boundpath.llm.shared import read_table
from boundpath.llm.textkernel import Words, mix, shingles, words

RADIUS, BLOCKS = 19, 4
#: An item takes some 5 kB of index and ten times its text in each worker.
ITEMS_PER_PASS, BYTES_PER_PASS = 20_000, 16_000_000
RESULT_SCHEMA = "doc_id bigint, item_id bigint, similarity double, n_windows bigint, first_word bigint"


def simhash(hashes: np.ndarray, counts: np.ndarray | None = None) -> int:
    bits = np.unpackbits(mix(hashes, 31).view(np.uint8)).reshape(len(hashes), 64).astype(np.int64) * 2 - 1
    if counts is not None:
        bits *= counts[:, None]
    return int(np.packbits(bits.sum(axis=0) > 0).view(np.uint64)[0])


def _near(radius: int, bits: int) -> np.ndarray:
    """All masks of up to ``radius`` bits."""
    return np.array([sum(1 << b for b in c) for r in range(radius + 1) for c in combinations(range(bits), r)], np.int64)


class HammingIndex:
    """All fingerprints within a radius, by blocks: some block is within radius // blocks bits (pigeonhole).  Half of these
    bits are spent on the fingerprints' side, the rest on the queries'."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS, blocks: int = BLOCKS):
        self.prints, self.radius, self.blocks = prints, radius, blocks
        self.bits = 64 // blocks
        each = radius // blocks
        self.masks = _near(each - each // 2, self.bits)
        masks = _near(each // 2, self.bits)
        self.tables = []
        for b in range(blocks):
            key = (self._block(prints, b)[:, None] ^ masks[None, :]).reshape(-1)
            owner = np.repeat(np.arange(len(prints), dtype=np.int32), len(masks))
            order = np.argsort(key, kind="stable")
            self.tables.append((key[order].astype(np.int32), owner[order]))

    def _block(self, prints: np.ndarray, b: int) -> np.ndarray:
        return (prints >> np.uint64(b * self.bits)).astype(np.int64) & ((1 << self.bits) - 1)

    def search(self, queries: np.ndarray, part: int = 2048) -> tuple[np.ndarray, np.ndarray]:
        """(query, print) numbers of all pairs within the radius."""
        found = [np.zeros(0, np.int64)]
        for lo in range(0, len(queries), part):
            mine = queries[lo : lo + part]
            for b, (key, owner) in enumerate(self.tables):
                value = (self._block(mine, b)[:, None] ^ self.masks[None, :]).reshape(-1).astype(np.int32)
                first = np.searchsorted(key, value)
                n = np.searchsorted(key, value, "right") - first
                q = np.repeat(np.arange(len(value)) // len(self.masks) + lo, n)
                at = np.arange(len(q)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first, n)
                found.append(np.unique(q * len(self.prints) + owner[at]))
        pair = np.unique(np.concatenate(found))
        q, p = pair // max(1, len(self.prints)), pair % max(1, len(self.prints))
        close = np.bitwise_count(queries[q] ^ self.prints[p]) <= self.radius
        return q[close], p[close]


@dataclass
class Items:
    """Benchmark items of one pass, the index of their fingerprints by number of words, and their shingles by length."""

    ids: list
    n_words: np.ndarray
    bags: list  # Counter of shingles
    index: dict  # n_words -> (item numbers, HammingIndex)
    shingles: dict  # words in a shingle -> _Known


@dataclass
class _Known:
    """Shingles of one length: sorted, the sizes of the items that hold each, and a filter of their first bits."""

    sorted: np.ndarray
    size_of: dict
    bitmap: np.ndarray

    def hits(self, hashed: np.ndarray) -> np.ndarray:
        maybe = np.flatnonzero(self.bitmap[(hashed >> np.uint64(44)).astype(np.int64)])
        slot = np.minimum(np.searchsorted(self.sorted, hashed[maybe]), len(self.sorted) - 1)
        return maybe[self.sorted[slot] == hashed[maybe]]


def build_items(rows: list[tuple], k: int) -> Items:
    bags, sizes, ids, prints = [], [], [], []
    for item_id, text in rows:
        for w in words(pa.array([text or ""]), "alnum"):
            if len(w.hash):
                _, _, hashed = shingles(w, min(k, len(w.hash)))
                ids.append(item_id)
                sizes.append(len(w.hash))
                bags.append(Counter(hashed.tolist()))
                prints.append(simhash(hashed))
    n_words, prints = np.array(sizes, np.int64), np.array(prints, np.uint64)
    index = {}
    for n in np.unique(n_words).tolist():
        mine = np.flatnonzero(n_words == n)
        index[n] = (mine, HammingIndex(prints[mine]))
    held: dict[int, dict[int, set]] = {}
    for bag, n in zip(bags, sizes, strict=True):
        for s in bag:
            held.setdefault(min(k, n), {}).setdefault(s, set()).add(n)
    known = {}
    for length, of in held.items():
        each = np.array(sorted(of), np.uint64)
        bitmap = np.zeros(1 << 20, bool)
        bitmap[(each >> np.uint64(44)).astype(np.int64)] = True
        known[length] = _Known(each, {s: sorted(v) for s, v in of.items()}, bitmap)
    return Items(ids, n_words, bags, index, known)


def _starts(at: np.ndarray, span: int, last: int) -> np.ndarray:
    """Window starts (of ``span`` shingles) that cover one of the shingle positions ``at``; at most ``last``."""
    flag = np.zeros(last + 2, np.int64)
    lo = np.maximum(at - span + 1, 0)
    hi = np.minimum(at, last)
    ok = lo <= hi
    np.add.at(flag, lo[ok], 1)
    np.add.at(flag, hi[ok] + 1, -1)
    return np.flatnonzero(np.cumsum(flag)[: last + 1] > 0)


def scan(w: Words, items: Items, k: int, threshold: float) -> list[tuple]:
    """(document in chunk, item number, similarity, windows, first word) of the chunk's contaminated pairs."""
    out = []
    for length, known in items.shingles.items():
        out += _scan_length(w, items, length, known, threshold)
    merged: dict[tuple, tuple] = {}
    for d, i, sim, n, s in out:
        old = merged.get((d, i))
        merged[d, i] = (sim, n, s) if old is None else (max(sim, old[0]), n + old[1], s if sim > old[0] else old[2])
    return [(d, i, *v) for (d, i), v in sorted(merged.items())]


def _scan_length(w: Words, items: Items, length: int, known: _Known, threshold: float) -> list[tuple]:
    doc, pos, hashed = shingles(w, length)
    hit = known.hits(hashed) if len(hashed) else hashed
    if not len(hit):
        return []
    out = []
    per_doc = np.bincount(doc, minlength=w.n_docs)
    base = np.cumsum(per_doc) - per_doc
    cut = np.flatnonzero(np.diff(doc[hit])) + 1
    for group in np.split(hit, cut):
        d = int(doc[group[0]])
        mine = hashed[base[d] : base[d] + per_doc[d]]
        sizes: dict[int, list] = {}
        for g in group.tolist():
            for n in known.size_of[int(hashed[g])]:
                sizes.setdefault(n, []).append(g - base[d])
        bits = None
        for n, at in sizes.items():
            span = min(n - length + 1, len(mine))
            starts = _starts(np.array(at), span, len(mine) - span)
            if not len(starts):
                continue
            if bits is None:
                low = int(group[0] - base[d])
                widest = max(sizes)
                lo, hi = max(0, low - widest), min(len(mine), int(group[-1] - base[d]) + widest + 1)
                raw = np.unpackbits(mix(mine[lo:hi].copy(), 31).view(np.uint8)).reshape(hi - lo, 64).astype(np.int32) * 2 - 1
                bits = np.concatenate([np.zeros((1, 64), np.int32), np.cumsum(raw, axis=0, dtype=np.int32)])
            numbers, index = items.index[n]
            for part in np.array_split(starts, -(-len(starts) // 8192)):
                total = bits[part + span - lo] - bits[part - lo]
                prints = np.packbits(total > 0, axis=1).view(np.uint64).reshape(-1)
                q, p = index.search(prints)
                best: dict[int, list] = {}
                for s, i in zip(part[q].tolist(), numbers[p].tolist(), strict=True):
                    sim = bag_similarity(Counter(mine[s : s + span].tolist()), items.bags[i])
                    if sim >= threshold:
                        best.setdefault(i, []).append((sim, s))
                for i, found in best.items():
                    top = max(found, key=lambda x: (x[0], -x[1]))
                    out.append((d, i, top[0], len(found), top[1]))
    return out


def bag_similarity(a: Counter, b: Counter) -> float:
    both = sum(min(n, b[s]) for s, n in a.items() if s in b)
    return both / (sum(a.values()) + sum(b.values()) - both)


_BUILT: dict[str, Items] = {}


def _built(items, tag: str, k: int) -> Items:
    """The index of a pass, kept by the worker; two at most, since a union's passes may take turns."""
    if tag not in _BUILT:
        while len(_BUILT) > 1:
            _BUILT.pop(next(iter(_BUILT)))
        _BUILT[tag] = build_items(items.value, k)
    return _BUILT[tag]


def _kernel(items, tag: str, k: int, threshold: float):
    def run(batches):
        known = _built(items, tag, k)
        for batch in batches:
            ids = batch.column(0)
            rows = []
            for w in words(batch.column(1), "alnum"):
                for d, i, sim, n, s in scan(w, known, k, threshold):
                    rows.append((ids[w.first + d].as_py(), known.ids[i], sim, n, s))
            types = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64())
            names = ["doc_id", "item_id", "similarity", "n_windows", "first_word"]
            columns = zip(*rows, strict=True) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, types, strict=True)], names=names)

    return run


#: Bytes of text that the sieve takes at once: rows with all their columns lie beside them in the worker.
SIEVE_CHUNK = 500_000


def _sieve(items, tag: str, k: int, threshold: float, text: int):
    """Whole rows of documents that repeat no item; column ``text`` holds the texts."""

    def run(batches):
        known = _built(items, tag, k)
        for batch in batches:
            clean = np.ones(batch.num_rows, bool)
            for w in words(batch.column(text).cast(pa.string()), "alnum", SIEVE_CHUNK):
                for d, *_ in scan(w, known, k, threshold):
                    clean[w.first + d] = False
            yield batch if clean.all() else batch.filter(pa.array(clean))

    return run


def _passes(benchmark: DataFrame, items_per_pass: int) -> list[tuple]:
    """(broadcast items, tag) of each pass over the documents."""
    spark = benchmark.sparkSession
    items = benchmark.select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text")).filter("text is not null")
    n, size = items.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    passes = max(1, -(-n // items_per_pass), -(-size // BYTES_PER_PASS))
    out = []
    for p in range(passes):
        mine = items if passes == 1 else items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(passes)) == p)
        out.append((spark.sparkContext.broadcast([tuple(r) for r in mine.orderBy("item_id", "text").collect()]), uuid4().hex))
    return out


def contaminated(docs: DataFrame, benchmark: DataFrame, k: int = 5, threshold: float = 0.8, items_per_pass: int = ITEMS_PER_PASS) -> DataFrame:
    """(doc_id, item_id, similarity, n_windows, first_word): documents with a window that repeats a benchmark item.

    similarity is that of the best window, first_word where it starts, n_windows how many windows reach the threshold."""
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = None
    for items, tag in _passes(benchmark, items_per_pass):
        found = own.mapInArrow(_kernel(items, tag, k, threshold), RESULT_SCHEMA)
        out = found if out is None else out.union(found)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, k: int = 5, threshold: float = 0.8, items_per_pass: int = ITEMS_PER_PASS) -> DataFrame:
    """``docs`` without the rows whose text repeats a benchmark item, all columns kept: each row is judged where it is read, without a shuffle."""
    out = docs
    for items, tag in _passes(benchmark, items_per_pass):
        out = out.mapInArrow(_sieve(items, tag, k, threshold, docs.columns.index("text")), docs.schema)
    return out


def op1_decontamination(spark, sf_dir: str) -> DataFrame:
    return contaminated(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


QUERIES = {"op1_decontamination": op1_decontamination}
