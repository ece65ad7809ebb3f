"""Vectorised word streams over Arrow string columns.

The kernels read the UTF-8 buffer of an Arrow array directly: words are found and hashed with numpy, so no Python
object is made per word.  Work goes through chunks of a few MB of text, whatever the size of the Arrow batch, which
bounds the memory of a Python worker; one document is never split, so a very long one makes a chunk of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 2_000_000
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1


@cache
def word_bytes(kind: str) -> np.ndarray:
    """Which bytes belong to words: ``space`` splits at ASCII white space, ``alnum`` keeps ASCII letters, digits and
    all bytes of non-ASCII characters."""
    table = np.ones(256, bool)
    if kind == "space":
        table[[32, *range(9, 14)]] = False
    else:
        table[:128] = False
        for low, high in ((48, 58), (65, 91), (97, 123)):
            table[low:high] = True
    return table


@cache
def lower_table() -> np.ndarray:
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


_POWERS: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if "p" not in _POWERS or len(_POWERS["p"]) < n:
        size = max(n, CHUNK_BYTES + 1)
        for name, base in (("p", _BASE), ("i", pow(_BASE, -1, 1 << 64))):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            _POWERS[name] = np.multiply.accumulate(out)
    return _POWERS["p"], _POWERS["i"]


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser (shift-multiply), salted."""
    x = x + np.uint64((salt * 0xD1B54A32D192ED03 + 0x632BE59BD9B4E019) & _MASK)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


@dataclass
class Words:
    """Words of consecutive documents: byte spans in ``data``, the document of each word, and its hash."""

    first: int  # row of the first document in the batch
    n_docs: int
    data: np.ndarray
    doc_start: np.ndarray  # byte offsets of documents, one more than documents
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    hash: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.bincount(self.doc, minlength=self.n_docs)

    def text(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()


def _buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32, n + 1, column.offset * (8 if wide else 4)).astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return off, raw


def chunks(column: pa.Array | pa.ChunkedArray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, document offsets from 0, bytes) of runs of whole documents of about ``limit`` bytes; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if pa.types.is_null(column.type):
        column = column.cast(pa.string())
    if column.null_count:
        column = column.fill_null("" if not (pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type)) else b"")
    if not len(column):
        return
    off, raw = _buffers(column)
    at, n = 0, len(column)
    while at < n:
        to = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
        to = min(to, at + 4000, n)
        yield at, off[at : to + 1] - off[at], raw[off[at] : off[to]]
        at = to


def split_spans(off: np.ndarray, raw: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte spans of words: runs of bytes of ``table``, cut where documents end."""
    n = len(raw)
    inside = np.zeros(n + 2, bool)
    inside[1:-1] = table[raw]
    change = np.flatnonzero(inside[1:] != inside[:-1])
    borders = off[1:-1]
    borders = np.unique(borders[(borders > 0) & (borders < n)])
    crossed = borders[inside[borders] & inside[borders + 1]] if len(borders) else borders
    if len(crossed):
        change = np.sort(np.concatenate([change, crossed, crossed]), kind="stable")
    return change[0::2], change[1::2]


def words(column, kind: str = "space", limit: int = CHUNK_BYTES) -> Iterator[Words]:
    """Word streams with A-Z lower-cased."""
    table, low = word_bytes(kind), lower_table()
    for first, off, raw in chunks(column, limit):
        data = low[raw]
        n_docs, n = len(off) - 1, len(raw)
        start, end = split_spans(off, raw, table)
        power, inverse = powers(n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[:n], out=total[1:])
        hashed = mix((total[end] - total[start]) * inverse[start], 1)
        doc = np.searchsorted(off, start, "right") - 1
        yield Words(first, n_docs, data, off, start, end, doc, hashed)


_COEF = [np.uint64((0xA24BAED4963EE407 * (2 * i + 3) ** 7) & _MASK | 1) for i in range(16)]


def shingles(w: Words, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, word position, hash) of all runs of k words; a document of fewer words has one, its whole sequence."""
    counts = w.counts
    n = len(w.hash)
    first_word = np.concatenate([[0], np.cumsum(counts)[:-1]]).astype(np.int64)
    per_doc = np.where(counts >= k, counts - k + 1, (counts > 0).astype(np.int64))
    doc = np.repeat(np.arange(w.n_docs), per_doc)
    at = np.arange(len(doc)) - np.repeat(np.cumsum(per_doc) - per_doc, per_doc) + np.repeat(first_word, per_doc)
    out = np.zeros(len(doc), np.uint64)
    last = (first_word + counts)[doc]
    short = counts.min(initial=k) < k
    padded = np.concatenate([w.hash, np.zeros(k, np.uint64)]) if n else np.zeros(k, np.uint64)
    for i in range(k):
        part = padded[at + i] * _COEF[i]
        if short:
            part = np.where(at + i < last, part, np.uint64(0x51ED270B7A1F3C25))
        out += part
    return doc, at - first_word[doc], mix(out, 2)


def distinct(doc: np.ndarray, hashed: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (document, hash) pairs sorted by document, and how many each document has.

    Document and 52 bits of the hash share one integer, which sorts fast (chunks have at most 4000 documents)."""
    key = (doc.astype(np.uint64) << np.uint64(52)) | (hashed >> np.uint64(12))
    key.sort()
    if len(key):
        keep = np.ones(len(key), bool)
        np.not_equal(key[1:], key[:-1], out=keep[1:])
        key = key[keep]
    owner = (key >> np.uint64(52)).astype(np.int64)
    return owner, key & np.uint64((1 << 52) - 1), np.bincount(owner, minlength=n_docs)


def segment_sum(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sums over consecutive segments; an empty segment has 0."""
    out = np.zeros(len(counts), values.dtype)
    full = counts > 0
    if full.any():
        out[full] = np.add.reduceat(values, (np.cumsum(counts) - counts)[full])
    return out
