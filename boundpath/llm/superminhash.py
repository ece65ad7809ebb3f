"""SuperMinHash signatures.

Every element draws a random order of the signature's places and offers place p, reached at step j, the value
j + u with u uniform in [0, 1).  A place keeps the least offer.  The steps of all elements go round by round; a
document is finished, and its elements stop early, as soon as all its places have an offer, because later steps
only offer more.  Values are held as 7 bits of j and 25 bits of u.
"""

from __future__ import annotations

import numpy as np

from boundpath.llm.textkernel import mix

_U = 25


def _step(seed: np.ndarray, j: int, places: int) -> tuple[np.ndarray, np.ndarray]:
    x = mix(seed, 101 + j)
    at = j + ((x >> np.uint64(32)) * np.uint64(places - j) >> np.uint64(32)).astype(np.int64)
    return at, (np.uint32(j) << np.uint32(_U)) | (x & np.uint64((1 << _U) - 1)).astype(np.uint32)


def signatures(owner: np.ndarray, elements: np.ndarray, n_docs: int, places: int = 128, block: int = 200_000) -> np.ndarray:
    """One row of ``places`` values for each document; owner is sorted.  Rows of documents without elements are full
    of the largest value."""
    out = np.full((n_docs, places), 0xFFFFFFFF, np.uint32)
    if not len(owner):
        return out
    flat = out.reshape(-1)
    at0, value = _step(elements, 0, places)
    np.minimum.at(flat, owner * places + at0, value)
    has = np.bincount(owner, minlength=n_docs) > 0
    open_docs = has & (out == 0xFFFFFFFF).any(axis=1)
    picked = np.flatnonzero(open_docs[owner])
    for lo in _cuts(owner[picked], block):
        rows = picked[lo]
        own, seed, first = owner[rows], elements[rows], at0[rows]
        order = np.tile(np.arange(places, dtype=np.uint8), (len(rows), 1))
        line = np.arange(len(rows))
        order[line, first] = 0
        for j in range(1, places):
            at, value = _step(seed, j, places)
            place = order[line, at].astype(np.int64)
            order[line, at] = order[line, j]
            np.minimum.at(flat, own * places + place, value)
            docs = np.unique(own)
            docs = docs[(out[docs] == 0xFFFFFFFF).any(axis=1)]
            if not len(docs):
                break
            stay = np.zeros(n_docs, bool)
            stay[docs] = True
            stay = stay[own]
            if stay.sum() < 0.7 * len(own):
                own, seed, order = own[stay], seed[stay], order[stay]
                line = np.arange(len(own))
    return out


def _cuts(own: np.ndarray, block: int):
    """Slices of about ``block`` elements that don't split a document (one document may exceed it)."""
    lo, n = 0, len(own)
    while lo < n:
        hi = min(n, lo + block)
        if hi < n:
            left = int(np.searchsorted(own, own[hi], "left"))
            hi = left if left > lo else int(np.searchsorted(own, own[hi], "right"))
        yield slice(lo, hi)
        lo = hi


def band_keys(signature: np.ndarray, rows: int) -> np.ndarray:
    """A 64-bit key for each band of ``rows`` places; the band's number is part of the key."""
    n, places = signature.shape
    bands = places // rows
    part = signature[:, : bands * rows].reshape(n, bands, rows).astype(np.uint64)
    key = np.broadcast_to(np.arange(bands, dtype=np.uint64), (n, bands)).copy()
    for i in range(rows):
        key = mix(key * np.uint64(0x9FB21C651E98DF25) + part[:, :, i], 7 + i)
    return key.view(np.int64)
