"""Word shingles of a batch of UTF-8 texts as hashed sets, in array operations."""

from __future__ import annotations

import numpy as np

from .common import mix64, powers

_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_STEP = np.uint64(0xA0761D6478BD642F)


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words (runs of bytes but space and 09-0D, A-Z lower-cased) of all texts, and the word offsets of each text."""
    if not len(data):
        return np.empty(0, np.uint64), np.zeros(len(offsets), np.int64)
    inside = ~_SPACE[data]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    edges = offsets[(offsets > 0) & (offsets < len(data))]
    first[edges] |= inside[edges]
    last[edges - 1] |= inside[edges - 1]
    s, e = np.flatnonzero(first), np.flatnonzero(last)
    total = np.cumsum((_FOLD[data].astype(np.uint64) + np.uint64(1)) * powers(len(data)))
    before = np.where(s > 0, total[s - 1], np.uint64(0))
    return mix64((total[e] - before) * powers(len(data), inverse=True)[s]), np.searchsorted(s, offsets)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed k-word shingles, ascending within each text, and their offsets by text.

    A text with fewer words has its whole sequence as its one shingle; one without words has none.
    """
    w, at = words(data, offsets)
    counts = np.diff(at)
    owner = np.repeat(np.arange(len(counts)), counts)
    rest = at[1:][owner] - np.arange(len(w))  # words from here to the end of the text
    h, keep = w.copy(), rest >= k
    for j in range(1, k):
        live = np.flatnonzero(rest > j)
        h[live] = mix64(h[live] * _STEP + w[live + j])
    short = (counts < k) & (counts > 0)
    keep[at[:-1][short]] = True
    h = mix64(h + np.minimum(rest, k).astype(np.uint64) * _STEP)[keep]
    owner = owner[keep]
    order = np.lexsort((h, owner))
    h, owner = h[order], owner[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    h, owner = h[new], owner[new]
    return h, np.searchsorted(owner, np.arange(len(counts) + 1))


def set_names(h: np.ndarray, at: np.ndarray) -> np.ndarray:
    """A 63-bit name of each set, the same for equal sets; 0 for the empty set."""
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix64(h * _STEP + np.uint64(1)))])
    size = np.diff(at).astype(np.uint64)
    name = mix64((total[at[1:]] - total[at[:-1]]) ^ mix64(size * _STEP)) >> np.uint64(1)
    return np.where(size > 0, np.maximum(name, np.uint64(1)), np.uint64(0)).astype(np.int64)
