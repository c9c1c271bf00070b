"""Shape features of whole texts: rates of characters, words, repeats and lines, in array operations over a batch."""

from __future__ import annotations

import numpy as np

from .common import byte_slabs
from .shingles import words

_CLASS = np.zeros(256, np.int64)
for _i, _chars in enumerate([b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"!", b"?", b"|", b"#$%&*", b"@<>{}[]()=+/\\^~`_", b".,;:", b"\"'-", b"\n"], 1):
    _CLASS[list(_chars)] = _i
_CLASS[128:] = 11
_SPACE_OR_END = np.zeros(256, bool)
_SPACE_OR_END[[0x20, *range(0x09, 0x0E)]] = True
_N = 12
NAMES = ["log_bytes", "log_words", "word_length", "upper", "digits", "bang", "question", "pipe", "symbols", "brackets", "stops", "quotes", "newlines", "high_bytes", "bang_words", "symbol_words", "pipe_words", "distinct_words", "same_next", "top_word", "same_lines"]


def _per_row(values: np.ndarray, at: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values)])
    return total[at[1:]] - total[at[:-1]]


def shape(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of features for each text; empty texts have zeros."""
    n = len(offsets) - 1
    out = np.zeros((n, len(NAMES)))
    for a, b in byte_slabs(offsets, 1 << 20):
        out[a:b] = _shape(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
    return out


def _shape(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    n, size = len(offsets) - 1, np.diff(offsets)
    rows = np.repeat(np.arange(n), size)
    kind = _CLASS[data]
    counts = np.bincount(rows * _N + kind, minlength=n * _N).reshape(n, _N).astype(float)
    w, at = words(data, offsets)
    n_words = np.diff(at)
    owner = np.repeat(np.arange(n), n_words)
    # the character before a blank or the end is a word's last one
    blank = _SPACE_OR_END[data]
    last = ~blank
    last[:-1] &= blank[1:]
    inner = offsets[1:-1]
    inner = inner[(inner > 0) & (inner < len(data))]
    if len(data):
        last[inner - 1] |= ~blank[inner - 1]
        last[-1] = not blank[-1]
    ends = np.bincount(rows[last] * _N + kind[last], minlength=n * _N).reshape(n, _N).astype(float)
    order = np.lexsort((w, owner))
    sw, so = w[order], owner[order]
    new = np.ones(len(sw), bool)
    new[1:] = (sw[1:] != sw[:-1]) | (so[1:] != so[:-1])
    distinct = np.bincount(so[new], minlength=n)
    first = np.flatnonzero(new)
    runs = np.diff(np.append(first, len(sw)))
    top = np.zeros(n)
    np.maximum.at(top, so[first], runs)
    same_next = np.zeros(len(w), bool)
    same_next[1:] = (w[1:] == w[:-1]) & (owner[1:] == owner[:-1])
    repeats = np.bincount(owner[same_next], minlength=n)
    # lines by length and first word: cheap stand-in for equal lines
    newline = np.flatnonzero(data == 10)
    starts = np.unique(np.concatenate([offsets[:-1][size > 0], newline + 1]))
    starts = starts[starts < len(data)]
    ids = np.searchsorted(offsets, starts, "right") - 1
    length = np.diff(np.append(starts, len(data)))
    code = np.stack([ids, length, kind[starts] if len(starts) else starts, data[starts].astype(np.int64) if len(starts) else starts], axis=1)
    lines = np.bincount(ids, minlength=n)
    kinds = np.unique(code, axis=0) if len(code) else code
    unlike = np.bincount(kinds[:, 0].astype(np.int64), minlength=n) if len(kinds) else np.zeros(n)
    per_byte, per_word = np.maximum(size, 1), np.maximum(n_words, 1)
    cols = [np.log1p(size), np.log1p(n_words), size / per_word, *(counts[:, j] / per_byte for j in range(1, _N)), ends[:, 3] / per_word, ends[:, 6] / per_word, ends[:, 5] / per_word, distinct / per_word, repeats / per_word, top / per_word, 1 - unlike / np.maximum(lines, 1)]
    out = np.stack(cols, axis=1)
    out[size == 0] = 0
    return out
