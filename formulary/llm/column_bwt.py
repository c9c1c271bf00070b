"""Column-wise construction of the Burrows-Wheeler transform and common prefixes of a collection of strings.

Strings are inserted from their last symbol to their first: each round adds one suffix of every string that still
has symbols, at the place that its symbol and the place of the suffix before it determine, and updates the
transform and the array of longest common prefixes. Both arrays are kept in files that a round reads and writes
from front to back; ends of strings sort first and never match each other.
"""

from __future__ import annotations

import os
import tempfile

import numpy as np

#: In the transform: the suffix is a whole string, nothing comes before it. Real symbols are 1 to 65535.
DONE = 0


class SequentialArray:
    """An array in two files that take turns: a round reads one from the front and writes the other from the front.

    Both stay open and only grow, so a round costs no file creation, renaming or truncation.
    """

    def __init__(self, folder: str, name: str, dtype):
        self.files = [open(os.path.join(folder, f"{name}{i}"), "w+b") for i in range(2)]  # noqa: SIM115
        self.dtype, self.turn, self.length = np.dtype(dtype), 0, 0

    def write(self, values: np.ndarray) -> None:
        self.turn, self.length = 1 - self.turn, len(values)
        f = self.files[self.turn]
        f.seek(0)
        f.write(np.ascontiguousarray(values, self.dtype).data)
        f.flush()

    def read(self) -> np.ndarray:
        f, out = self.files[self.turn], np.empty(self.length, self.dtype)
        f.seek(0)
        f.readinto(out.data)
        return out

    def close(self) -> None:
        for f in self.files:
            f.close()


def _order(symbols: np.ndarray) -> np.ndarray:
    """Stable order of symbols. Most fit a byte, whose sort takes one pass; the few others come last and are sorted then."""
    order = np.argsort(np.minimum(symbols, 255).astype(np.uint8), kind="stable")
    wide = np.count_nonzero(symbols >= 255)
    if wide:
        last = order[len(order) - wide :]
        order[len(order) - wide :] = last[np.argsort(symbols[last], kind="stable")]
    return order


def _spread(old: np.ndarray, at: np.ndarray, new: np.ndarray) -> np.ndarray:
    """old with new values inserted so that they stand at the places `at` (ascending) of the result."""
    out = np.empty(len(old) + len(new), old.dtype)
    stays = np.ones(len(out), bool)
    stays[at] = False
    out[stays] = old
    out[at] = new
    return out


def _least(lcp: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Minimum of lcp[left + 1 .. right] for each pair of places left < right."""
    if not len(left):
        return np.empty(0, lcp.dtype)
    bounds = np.empty(2 * len(left), np.int64)
    bounds[::2], bounds[1::2] = left + 1, right + 1
    order = np.argsort(bounds[::2], kind="stable")
    bounds = np.stack([bounds[::2][order], bounds[1::2][order]], axis=1).ravel()
    padded = np.append(lcp, lcp.dtype.type(0))
    out = np.empty(len(left), lcp.dtype)
    out[order] = np.minimum.reduceat(padded, bounds)[::2]
    return out


def build(strings: list[np.ndarray], cap: int, folder: str | None = None) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """(transform, common prefixes, places) of a collection.

    transform[i] is the symbol before suffix i in sorted order (DONE at a string's start); common prefixes are
    capped at `cap`; places[k][o] is the place of the suffix of string k that starts at its symbol o (o = length:
    the empty suffix). Strings are arrays of symbols from 1 to 65535.
    """
    with tempfile.TemporaryDirectory(prefix="bwt-", dir=folder) as tmp:
        bwt_file, lcp_file = SequentialArray(tmp, "bwt", np.uint16), SequentialArray(tmp, "lcp", np.int16)
        m = len(strings)
        length = np.array([len(s) for s in strings], np.int64)
        flat = np.concatenate([np.asarray(s, np.uint16) for s in strings]) if m else np.empty(0, np.uint16)
        begin = np.concatenate([[0], np.cumsum(length)])[:-1] if m else np.empty(0, np.int64)
        before = lambda k, o: np.where(o > 0, flat[np.minimum(begin[k] + np.maximum(o, 1) - 1, max(len(flat) - 1, 0))], DONE) if len(flat) else np.zeros(len(k), np.uint16)

        at = np.arange(m)  # where each string's latest suffix stands
        bwt_file.write(before(np.arange(m), length).astype(np.uint16))
        lcp_file.write(np.zeros(m, np.int16))
        history: list[tuple[np.ndarray, np.ndarray]] = []  # per round: the strings and the places that they took then
        done = 0
        while True:
            live = np.flatnonzero(length > done)
            bwt, lcp = bwt_file.read(), lcp_file.read()
            if not len(live):
                break
            order = _order(bwt)[np.count_nonzero(bwt == DONE) :]
            rank = np.empty(len(bwt), np.int32)  # half the bytes: these arrays go through the caches in every round
            rank[order] = np.arange(len(order), dtype=np.int32)
            live = live[np.argsort(rank[at[live]], kind="stable")]
            k = rank[at[live]].astype(np.int64)
            place = m + k  # empty suffixes come first, then the extension of each place in order
            own = at[live]
            head = np.zeros(len(live), np.int16)
            prev = order[np.maximum(k - 1, 0)]
            same = (k > 0) & (bwt[prev] == bwt[own])
            head[same] = np.minimum(_least(lcp, prev[same], own[same]) + 1, cap)
            tail = np.zeros(len(live), np.int16)
            follows = k + 1 < len(order)
            nxt = order[np.minimum(k + 1, len(order) - 1)]
            same = follows & (bwt[nxt] == bwt[own])
            tail[same] = np.minimum(_least(lcp, own[same], nxt[same]) + 1, cap)
            left = length[live] - done - 1
            bwt = _spread(bwt, place, before(live, left).astype(np.uint16))
            lcp = _spread(lcp, place, head)
            lcp[(place + 1)[follows]] = tail[follows]
            bwt_file.write(bwt)
            lcp_file.write(lcp)
            done += 1
            history.append((live, place))
            at[live] = place
            rest = np.flatnonzero(length < done)  # finished strings move with what was inserted before them
            if len(rest):
                # the j-th inserted suffix stands at place[j]; an older one moves by the number of those at or before its new place
                at[rest] = _moved(at[rest], place)
        # replay the insertions backwards: where did each round's suffixes end?
        bwt_file.close()
        lcp_file.close()
        table = np.zeros((m, int(length.max(initial=0)) + 1), np.int64)
        final = np.arange(len(bwt), dtype=np.int32)
        for step in range(len(history) - 1, -1, -1):
            who, where = history[step]
            table[who, length[who] - step - 1] = final[where]
            stays = np.ones(len(final), bool)
            stays[where] = False
            final = final[stays]
        table[np.arange(m), length] = final
        return bwt, lcp, [table[s, : n + 1] for s, n in enumerate(length)]


def _moved(old: np.ndarray, inserted: np.ndarray) -> np.ndarray:
    """New places of old ones after insertions that stand at `inserted` (ascending) in the new order."""
    gap = inserted - np.arange(len(inserted))  # number of old items before each inserted one
    return old + np.searchsorted(gap, old, "right")


def repeated_windows(strings: list[np.ndarray], width: int, folder: str | None = None) -> list[np.ndarray]:
    """For each string, which of its windows of `width` symbols occur at another place in the collection."""
    _, lcp, places = build(strings, width, folder)
    shared = np.append(lcp, np.int16(0))
    hit = np.maximum(shared[:-1], shared[1:]) >= width
    return [hit[p[: max(0, len(p) - width)]] for p in places]
