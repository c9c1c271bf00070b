"""Removal of long repeated byte strings through a suffix structure built column by column.

A plain column-wise build over whole texts makes one pass over the whole collection for every byte of the longest
text. Here the collection is first cut into short strings around content-defined anchors, so that a build over
many of them needs few rounds and independent builds can run in parallel:

1. Anchors. Of each window of `width` bytes, the 32-byte gram with the least hash is its anchor, so equal windows
   have equal anchors at equal places. An anchor that occurs once in the corpus has no repeated window.
2. Cells. The windows of a repeated anchor are divided by their distance to it into cells of 64. All windows of a
   cell share a core of width - 63 bytes; equal windows have equal anchors, cells and cores. Cells are shuffled as
   hashes with the number of texts behind them; cells with equal flanks, or of texts that occur more than once, are
   covered as a whole.
3. Columns. Cells with the same core and different flanks become strings: left flank, core (one symbol), right
   flank. The column-wise build gives the common prefixes of all suffixes, and a window is repeated where one with
   a neighbour covers it.
4. Cores with more different flanks than a build takes are resolved window by window: equal 128-bit hashes of the
   windows, counted and joined back. Nothing is capped or dropped.

Intervals of repeated windows then meet their text again, which is cut and hashed.

Two widths. Passages (some fifty words, 240 bytes) can be found beside the windows of `width`: a repeated window of 400
bytes lies whole in a run that repeated strings of 240 bytes cover. So the passages are found first in all texts, and the
wider windows only in those runs, each of which is a short text of its own.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .column_bwt import repeated_windows
from .common import byte_slabs, discard, materialise, membership_bits, mix64, powers, utf8_view

WIDTH = 400
#: A passage of some fifty words.
PASSAGE = 240
GRAM = 32
CELL = 64
#: Strings of one build, and the most different flanks of a core that go into one build.
BUILD = 1500
FLANKS = 500
_SLAB = 1 << 20
#: Windows that are hashed at once.
_STRETCH = 1 << 15
_WIDEST = 1 << 12
_POWERS = powers(_STRETCH + _WIDEST), powers(_STRETCH + _WIDEST, inverse=True)
_POSITION = np.uint64((1 << 22) - 1)


def anchors(data: np.ndarray, offsets: np.ndarray, width: int = WIDTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, anchor hash, anchor place, first window, last window) of every run of windows with one anchor.

    Places are relative to the text. Short texts are taken together and long ones in stretches of windows, so that the
    passes over their bytes stay in a core's cache and any text length does.
    """
    sizes = np.diff(offsets)
    long_enough = np.flatnonzero(sizes >= width)
    out: list[list[np.ndarray]] = [[], [], [], [], []]
    ahead, back = _POWERS if width <= _WIDEST else (powers(_STRETCH + width), powers(_STRETCH + width, inverse=True))
    k = 0
    while k < len(long_enough):
        begin = int(offsets[long_enough[k]])
        # texts k to last - 1, with what lies between them, or text k alone
        last = max(k + 1, int(np.searchsorted(offsets[long_enough + 1], begin + _STRETCH, "right")))
        own = long_enough[k:last]
        end, k = int(offsets[own[-1] + 1]), last
        for s in range(begin, end - width + 1, _STRETCH):
            stop = min(s + _STRETCH, end - width + 1)  # window starts s .. stop - 1
            part = data[s : stop + width - 1]
            n = len(part) - gram + 1
            total = np.zeros(len(part) + 1, np.uint64)
            np.cumsum((part.astype(np.uint64) + np.uint64(1)) * ahead[: len(part)], out=total[1:])
            coded = mix64((total[gram:] - total[:-gram]) * back[:n])
            h = coded.copy()
            coded &= ~_POSITION
            coded |= np.arange(n, dtype=np.uint64)  # least hash, then leftmost
            at = (_sliding_least(coded, width - gram + 1) & _POSITION).astype(np.int64)
            if len(own) == 1:
                first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
                final = np.append(first[1:], len(at)) - 1
                text = np.full(len(first), own[0])
            else:
                starts, stops = offsets[own] - s, offsets[own + 1] - s - width  # of each text: its first and its last window
                fresh = np.concatenate([[True], at[1:] != at[:-1]])
                fresh[starts] = True
                fresh[stops[:-1] + 1] = True  # what follows a text's last window is none, until the next text starts
                first = np.flatnonzero(fresh)
                final = np.append(first[1:], len(at)) - 1
                mine = np.searchsorted(starts, first, "right") - 1
                inside = first <= stops[mine]
                first, final, mine = first[inside], final[inside], mine[inside]
                text = own[mine]
            shift, a = s - offsets[text], at[first]
            for old, new in zip(out, (text, h[a], a + shift, first + shift, final + shift)):
                old.append(new)
    return tuple(np.concatenate(x) if x else np.empty(0, np.uint64 if j == 1 else np.int64) for j, x in enumerate(out))


def _sliding_least(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w consecutive values: running minima of blocks of w from both sides."""
    n = len(x)
    blocks = np.full(-(-n // w) * w, np.iinfo(np.uint64).max, np.uint64)
    blocks[:n] = x
    blocks = blocks.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - w + 1], ahead[w - 1 : n])


def _digest(text):
    return hashlib.blake2b(text, digest_size=16).digest()


def _texts(batch: pa.RecordBatch, column: int) -> list[memoryview]:
    data, offsets = utf8_view(batch.column(column))
    view = memoryview(np.ascontiguousarray(data)).cast("B") if len(data) else memoryview(b"")
    return [view[a:b] for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]


def _named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = _texts(batch, 1)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([_digest(t) for t in texts], pa.binary())], ["doc_id", "n_bytes", "digest"])


def _anchored(width: int):
    """Rows (anchor, digest, place): the anchors of every text, a text once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in batches:
            names = [_digest(t) for t in _texts(batch, 0)]
            data, offsets = utf8_view(batch.column(0))
            for a, b in byte_slabs(offsets, _SLAB):
                own, h, at, _, _ = anchors(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], width)
                fresh = np.array([x not in seen for x in names[a:b]], bool)
                seen.update(names[a:b])
                keep = fresh[own] if len(own) else np.empty(0, bool)
                own, h, at = own[keep], h[keep], at[keep]
                if len(h):
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array([names[a + i] for i in own.tolist()], pa.binary()), pa.array(at.astype(np.int32))], ["anchor", "digest", "place"])

    return run


def _bits(rows: DataFrame) -> np.ndarray:
    """A bit set of fixed size (2 MB) with a bit of every digest of rows: it spares most other texts a shuffle."""
    start = F.conv(F.hex(F.substring("digest", 1, 4)), 16, 10).cast("long")
    return membership_bits(rows.select(start.alias("node")))


def _with_name(bits: np.ndarray):
    """Rows (digest, text as bytes) of the texts that the bit set lets through, a text once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in batches:
            names = [_digest(t) for t in _texts(batch, 0)]
            start = np.frombuffer(b"".join(n[:4] for n in names), ">u4").astype(np.int64)
            let = (bits[(start >> 6) % len(bits)] >> (start % 64).astype(np.uint64)) & np.uint64(1) > 0
            fresh = [i for i in np.flatnonzero(let).tolist() if not (names[i] in seen or seen.add(names[i]))]
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in fresh], pa.binary()), batch.column(0).take(pa.array(fresh, pa.int64()))], ["digest", "text"])

    return run


def _celled(width: int, cell: int):
    """(digest, n, text, places of repeated anchors) -> rows of cells as hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h64, mask = xxhash.xxh3_64_intdigest, (1 << 64) - 1
        for batch in batches:
            names, counts, texts, places = batch.column(0).to_pylist(), batch.column(1).to_numpy(), _texts(batch, 2), batch.column(3).to_pylist()
            data, offsets = utf8_view(batch.column(2))
            for a, b in byte_slabs(offsets, _SLAB):
                own, h, at, first, last = anchors(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], width)
                wanted = [set(places[i]) for i in range(a, b)]
                keep = np.fromiter((p in wanted[i] for i, p in zip(own.tolist(), at.tolist())), bool, len(own))
                own, h, at, first, last = own[keep], h[keep], at[keep], first[keep], last[keep]
                # a row for each cell of each run of windows: its number, its first window and the last one that it can have
                low, high = (at - last) // cell, (at - first) // cell
                times = high - low + 1
                run_of = np.repeat(np.arange(len(own)), times)
                j = high[run_of] - (np.arange(len(run_of)) - np.repeat(np.cumsum(times) - times, times))
                end = at[run_of] - j * cell
                s, e = np.maximum(first[run_of], end - cell + 1), np.minimum(last[run_of], end)
                x = end - cell + 1
                owner = (own + a)[run_of]
                cores, flanks = np.empty(len(s), np.uint64), np.empty(len(s), np.uint64)
                for k, (i, hv, jv, xv, sv, ev, d) in enumerate(zip(owner.tolist(), h[run_of].tolist(), j.tolist(), x.tolist(), s.tolist(), (e + width).tolist(), (at[run_of] - s).tolist())):
                    t = texts[i]
                    cores[k] = h64(t[xv + cell - 1 : xv + width], hv + jv & mask)
                    flanks[k] = h64(t[sv:ev], d)
                if len(s):
                    yield pa.RecordBatch.from_arrays([pa.array(cores.view(np.int64)), pa.array(flanks.view(np.int64)), pa.array(counts[owner]), pa.array([names[i] for i in owner.tolist()], pa.binary()), *(pa.array(c.astype(np.int32)) for c in (s, e - s + 1, end))], ["core", "flanks", "n", "digest", "first", "windows", "last_of_cell"])

    return run


def _flanked(width: int, cell: int, flanks: int):
    """(digest, text, cells) -> strings of cells for the builds, or hashes of windows where a core has too many flanks."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for name, text, wanted in zip(f["digest"], f["text"], f["wanted"]):
                raw = bytes(text)
                for c in wanted:
                    s, n, last = c["first"], c["windows"], c["last_of_cell"]
                    if c["variants"] <= flanks:
                        core_end = last - cell + 1 + width
                        rows.append((c["core"], name, s, n, last - s, raw[s:last] + raw[core_end : s + n - 1 + width], None))
                    else:
                        seed = c["core"].to_bytes(8, "little", signed=True)
                        rows += [(c["core"], name, w, 1, last - w, None, hashlib.blake2b(raw[w : w + width], digest_size=16, key=seed + (last - w).to_bytes(2, "little")).digest()) for w in range(s, s + n)]
            yield pd.DataFrame(rows, columns=["core", "digest", "first", "windows", "before", "bytes", "window"])

    return run


def _built(cell: int, build: int):
    """Strings in runs of one core -> (digest, first, last): runs of repeated windows."""

    def settle(rows: list[tuple]) -> list[tuple]:
        symbols: dict[int, int] = {}
        strings = []
        for core, _, _, _, before, raw in rows:
            symbol = symbols.setdefault(core, 257 + len(symbols))
            b = np.frombuffer(raw, np.uint8).astype(np.uint16) + 1
            strings.append(np.concatenate([b[:before], [np.uint16(symbol)], b[before:]]).astype(np.uint16))
        found = []
        for (_, name, first, windows, _, _), hit in zip(rows, repeated_windows(strings, cell)):
            hit = np.flatnonzero(hit[:windows])
            if len(hit):
                cuts = np.flatnonzero(np.diff(hit) > 1)
                for x, y in zip(np.concatenate([hit[:1], hit[cuts + 1]]).tolist(), np.concatenate([hit[cuts], hit[-1:]]).tolist()):
                    found.append((name, first + x, first + y))
        return found

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows: list[tuple] = []
        for f in frames:
            for row in zip(f["core"].tolist(), f["digest"], f["first"].tolist(), f["windows"].tolist(), f["before"].tolist(), f["bytes"]):
                if len(rows) >= build and row[0] != rows[-1][0]:
                    yield pd.DataFrame(settle(rows), columns=["digest", "first", "last"])
                    rows = []
                rows.append(row)
        if rows:
            yield pd.DataFrame(settle(rows), columns=["digest", "first", "last"])

    return run


def repeated_intervals(texts: DataFrame, named: DataFrame, width: int = WIDTH, cell: int = CELL, build: int = BUILD, flanks: int = FLANKS) -> DataFrame:
    """Rows (digest, spans): byte ranges of each text that repeated windows cover, unordered, for texts that have any.

    texts: one column text (binary); named: (digest, n) with the number of rows of each text.
    """
    found = materialise(texts.mapInArrow(_anchored(width), "anchor long, digest binary, place int"), "suffix-anchors")
    again = found.groupBy("anchor").agg(F.min(F.struct("digest", "place")).alias("a"), F.max(F.struct("digest", "place")).alias("b"))
    again = materialise(again.where("a <> b").select("anchor"), "suffix-repeated")
    live = found.join(again, "anchor").groupBy("digest").agg(F.collect_set("place").alias("places"))
    live = materialise(live.join(named, "digest").select("digest", "n", "places"), "suffix-live")
    discard(found)
    rows = texts.mapInArrow(_with_name(_bits(live)), _HOLDERS).join(live, "digest").select("digest", "n", "text", "places").mapInArrow(_celled(width, cell), "core long, flanks long, n long, digest binary, first int, windows int, last_of_cell int")
    rows = materialise(rows, "suffix-cells")
    kinds = rows.groupBy("core", "flanks").agg(F.sum("n").alias("n"), F.min(F.struct("digest", "first", "windows", "last_of_cell")).alias("r"))
    kinds = materialise(kinds.select("core", "flanks", (F.col("n") > 1).alias("whole"), "r"), "suffix-kinds")
    whole = rows.join(kinds.where("whole").select("core", "flanks"), ["core", "flanks"]).select("digest", "first", (F.col("first") + F.col("windows") - 1).alias("last"))
    whole = materialise(whole, "suffix-whole")
    mixed = materialise(kinds.groupBy("core").agg(F.count("*").alias("variants")).where("variants > 1"), "suffix-mixed")
    wanted = kinds.join(mixed, "core").select("r.digest", F.struct("core", "variants", "r.first", "r.windows", "r.last_of_cell").alias("c")).groupBy("digest").agg(F.collect_list("c").alias("wanted"))
    wanted = materialise(wanted, "suffix-wanted")
    strings = texts.mapInArrow(_with_name(_bits(wanted)), _HOLDERS).join(wanted, "digest").select("digest", "text", "wanted").mapInPandas(_flanked(width, cell, flanks), "core long, digest binary, first int, windows int, before int, bytes binary, window binary")
    strings = materialise(strings, "suffix-strings")
    flanked = strings.where("bytes IS NOT NULL").drop("window")
    tasks = max(1, -(-flanked.count() // (2 * build)))  # a build costs seconds, not bytes: no coalescing by size
    dealt = flanked.repartition(tasks, "core").sortWithinPartitions("core", "digest", "first")
    built = dealt.mapInPandas(_built(cell, build), "digest binary, first int, last int")
    single = strings.where("window IS NOT NULL").select("window", "digest", "first")
    twice = single.groupBy("window").agg(F.min(F.struct("digest", "first")).alias("a"), F.max(F.struct("digest", "first")).alias("b"))
    twice = materialise(twice.where("a <> b").select("window"), "suffix-windows")
    alone = single.join(twice, "window").select("digest", "first", F.col("first").alias("last"))
    spans = whole.unionByName(built).unionByName(alone)
    spans = spans.groupBy("digest").agg(F.collect_set(F.struct("first", (F.col("last") + width).alias("end"))).alias("spans"))
    spans = materialise(spans, "suffix-spans")
    discard(again, live, rows, kinds, whole, mixed, wanted, strings, twice)
    return spans


_HOLDERS = "digest binary, text binary"


def _pieces(width: int):
    """(digest, n, text, spans) -> the runs of at least width bytes: digest, n, at (place in the text), piece (digest of the run), text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, n, text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), _texts(batch, 2), batch.column(3).to_pylist()):
                runs = [(a, bytes(text[a:b])) for a, b in merged(spans, False, len(text), width) if b - a >= width]
                if runs:
                    yield pa.RecordBatch.from_arrays([pa.array([name] * len(runs), pa.binary()), pa.array([n] * len(runs), pa.int64()), pa.array([a for a, _ in runs], pa.int64()), pa.array([_digest(r) for _, r in runs], pa.binary()), pa.array([r for _, r in runs], pa.binary())], ["digest", "n", "at", "piece", "text"])

    return run


def intervals_within(texts: DataFrame, named: DataFrame, passages: DataFrame, width: int, **tuning) -> DataFrame:
    """repeated_intervals for a width above that of the given passages: only the runs that these cover are searched."""
    held = texts.mapInArrow(_with_name(_bits(passages)), _HOLDERS).join(passages.join(named, "digest"), "digest")
    pieces = held.select("digest", "n", "text", "spans").mapInArrow(_pieces(width), "digest binary, n long, at long, piece binary, text binary")
    pieces = materialise(pieces.dropDuplicates(["digest", "at"]), "suffix-pieces")
    counts = materialise(pieces.groupBy("piece").agg(F.sum("n").alias("n"), F.first(F.octet_length("text")).alias("size")), "suffix-counts")
    found = repeated_intervals(pieces.select("text"), counts.select(F.col("piece").alias("digest"), "n"), width, **tuning)
    whole = F.array(F.struct(F.lit(0).alias("first"), F.col("size").alias("end")))
    own = counts.join(found.withColumnRenamed("digest", "piece"), "piece", "left").select("piece", F.when(F.col("n") > 1, whole).otherwise(F.col("spans")).alias("spans")).where("spans IS NOT NULL")
    placed = pieces.select("digest", "at", "piece").join(own, "piece").select("digest", F.explode("spans").alias("s"), "at")
    placed = placed.groupBy("digest").agg(F.collect_set(F.struct((F.col("s.first") + F.col("at")).cast("int").alias("first"), (F.col("s.end") + F.col("at")).cast("int").alias("end"))).alias("spans"))
    placed = materialise(placed, "suffix-spans")
    discard(pieces, counts)
    return placed


def merged(spans: list, repeated: bool, n: int, width: int) -> list[tuple[int, int]]:
    """Maximal runs of removed bytes. A text that occurs more than once and is long enough goes as a whole."""
    if repeated and n >= width:
        return [(0, n)]
    out: list[list[int]] = []
    for a, b in sorted((s["first"], s["end"]) for s in spans) if spans is not None else []:
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def merged_rows(spans: pa.Array, repeated: np.ndarray, sizes: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """merged() of every row of a column of spans: first and end of the runs, row after row, and how many each row has."""
    whole = repeated & (sizes >= width)
    count = pc.fill_null(pc.list_value_length(spans), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat, owner = spans.flatten(), np.repeat(np.arange(len(count)), count)
    a, b = (pc.struct_field(flat, c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("first", "end"))
    on = ~whole[owner]
    owner, a, b = np.append(owner[on], np.flatnonzero(whole)), np.append(a[on], np.zeros(whole.sum(), np.int64)), np.append(b[on], sizes[whole])
    order = np.lexsort((a, owner))
    owner, a, b = owner[order], a[order], b[order]
    reach = np.maximum.accumulate((owner << 40) + b)  # a row's places come after those of the row before
    new = np.ones(len(a), bool)
    new[1:] = (owner[1:] << 40) + a[1:] > reach[:-1]
    last = np.append(np.flatnonzero(new)[1:], len(a)) - 1
    return a[new], reach[last[: new.sum()]] - (owner[new] << 40), np.bincount(owner[new], minlength=len(count))


def run_lists(first: np.ndarray, end: np.ndarray, many: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), pa.StructArray.from_arrays([pa.array(first), pa.array(end)], ["first", "end"]))


def _inside(text: memoryview, a: int, b: int) -> tuple[int, int]:
    """The part of a run that starts and ends between characters."""
    while a < b and text[a] & 0xC0 == 0x80:
        a += 1
    while a < b < len(text) and text[b] & 0xC0 == 0x80:
        b -= 1
    return a, b


def _named_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([_digest(t) for t in _texts(batch, batch.num_columns - 1)], pa.binary())], [*batch.schema.names, "_digest"])


def remove_repeats(docs: DataFrame, text_col: str = "text", width: int = WIDTH, whole_characters: bool = False, passage: int | None = None, **tuning) -> DataFrame:
    """docs with columns _kept (the text without its repeated bytes, binary), _removed (runs of bytes) and _n_bytes.

    Every byte that a string of `width` bytes covers which also starts elsewhere (same text included, overlaps
    too) goes; strings are judged on the input. Null and empty texts stay empty; repeated rows are repeats of each
    other. whole_characters: leave the bytes of a character that a run would cut, so that what stays is UTF-8.
    passage: a shorter width whose runs are reported as _passages, and not removed. An empty table gives an empty
    result. Columns keep their names and values, whatever they are called (names starting with _ are reserved).
    """
    if passage is not None and passage >= width:
        raise ValueError("passages are shorter than the width that is removed")
    text = F.col(text_col).cast("string").cast("binary").alias("text")
    texts = docs.select(text)
    named = materialise(docs.select(F.lit(0).cast("long").alias("doc_id"), text).mapInArrow(_named, "doc_id long, n_bytes long, digest binary").groupBy("digest").agg(F.count("*").alias("n")), "suffix-names")
    short = repeated_intervals(texts, named, passage or width, **tuning)
    spans = intervals_within(texts, named, short, width, **tuning) if passage else short
    marks = named.where("n > 1").join(spans, "digest", "full").select("digest", F.coalesce("n", F.lit(1)).alias("_n"), F.col("spans").alias("_spans"))
    short = short.select("digest", F.col("spans").alias("_short")) if passage else short.select("digest", F.lit(None).cast("array<struct<first: int, end: int>>").alias("_short")).limit(0)
    marks = materialise(marks.join(short, "digest", "full").select(F.col("digest").alias("_mark"), F.coalesce("_n", F.lit(1)).alias("_n"), "_spans", "_short"), "suffix-marks")
    rows = docs.withColumn("_text", text)
    rows = rows.mapInArrow(_named_rows, _ddl(rows.schema, "_digest binary"))
    rows = rows.join(marks, F.col("_digest") == F.col("_mark"), "left").drop("_mark", "_digest")
    added = ("_text", "_n", "_spans", "_short")
    run_type = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = {name: i for i, name in enumerate(batch.schema.names)}
            texts = _texts(batch, at["_text"])
            sizes = np.array([len(t) for t in texts], np.int64)
            repeated = pc.fill_null(batch.column(at["_n"]), 1).to_numpy(zero_copy_only=False) > 1
            first, end, many = merged_rows(batch.column(at["_spans"]), repeated, sizes, width)
            passages = run_lists(*merged_rows(batch.column(at["_short"]), repeated, sizes, passage)) if passage else pa.nulls(len(batch), run_type)
            kept, stop = [], np.cumsum(many)
            for i, (t, low, high) in enumerate(zip(texts, (stop - many).tolist(), stop.tolist())):
                parts, done = [], 0
                for r in range(low, high):
                    if whole_characters:
                        first[r], end[r] = _inside(t, int(first[r]), int(end[r]))
                    parts.append(t[done : first[r]])
                    done = int(end[r])
                kept.append(b"".join([*parts, t[done:]]))
            own = [batch.column(i) for name, i in at.items() if name not in added]
            yield pa.RecordBatch.from_arrays([*own, pa.array(kept, pa.binary()), run_lists(first, end, many), pa.array(sizes), passages], [*(n for n in at if n not in added), "_kept", "_removed", "_n_bytes", "_passages"])

    out = rows.mapInArrow(cut, _ddl(docs.schema, "_kept binary", "_removed array<struct<first: long, end: long>>", "_n_bytes long", "_passages array<struct<first: long, end: long>>"))
    return out if passage else out.drop("_passages")


def _ddl(schema, *more: str) -> str:
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in schema), *more])


def repeat_digest(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, passage: int | None = PASSAGE, **tuning) -> DataFrame:
    """One row per input row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, with passage, n_passages and
    passage_bytes: the maximal runs that repeated strings of so many bytes cover, and their bytes.

    Null and empty texts: 0 bytes, nothing removed; a null id keeps its row; extra columns are ignored; an empty
    table gives an empty result.
    """
    out = remove_repeats(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")), "text", width, passage=passage, **tuning)
    covered = F.aggregate("_passages", F.lit(0).cast("long"), lambda s, r: s + r["end"] - r["first"])
    more = [F.size("_passages").cast("long").alias("n_passages"), covered.alias("passage_bytes")] if passage else []
    return out.select("doc_id", F.col("_n_bytes").alias("n_bytes"), (F.col("_n_bytes") - F.octet_length("_kept")).alias("n_removed"), F.size("_removed").cast("long").alias("n_spans"), F.sha2("_kept", 256).alias("kept_sha256"), *more)


def op3_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return repeat_digest(table(spark, sf_dir, "documents"))
