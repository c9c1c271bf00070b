"""Sequence packing by bounded-space online best-fit.

A fixed number of bins is open at a time. They are keyed by free space in a bitset, so the fullest bin that still
takes a piece is found by one shift; when none takes it and all places are taken, the fullest bin closes first.
Partitions are packed independently, each with its own open bins, from narrow rows (no text).
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .token_counts import PRETOKEN, byte_alphabet

CAPACITY = 1024
OPEN_BINS = 1024
SEPARATOR = 2


class BestFit:
    """Online best-fit over bins of one capacity with at most `open_bins` open; place() gives (bin, offset)."""

    def __init__(self, capacity: int = CAPACITY, open_bins: int = OPEN_BINS):
        self.capacity, self.open_bins = capacity, open_bins
        self.bits, self.count, self.bins = 0, 0, 0
        self.by_space: list[list[int]] = [[] for _ in range(capacity + 1)]

    def _take(self, space: int) -> int:
        b = self.by_space[space].pop()
        if not self.by_space[space]:
            self.bits &= ~(1 << space)
        self.count -= 1
        return b

    def place(self, length: int) -> tuple[int, int]:
        if not 0 < length <= self.capacity:
            raise ValueError(f"a piece of {length} tokens for bins of {self.capacity}")
        fits = self.bits >> length
        if fits:
            space = length + (fits & -fits).bit_length() - 1
            b = self._take(space)
        else:
            b, space = self.bins, self.capacity
            self.bins += 1
            if self.count >= self.open_bins and length < self.capacity:
                self._take((self.bits & -self.bits).bit_length() - 1)
        left = space - length
        if left:
            self.by_space[left].append(b)
            self.bits |= 1 << left
            self.count += 1
        return b, self.capacity - space


class Encoder:
    """Token ids of whole texts, as the tokenizers library gives them for the same vocabulary file.

    The fast path runs the file's ranks in tiktoken, which gives the same ids (tested); texts that it can't take
    go to the tokenizers library itself. Special strings inside a text become their one id, as by default there.
    """

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte = {c: b for b, c in enumerate(byte_alphabet())}
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(map(byte.__getitem__, s)): i for s, i in spec["model"]["vocab"].items() if s not in self.specials}
        self.fast = tiktoken.Encoding("ranks", pat_str=PRETOKEN, mergeable_ranks=ranks, special_tokens={})
        self.path, self.exact = path, None

    def library(self):
        if self.exact is None:
            from tokenizers import Tokenizer

            self.exact = Tokenizer.from_file(self.path)
        return self.exact

    def ids(self, text: str | None) -> np.ndarray:
        if not text:
            return np.empty(0, np.uint32)
        if any(s in text for s in self.specials) or len(text) > 1 << 20:
            return np.array(self.library().encode(text, add_special_tokens=False).ids, np.uint32)
        try:
            return self.fast.encode_to_numpy(text, disallowed_special=())
        except BaseException as e:  # a panic of the fast library (no Exception), on very long runs of white space
            if type(e).__name__ != "PanicException":
                raise
            return np.array(self.library().encode(text, add_special_tokens=False).ids, np.uint32)


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def cut(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document of n tokens: only the first may be shorter than a bin."""
    head = n % capacity or min(n, capacity)
    return [(0, head), *((s, capacity) for s in range(head, n, capacity))] if n else []


def pieces(docs: DataFrame, vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, separator: int = SEPARATOR) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every document's pieces; a null or empty text is the separator alone."""

    names, types = ["doc_id", "piece", "start", "length", "ids_crc32"], [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(vocabulary_path)
        for batch in batches:
            rows = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = np.append(enc.ids(text), np.uint32(separator)).astype("<u4")
                rows += [(key, i, s, n, zlib.crc32(ids[s : s + n].tobytes())) for i, (s, n) in enumerate(cut(len(ids), capacity))]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return narrow.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack(rows: DataFrame, capacity: int = CAPACITY, open_bins: int = OPEN_BINS) -> DataFrame:
    """Add sequence_id and offset to rows with a length (1 to capacity); other columns stay, whatever they are called.

    Columns that are called sequence_id or offset already are replaced. A row whose length is null or 0 takes no
    place: both are null. A length beyond the capacity is an error. Repeated rows are packed each; an empty table
    gives an empty result. Rows are dealt by a hash of their values and packed in hash order, so a task that runs
    again packs alike. Sequences of different partitions have different ids; within one, pieces lie without gaps
    from offset 0.
    """
    rows = rows.drop("sequence_id", "offset")
    deal = "deal"
    while deal in rows.columns:
        deal += "_"
    at = rows.columns.index("length")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fit, base = BestFit(capacity, open_bins), TaskContext.get().partitionId() << 40
        for batch in batches:
            placed = [fit.place(n) if n else None for n in batch.column(at).to_pylist()]
            sequence = pa.array([None if p is None else base + p[0] for p in placed], pa.int64())
            offset = pa.array([None if p is None else p[1] for p in placed], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], sequence, offset], [*batch.schema.names[:-1], "sequence_id", "offset"])

    keys = [F.col(f"`{c}`") for c in rows.columns]
    dealt = rows.withColumn(deal, F.xxhash64(*keys))
    dealt = dealt.repartition(deal).sortWithinPartitions(deal, *keys)
    schema = ", ".join(f"`{n}` {t}" for n, t in rows.dtypes) + ", sequence_id long, offset long"
    return dealt.mapInArrow(run, schema)


def pack_documents(docs: DataFrame, vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, open_bins: int = OPEN_BINS, separator: int = SEPARATOR) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are one piece of one token; repeated rows are packed each; a null id keeps its row;
    other columns are ignored whatever their names; an empty table gives an empty result. Very long texts are
    tokenised whole.
    """
    return pack(pieces(docs, vocabulary_path, id_col, text_col, capacity, separator), capacity, open_bins)


def op9_query(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .common import table

    return pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
