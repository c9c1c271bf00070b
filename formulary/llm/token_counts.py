"""Token counts by rank-synchronous merging of ragged arrays.

A batch of distinct pre-tokens lies end to end in one array of symbols. In each round every pre-token applies its
own lowest-rank pair, all at once and at all its places from left to right; a pre-token without a known pair is
finished and leaves the arrays. The symbols that survive are its tokens.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed value: the public pattern that splits text into pre-tokens for this vocabulary.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
LIMIT = 512
CACHE = 400_000
LONG = 64
_SHIFT = np.int64(1 << 20)


def byte_alphabet() -> list[str]:
    """The character that stands for each byte in the vocabulary file: printable Latin-1 as itself, the rest from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b if b in plain else next(spare)) for b in range(256)]


class RankMerger:
    """Byte-level pair merging with the ranks of a public vocabulary file."""

    def __init__(self, vocabulary_path: str, cache: int = CACHE):
        with open(vocabulary_path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, merges = spec["model"]["vocab"], [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.first = np.array([vocab[c] for c in byte_alphabet()], np.int64)
        keys = np.array([vocab[a] * int(_SHIFT) + vocab[b] for a, b in merges], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank = keys[order], order.astype(np.int64)
        self.merged = np.array([vocab[a + b] for a, b in merges], np.int64)
        self.specials = [t["content"] for t in spec.get("added_tokens", [])]
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.specials, key=len, reverse=True)))) if self.specials else None
        self.pattern, self.known, self.cache = regex.compile(PRETOKEN), {}, cache

    def pair_ranks(self, pairs: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.keys, pairs), len(self.keys) - 1)
        return np.where(self.keys[at] == pairs, self.rank[at], np.iinfo(np.int64).max)

    def symbol_counts(self, pretokens: list[str]) -> np.ndarray:
        """Number of tokens of each pre-token."""
        raw = [p.encode("utf-8", "surrogatepass") for p in pretokens]
        size = np.array([len(r) for r in raw], np.int64)
        out = size.copy()
        symbols = self.first[np.frombuffer(b"".join(raw), np.uint8)]
        owner = np.repeat(np.arange(len(raw)), size)
        never = np.iinfo(np.int64).max
        while len(symbols):
            rank = self.pair_ranks(symbols[:-1] * _SHIFT + symbols[1:])
            rank[owner[1:] != owner[:-1]] = never
            rank = np.r_[rank, never]
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            best = np.minimum.reduceat(rank, starts)
            length = np.diff(np.r_[starts, len(symbols)])
            out[owner[starts]] = length
            going = np.repeat(best != never, length)
            hit = (rank == np.repeat(best, length)) & going
            if not hit.any():
                break
            follows = np.r_[False, hit[:-1]] & hit  # a run of equal symbols: every other place merges
            if follows.any():
                at = np.arange(len(hit))
                head = np.maximum.accumulate(np.where(hit & ~follows, at, 0))
                hit &= (at - head) % 2 == 0
            places = np.flatnonzero(hit)
            symbols[places] = self.merged[rank[places]]
            stays = going.copy()
            stays[places + 1] = False
            symbols, owner = symbols[stays], owner[stays]
        return out

    def _count_plain(self, text: str) -> int:
        if len(text) <= 1 << 20:
            return self._add(self.pattern.findall(text))
        total, found = 0, (m.group() for m in self.pattern.finditer(text))
        while part := list(islice(found, 200_000)):
            total += self._add(part)
        return total

    def _add(self, pretokens: list[str]) -> int:
        known = self.known
        try:
            return sum(map(known.__getitem__, pretokens))
        except KeyError:
            pass
        fresh = [p for p in set(pretokens) - known.keys()]
        counts = dict(zip(fresh, self.symbol_counts(fresh).tolist())) if fresh else {}
        if len(known) + len(fresh) > self.cache:
            known.clear()
        total = sum(counts[p] if p in counts else known[p] if p in known else int(self.symbol_counts([p])[0]) for p in pretokens)
        known.update((p, n) for p, n in counts.items() if len(p) <= LONG)
        return total

    def count(self, text: str | None) -> int:
        """Tokens of a whole text: special strings are one token each, as the library takes them by default."""
        if not text:
            return 0
        if self.special is None or not any(s in text for s in self.specials):
            return self._count_plain(text)
        parts = self.special.split(text)
        return len(parts) - 1 + sum(self._count_plain(p) for p in parts if p)


_MERGERS: dict[str, RankMerger] = {}


def merger(path: str) -> RankMerger:
    if path not in _MERGERS:
        _MERGERS[path] = RankMerger(path)
    return _MERGERS[path]


def count_batch(m: RankMerger, texts: list[str | None]) -> list[int]:
    """Pre-tokens are found once a text; those not seen yet are merged together for the whole batch."""
    plain = [t for t in texts if t and len(t) <= 1 << 20 and not any(s in t for s in m.specials)]
    found = {}
    for t in plain:
        if t not in found:
            found[t] = m.pattern.findall(t)
    fresh: set[str] = set()
    for pretokens in found.values():
        fresh.update(pretokens)
    fresh = list(fresh - m.known.keys())
    if len(m.known) + len(fresh) > m.cache:
        m.known.clear()
        fresh = list(set().union(*found.values()))
    new = dict(zip(fresh, m.symbol_counts(fresh).tolist())) if fresh else {}
    m.known.update(new)
    counts = {t: sum(map(m.known.__getitem__, pretokens)) for t, pretokens in found.items()}
    for p in new:
        if len(p) > LONG:
            m.known.pop(p, None)
    return [counts[t] if t in counts else m.count(t) for t in texts]


def count_tokens(docs: DataFrame, vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = LIMIT) -> DataFrame:
    """One row per input row: doc_id, n_bytes, n_tokens, over_limit.

    Null and empty texts have 0 bytes and 0 tokens; repeated rows are counted each; a null id keeps its row; other
    columns are ignored whatever their names; an empty table gives an empty result. Texts are never cut.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = merger(vocabulary_path)
        for batch in batches:
            counts, part, held = [], [], 0
            for t in batch.column(2).to_pylist():
                part.append(t)
                held += len(t or "")
                if held > 1 << 20:
                    counts += count_batch(m, part)
                    part, held = [], 0
            counts += count_batch(m, part)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("n_bytes"), F.col(text_col).alias("text"))
    return narrow.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)


def op2_query(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .common import table

    return count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
