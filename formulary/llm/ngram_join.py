"""Jaccard self-join of word shingle sets with token-combination prefixes.

1. Live sets. A set with a partner shares all but a few tokens with it. Over a quarter of the token space, every
   task sends its tokens as sorted blocks of short fingerprints and learns how many of each set's tokens any other
   set has; sets with too few can't have a partner. (Equal fingerprints of unlike tokens only let more sets live.)
   A token that several sets of a chunk have is counted there and sent once, so a token of a third of all rows costs
   an entry a chunk; the number of buckets follows the number of tokens.
2. Order. Of the live sets, the same exchange returns each token's document frequency. Tokens have one global
   order, the rarest first, then by hash.
3. Prefixes. A set's prefix holds so many of its first tokens that two sets similar enough must meet in it. Rare
   tokens of the prefix are indexed one by one. Frequent tokens fall into classes; of each class the prefix's
   tokens are indexed in combinations of two, and the prefix is extended, since the first token that a class gives
   covers nothing. Where a set has too few tokens for that, its frequent tokens are also indexed singly, in a list
   space of their own. A token that no other set has fills its place in the prefix but isn't indexed.
4. Verification. Sets that meet in a list form candidate groups (by edges to the list's first set, not by pairs).
   Whole sets go once to their group, in small blocks that each have the group's first set as well; a block counts all
   its intersections and gives each set the least set that it is linked to, so copies of the first set are settled
   here. Groups of several blocks are then divided by size (sets of unlike sizes can't link) and compare the sets
   outside the division's largest class with all the others, block against block. Nothing is capped, and no step
   emits the pairs of a group.

Equal sets are one node. Names of sets are 63-bit hashes of their content.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slabs, discard, edges_to_components, materialise, membership_bits, mix64, utf8_view
from .shingles import set_names, shingle_sets

WORDS = 4
PERCENT = 85
#: A token is frequent if more live sets than this have it.
FREQUENT = 64
CLASSES = 16
#: Sets of a block with the group's first set, and of a block that is compared with another.
HEADED = 250
BLOCK = 1000
_SLAB = 1 << 20
#: Tokens that a task sends together in the first exchange, and tokens of a chunk of live sets.
_SENDING = 1 << 22
_CHUNK = 1 << 20
#: Least number of buckets, and most tokens that a bucket should have.
BUCKETS, BUCKET = 64, 1 << 24
_QUARTER = np.uint64(3)
#: Stands for the owner of a token that its chunk has counted already.
_COUNTED = 0xFFFFFFFF
_PAIR, _SINGLE = np.uint64(0x8EBC6AF09C88C6E3), np.uint64(0x589965CC75374CC3)


def prefix_size(n: np.ndarray | int, percent: int):
    """Tokens that a prefix must cover: one more than a similar set may lack."""
    return n - (percent * n + 99) // 100 + 1


def frequency_code(count: np.ndarray) -> np.ndarray:
    """A byte that rises with the logarithm of a count; 0 for 1."""
    return np.minimum(np.ceil(12 * np.log2(count)), 255).astype(np.uint8)


def prefix_keys(tokens: np.ndarray, code: np.ndarray, percent: int, frequent: int = FREQUENT, classes: int = CLASSES) -> np.ndarray:
    """Index keys of one set. tokens in global order (ascending code, then value); code: their frequency codes."""
    need = int(prefix_size(len(tokens), percent))
    rare = int(np.searchsorted(code, frequency_code(np.array([frequent]))[0], "right"))
    alone_in_corpus = int(np.searchsorted(code, 0, "right"))
    if rare >= need:
        return tokens[alone_in_corpus:need]
    first, common, need = tokens[alone_in_corpus:rare], tokens[rare:], need - rare
    group = (mix64(common ^ _PAIR) % np.uint64(classes)).astype(np.int64)
    members: dict[int, list[int]] = {}
    covered = taken = 0
    while covered < need and taken < len(common):
        covered += int(group[taken]) in members
        members.setdefault(int(group[taken]), []).append(taken)
        taken += 1
    left, right = [], []
    for own in members.values():
        for i, j in combinations(own, 2):
            left.append(i)
            right.append(j)
    pairs = mix64(common[left] * _PAIR + mix64(common[right])) if left else np.empty(0, np.uint64)
    alone = mix64(common[:need] ^ _SINGLE) if covered < need else np.empty(0, np.uint64)
    return np.concatenate([first, pairs, alone])


def similar(sets: list[np.ndarray], percent: int) -> np.ndarray:
    """Boolean matrix of the pairs with 100 * intersection >= percent * union; the diagonal is False."""
    m, size = len(sets), np.array([len(s) for s in sets], np.int64)
    tokens, owner = np.concatenate(sets), np.repeat(np.arange(m), size)
    order = np.argsort(tokens, kind="stable")
    tokens, owner = tokens[order], owner[order]
    new = np.ones(len(tokens), bool)
    new[1:] = tokens[1:] != tokens[:-1]
    column = np.cumsum(new) - 1
    shared = np.bincount(column)[column] > 1
    column, owner = column[shared], owner[shared]
    new = np.ones(len(column), bool)
    new[1:] = column[1:] != column[:-1]
    column = np.cumsum(new) - 1
    both = np.zeros((m, m), np.float32)
    width = 2048
    for c in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        a, b = np.searchsorted(column, [c, c + width])
        x = np.zeros((m, min(width, int(column[b - 1]) - c + 1)), np.float32)
        x[owner[a:b], column[a:b] - c] = 1
        both += x @ x.T
    both = both.astype(np.int64)
    out = 100 * both >= percent * (size[:, None] + size[None, :] - both)
    np.fill_diagonal(out, False)
    return out


def least_reached(linked: np.ndarray) -> np.ndarray:
    """For each row of a symmetric matrix, the first row reached by links (itself if none)."""
    label = np.arange(len(linked))
    while True:
        lower = np.minimum(label, np.where(linked, label[None, :], len(label)).min(axis=1))
        lower = np.minimum(lower, lower[lower])
        if (lower == label).all():
            return label
        label = lower


def _described(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8_view(batch.column(1))
            sizes, names = [], []
            for a, b in byte_slabs(offsets, _SLAB):
                h, at = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], k)
                sizes.append(np.diff(at))
                names.append(set_names(h, at))
            if sizes:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(sizes).astype(np.int64)), pa.array(np.concatenate(names))], ["doc_id", "n_shingles", "node"])

    return run


def bucket_count(tokens: int, least: int = BUCKETS, most: int = BUCKET) -> int:
    """Buckets for so many tokens: enough to work side by side and to bound a bucket."""
    return max(least, -(-tokens // most))


def _blocks(tokens: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """An order of tokens by (bucket, fingerprint), where each distinct one starts in it, the distinct fingerprints, and
    the borders of the buckets among these."""
    code = (tokens >> np.uint64(8)) % np.uint64(buckets) << np.uint64(32) | tokens >> np.uint64(32)
    order = np.argsort(code, kind="stable")
    code = code[order]
    first = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]])) if len(code) else np.empty(0, np.int64)
    code = code[first]
    return order, first, code.astype(np.uint32), np.searchsorted(code >> np.uint64(32), np.arange(buckets + 1).astype(np.uint64))


def _chunk_name(names: np.ndarray) -> int:
    """A 63-bit name of a chunk: a hash of the names of its sets and their places."""
    placed = mix64(names.view(np.uint64) + mix64(np.arange(1, len(names) + 1).astype(np.uint64)))
    return int(mix64(np.array([placed.sum() + np.uint64(len(names))], np.uint64))[0] >> np.uint64(1))


_SENT = "bucket int, spread long, chunk long, fp binary, idx binary"


def _sent(k: int, percent: int, buckets: int):
    """Texts -> blocks of the fingerprints of a quarter of all tokens, and a row of names for each chunk of sets.

    The row of names (bucket -1) has the sets' names as fp and, as idx, how many tokens shared with other chunks each needs.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []

        def send() -> pa.RecordBatch:
            names, need, size, tokens = (np.concatenate(x) for x in zip(*held))
            held.clear()
            chunk = _chunk_name(names)
            order, first, fp, at = _blocks(tokens, buckets)
            owner = np.repeat(np.arange(len(size), dtype=np.uint32), size)[order]
            times = np.diff(np.append(first, len(owner)))
            need = need - np.bincount(owner[np.repeat(times > 1, times)], minlength=len(need))
            owner = np.where(times > 1, np.uint32(_COUNTED), owner[first])
            used = np.flatnonzero(np.diff(at))
            rows = [(-1, chunk, chunk, names.tobytes(), need.astype(np.int32).tobytes()), *((int(b), 0, chunk, fp[at[b] : at[b + 1]].tobytes(), owner[at[b] : at[b + 1]].tobytes()) for b in used)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary()))], ["bucket", "spread", "chunk", "fp", "idx"])

        for batch in batches:
            data, offsets = utf8_view(batch.column(0))
            for a, b in byte_slabs(offsets, _SLAB):
                h, at = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], k)
                node, size = set_names(h, at), np.diff(at)
                fresh = np.array([x != 0 and not (x in seen or seen.add(x)) for x in node.tolist()], bool)
                quarter = (h & _QUARTER) == 0
                inside = np.concatenate([[0], np.cumsum(quarter)])
                inside = inside[at[1:]] - inside[at[:-1]]
                keep = quarter & np.repeat(fresh, size)
                held.append((node[fresh], (inside - prefix_size(size, percent) + 1)[fresh], inside[fresh], h[keep]))
                if sum(len(x[3]) for x in held) >= _SENDING or sum(len(x[0]) for x in held) > 400_000:
                    yield send()
        if any(len(x[0]) for x in held):
            yield send()

    return run


_SHARED = "chunk long, names binary, need binary, idx binary, got binary"


def _shared_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks in runs of one bucket -> a row for each block: which sets of its chunk have tokens that other blocks have
    too, and how many. The rows of names go through."""

    def rows(found: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found), (pa.int64(), *[pa.binary()] * 4))], ["chunk", "names", "need", "idx", "got"])

    def settle(held: list) -> list[tuple]:
        fp = np.concatenate([np.frombuffer(x[1], np.uint32) for x in held])
        block = np.repeat(np.arange(len(held)), [len(x[1]) // 4 for x in held])
        owner = np.concatenate([np.frombuffer(x[2], np.uint32) for x in held]).astype(np.int64)
        order = np.argsort(fp, kind="stable")
        same = fp[order][1:] == fp[order][:-1]
        shared = np.zeros(len(fp), bool)
        shared[order[1:]] |= same
        shared[order[:-1]] |= same
        shared &= owner != _COUNTED
        code, got = np.unique(block[shared] << 32 | owner[shared], return_counts=True)
        idx, at = (code & 0xFFFFFFFF).astype(np.uint32), np.searchsorted(code >> 32, np.arange(len(held) + 1))
        return [(held[k][0], None, None, idx[a:b].tobytes(), got[a:b].astype(np.uint32).tobytes()) for k, (a, b) in enumerate(zip(at, at[1:])) if b > a]

    bucket, held = None, []
    for batch in batches:
        for b, chunk, fp, idx in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3, 4))):
            if b < 0:
                yield rows([(chunk, fp, idx, None, None)])
                continue
            if b != bucket and held:
                if found := settle(held):
                    yield rows(found)
                held = []
            bucket = b
            held.append((chunk, fp, idx))
    if held and (found := settle(held)):
        yield rows(found)


def _live(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of _shared_counts in runs of one chunk, its names first -> node: the sets that have as many shared tokens as they need."""

    def settle(names: np.ndarray, left: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(names[left <= 0])], ["node"])

    chunk, names, left = None, None, None
    for batch in batches:
        for c, name, need, idx, got in zip(*(batch.column(i).to_pylist() for i in range(5))):
            if name is not None:  # equal chunks of two tasks send equal names
                if c != chunk:
                    if names is not None:
                        yield settle(names, left)
                    chunk, names, left = c, np.frombuffer(name, np.int64), np.frombuffer(need, np.int32).astype(np.int64)
            else:
                left[np.frombuffer(idx, np.uint32)] -= np.frombuffer(got, np.uint32)
    if names is not None:
        yield settle(names, left)


def _named_texts(k: int, bits: np.ndarray):
    """Rows (node, text) of the nodes that the bit set lets through, a node once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            data, offsets = utf8_view(batch.column(0))
            names = []
            for a, b in byte_slabs(offsets, _SLAB):
                h, at = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], k)
                names.append(set_names(h, at))
            node = np.concatenate(names) if names else np.empty(0, np.int64)
            let = (bits[(node >> 6) % len(bits)] >> (node % 64).astype(np.uint64)) & np.uint64(1) > 0
            fresh = np.array([i for i in np.flatnonzero(let & (node != 0)).tolist() if not (node[i] in seen or seen.add(int(node[i])))], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(node[fresh]), batch.column(0).take(pa.array(fresh))], ["node", "text"])

    return run


def _chunked(k: int):
    """(node, text) -> chunks of sets: chunk, nodes, sizes, tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def send() -> pa.RecordBatch:
            nodes, sizes, tokens = (np.concatenate(x) for x in zip(*held))
            held.clear()
            chunk = _chunk_name(nodes)
            return pa.RecordBatch.from_arrays([pa.array([chunk]), *(pa.array([x.tobytes()], pa.binary()) for x in (nodes, sizes.astype(np.int32), tokens))], ["chunk", "nodes", "sizes", "tokens"])

        for batch in batches:
            node = batch.column(0).to_numpy()
            data, offsets = utf8_view(batch.column(1))
            for a, b in byte_slabs(offsets, _SLAB):
                h, at = shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], k)
                held.append((node[a:b].astype(np.int64), np.diff(at), h))
                if sum(len(x[2]) for x in held) >= _CHUNK:
                    yield send()
        if any(len(x[0]) for x in held):
            yield send()

    return run


def _asked(buckets: int):
    """Chunks -> (bucket, chunk, fp, times): the distinct fingerprints of their tokens, and how many sets of the chunk have them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                order, first, fp, at = _blocks(np.frombuffer(raw, np.uint64), buckets)
                times = np.diff(np.append(first, len(order))).astype(np.uint32)
                used = np.flatnonzero(np.diff(at))
                yield pa.RecordBatch.from_arrays([pa.array(used.astype(np.int32)), pa.array([chunk] * len(used), pa.int64()), *(pa.array([x[at[b] : at[b + 1]].tobytes() for b in used], pa.binary()) for x in (fp, times))], ["bucket", "chunk", "fp", "times"])

    return run


def _answered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks in runs of one bucket -> (chunk, bucket, codes): the frequency code of each fingerprint of a block."""

    def settle(bucket: int, held: list) -> pa.RecordBatch:
        fp = np.concatenate([np.frombuffer(x[1], np.uint32) for x in held])
        _, back = np.unique(fp, return_inverse=True)
        code = frequency_code(np.bincount(back, np.concatenate([np.frombuffer(x[2], np.uint32) for x in held])))[back]
        at = np.concatenate([[0], np.cumsum([len(x[1]) // 4 for x in held])])
        return pa.RecordBatch.from_arrays([pa.array([x[0] for x in held], pa.int64()), pa.array([bucket] * len(held), pa.int32()), pa.array([code[a:b].tobytes() for a, b in zip(at, at[1:])], pa.binary())], ["chunk", "bucket", "codes"])

    bucket, held = None, []
    for batch in batches:
        for b, chunk, fp, times in zip(*(batch.column(i).to_pylist() for i in range(4))):
            if b != bucket and held:
                yield settle(bucket, held)
                held = []
            bucket = b
            held.append((chunk, fp, times))
    if held:
        yield settle(bucket, held)


def _keyed(percent: int, buckets: int, frequent: int):
    """(nodes, sizes, tokens, answers) -> (key, node): the prefix index."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for nodes, sizes, raw, answers in zip(*(batch.column(i).to_pylist() for i in range(4))):
                tokens, size = np.frombuffer(raw, np.uint64), np.frombuffer(sizes, np.int32).astype(np.int64)
                order, first, _, _ = _blocks(tokens, buckets)
                code = np.empty(len(tokens), np.uint8)
                code[order] = np.repeat(np.frombuffer(b"".join(x["codes"] for x in sorted(answers, key=lambda x: x["bucket"])), np.uint8), np.diff(np.append(first, len(order))))
                rank = np.lexsort((tokens, code, np.repeat(np.arange(len(size)), size)))
                tokens, code, at = tokens[rank], code[rank], np.concatenate([[0], np.cumsum(size)])
                keys = [prefix_keys(tokens[a:b], code[a:b], percent, frequent) for a, b in zip(at, at[1:])]
                lengths = [len(x) for x in keys]
                if sum(lengths):
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.repeat(np.frombuffer(nodes, np.int64), lengths))], ["key", "node"])

    return run


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Chunks -> (node, tokens)."""
    for batch in batches:
        for nodes, sizes, raw in zip(*(batch.column(i).to_pylist() for i in range(3))):
            at = np.concatenate([[0], np.cumsum(np.frombuffer(sizes, np.int32).astype(np.int64))]) * 8
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(nodes, np.int64)), pa.array([raw[a:b] for a, b in zip(at, at[1:])], pa.binary())], ["node", "tokens"])


def _linked(percent: int):
    """Blocks in sorted runs of (grp, b1, b2) -> (a, b): each linked set and the least set that the block links it to."""

    def settle(nodes: list[int], raw: list[bytes], sides: list[int]):
        at = {n: i for i, n in enumerate(nodes)}
        pick = sorted(at.values(), key=lambda i: nodes[i])
        if len(pick) < 2:
            return None
        hit = similar([np.frombuffer(raw[i], np.uint64) for i in pick], percent)
        side = np.array([sides[i] for i in pick])
        if (side != 2).any():
            hit &= side[:, None] != side[None, :]
        root = least_reached(hit)
        on = np.flatnonzero(root != np.arange(len(root)))
        names = np.array([nodes[i] for i in pick], np.int64)
        return (names[on], names[root[on]]) if len(on) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, ([], [], [])
        for batch in batches:
            grp = np.stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)], axis=1)
            cols = [batch.column(i).to_pylist() for i in (3, 4, 5)]
            starts = np.flatnonzero(np.concatenate([[True], (grp[1:] != grp[:-1]).any(axis=1)])) if len(grp) else []
            for s, e in zip(starts, [*starts[1:], len(grp)]):
                now = tuple(grp[s])
                if now != key:
                    if key is not None and (found := settle(*held)):
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["a", "b"])
                    key, held = now, ([], [], [])
                for old, c in zip(held, cols):
                    old.extend(c[s:e])
        if key is not None and (found := settle(*held)):
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in found], ["a", "b"])

    return run


def _compare(rows: DataFrame, percent: int, tag: str) -> DataFrame:
    """rows: grp, b1, b2, node, tokens, side."""
    dealt = rows.select("grp", "b1", "b2", "node", "tokens", "side").repartition("grp", "b1", "b2").sortWithinPartitions("grp", "b1", "b2", "node")
    return materialise(dealt.mapInArrow(_linked(percent), "a long, b long"), tag)


def _live_chunks(texts: DataFrame, words: int, percent: int, tokens: int) -> DataFrame:
    """Chunks of the sets that may have a partner."""
    buckets = bucket_count(tokens // 4)
    sent = texts.mapInArrow(_sent(words, percent, buckets), _SENT).repartition("bucket", "spread").sortWithinPartitions("bucket")
    counted = sent.mapInArrow(_shared_counts, _SHARED).withColumn("later", F.col("names").isNull())
    counted = counted.repartition("chunk").sortWithinPartitions("chunk", "later").drop("later")
    live = materialise(counted.mapInArrow(_live, "node long").distinct(), "join-live")
    held = texts.mapInArrow(_named_texts(words, membership_bits(live)), "node long, text string").join(live, "node").dropDuplicates(["node"])
    return materialise(held.select("node", "text").mapInArrow(_chunked(words), "chunk long, nodes binary, sizes binary, tokens binary"), "join-chunks")


def _divided(wide: DataFrame, percent: int) -> DataFrame:
    """Rows of wide groups with grp renamed to a part of it: sets of neighbouring size bands share one.

    A band spans a little more than the ratio of sizes that linked sets may have, so they are at most one apart; a set
    is in the parts of its own and the next lower band, within its group's.
    """
    size = (F.octet_length("tokens") / 8).cast("double")
    band = F.floor(F.log(size) / (math.log(100 / percent) * (1 + 1e-9))) if percent < 100 else size
    wide = wide.withColumn("band", band.cast("long"))
    ends = materialise(wide.groupBy("grp").agg(F.min("band").alias("lo"), F.max("band").alias("hi")), "join-bands")
    top = F.greatest(F.col("hi") - 1, F.col("lo"))
    parts = F.array_distinct(F.array(F.greatest(F.col("band") - 1, F.col("lo")), F.least(F.col("band"), top)))
    return wide.join(ends, "grp").withColumn("part", F.explode(parts)).withColumn("grp", F.xxhash64("grp", "part")).drop("band", "lo", "hi", "part")


def set_groups(docs: DataFrame, text_col: str, words: int = WORDS, percent: int = PERCENT, block: int = BLOCK, headed: int = HEADED, frequent: int = FREQUENT, tokens: int | None = None) -> DataFrame:
    """Rows (node, component) of the sets that are linked with another one; component: the least node reached.

    Null, empty and wordless texts have no set and no row; equal texts are one set; an empty table gives an empty
    result. tokens: the number of shingles of all texts, if known; it only sizes the exchanges.
    """
    texts = docs.select(F.col(text_col).alias("text"))
    if tokens is None:
        tokens = texts.select(F.lit(0).cast("long").alias("doc_id"), "text").mapInArrow(_described(words), "doc_id long, n_shingles long, node long").agg(F.sum("n_shingles")).first()[0] or 0
    chunks = _live_chunks(texts, words, percent, tokens)
    buckets = bucket_count((chunks.agg(F.sum(F.octet_length("tokens"))).first()[0] or 0) // 8)
    asked = chunks.select("chunk", "tokens").mapInArrow(_asked(buckets), "bucket int, chunk long, fp binary, times binary").repartition("bucket").sortWithinPartitions("bucket")
    answers = asked.mapInArrow(_answered, "chunk long, bucket int, codes binary").groupBy("chunk").agg(F.collect_list(F.struct("bucket", "codes")).alias("answers"))
    keyed = chunks.join(answers, "chunk").select("nodes", "sizes", "tokens", "answers").mapInArrow(_keyed(percent, buckets, frequent), "key long, node long")
    posted = materialise(keyed, "join-posted")
    lists = materialise(posted.groupBy("key").agg(F.min("node").alias("head"), F.max("node").alias("last")).where("head < last").select("key", "head"), "join-lists")
    edges = posted.join(lists, "key").where("node <> head").select(F.col("head").alias("a"), F.col("node").alias("b"))
    groups = edges_to_components(edges, "join-groups").select("node", F.col("component").alias("grp"))
    groups = materialise(groups, "join-groups")
    discard(posted, lists)
    counts = materialise(groups.groupBy("grp").agg(F.count("*").alias("members")), "join-sizes")
    groups = groups.join(counts, "grp").select("node", "grp", F.ceil(F.col("members") / headed).cast("int").alias("blocks"))
    sets = chunks.select("nodes", "sizes", "tokens").mapInArrow(_unpacked, "node long, tokens binary")
    sets = materialise(sets.join(groups, "node").select("node", "grp", "blocks", "tokens"), "join-sets")
    discard(chunks)
    spread = lambda salt, n: F.pmod(F.xxhash64("node", F.lit(salt)), F.col(n)).cast("int")
    blocks = F.when(F.col("node") == F.col("grp"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(spread(3, "blocks")))
    first = _compare(sets.select("grp", F.explode(blocks).alias("b1"), "node", "tokens").select("grp", "b1", F.col("b1").alias("b2"), "node", "tokens", F.lit(2).alias("side")), percent, "join-links")
    wide = sets.where("blocks > 1")
    if not wide.limit(1).count():  # a block has reached all that a group of one block can
        return first.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(first.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
    label = edges_to_components(first, "join-first").select(F.col("node").alias("_n"), "component")
    wide = wide.join(label, F.col("node") == F.col("_n"), "left").select("node", "grp", "tokens", F.coalesce("component", "node").alias("label"))
    wide = materialise(_divided(wide, percent), "join-wide")
    top = wide.groupBy("grp", "label").agg(F.count("*").alias("c")).groupBy("grp").agg(F.max(F.struct("c", "label")).alias("top"), F.sum("c").alias("all"))
    top = top.select("grp", F.col("top.label").alias("major"), F.ceil(F.col("all") / block).cast("int").alias("blocks"), F.ceil((F.col("all") - F.col("top.c")) / block).cast("int").alias("rest")).where("rest > 0")
    left = wide.join(materialise(top, "join-top"), "grp").withColumn("minor", F.col("label") != F.col("major")).withColumn("b", spread(3, "blocks")).withColumn("c", spread(5, "rest"))
    major = left.where("NOT minor").select("grp", "b", F.explode(F.sequence(F.lit(0), F.col("rest") - 1)).alias("c"), "node", "tokens", F.lit(0).alias("side"))
    minor = left.where("minor").select("grp", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("b"), "c", "node", "tokens", F.lit(1).alias("side"))
    among = left.where("minor").select("grp", "c", F.explode(F.sequence(F.lit(0), F.col("rest") - 1)).alias("o"), "node", "tokens")
    among = among.select("grp", (-1 - F.least("c", "o")).alias("b1"), F.greatest("c", "o").alias("b2"), "node", "tokens", F.when(F.col("c") == F.col("o"), 2).when(F.col("c") < F.col("o"), 0).otherwise(1).alias("side"))
    rows = major.unionByName(minor).select("grp", F.col("b").alias("b1"), F.col("c").alias("b2"), "node", "tokens", "side").unionByName(among)
    second = _compare(rows, percent, "join-more")
    discard(sets, wide)
    return edges_to_components(first.unionByName(second), "join-final")


def jaccard_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, percent: int = PERCENT, **tuning) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id.

    Null, empty and wordless texts have an empty set and are linked with nothing (their own component); repeated
    rows and equal texts are linked (equal sets); a null id keeps its row and takes part, but never names a
    component; other columns are ignored whatever their names; an empty table gives an empty result. Texts are
    taken whole.
    """
    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows = materialise(narrow.mapInArrow(_described(words), "doc_id long, n_shingles long, node long"), "join-docs")
    linked = set_groups(narrow, "text", words, percent, tokens=rows.agg(F.sum("n_shingles")).first()[0] or 0, **tuning)
    lowest = rows.where("node <> 0").groupBy("node").agg(F.min("doc_id").alias("low"))
    named = materialise(lowest.join(linked, "node", "left").select("node", "low", F.coalesce("component", "node").alias("c")), "join-nodes")
    least = materialise(named.groupBy("c").agg(F.min("low").alias("component_id")), "join-least")
    final = materialise(named.join(least, "c").select("node", "component_id"), "join-named")
    return rows.join(final, "node", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def _noded(k: int):
    """(id, key, text) -> (id, key, node)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8_view(batch.column(2))
            names = [set_names(*shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], k)) for a, b in byte_slabs(offsets, _SLAB)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.concatenate(names) if names else np.empty(0, np.int64))], ["id", "key", "node"])

    return run


def first_of_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, percent: int = PERCENT, **tuning) -> DataFrame:
    """The rows of docs that a removal of near copies leaves: of each group the one with the least id.

    Ties of ids (repeated ids, or groups whose rows have none) are broken by a hash of the whole row; rows that are
    equal in all columns are one. A null id comes last in its group. Texts without words belong to no group and stay.
    Columns keep their names and values (names starting with _ are reserved); an empty table gives an empty result.
    """
    row = F.xxhash64(*(F.col(f"`{c}`") for c in docs.columns))
    keyed = docs.select(F.col(id_col).cast("long").alias("id"), row.alias("key"), F.col(text_col).cast("string").alias("text"))
    rows = materialise(keyed.mapInArrow(_noded(words), "id long, key long, node long").where("node <> 0"), "join-rows")
    linked = set_groups(docs, text_col, words, percent, **tuning)
    first = rows.groupBy("node").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "key")).alias("r"))
    first = first.join(linked, "node", "left").groupBy(F.coalesce("component", "node")).agg(F.min("r").alias("r"))
    first = materialise(first.select(F.col("r.key").alias("_first")), "join-kept")
    discard(rows)
    wordless = ~F.coalesce(F.col(text_col).cast("string"), F.lit("")).rlike(r"[^\x20\x09-\x0D]")
    kept = docs.where(~wordless).withColumn("_key", row).join(first, F.col("_key") == F.col("_first"), "left_semi")
    return kept.dropDuplicates(["_key", id_col]).drop("_key").unionByName(docs.where(wordless))


def op5_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return jaccard_groups(table(spark, sf_dir, "documents"))
