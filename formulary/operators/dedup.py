"""Stage 4: near-duplicate removal by SimHash, its candidates, clusters and survivors, and comparison methods."""

from __future__ import annotations

import math
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import lexicon as L
from ..fixtures import md5_number
from ..functions import columns as C

BITS60 = 60
SHINGLE = 3


def exact(docs: DataFrame, text_col: str = "text", key: str = "doc_id") -> DataFrame:
    """digest, first key, copies of every text that occurs more than once."""
    return docs.groupBy(F.md5(F.col(text_col).cast("binary")).alias("digest")).agg(F.min(key).alias("first_id"), F.count("*").alias("copies")).where("copies > 1")


def shingled(docs: DataFrame, n: int = SHINGLE, key: str = "doc_id", text_col: str = "text") -> DataFrame:
    """key and its distinct n-word shingles."""
    return docs.select(key, C.shingles(C.tokens(F.col(text_col)), n).alias("sh"))


def fingerprint60(docs: DataFrame, n: int = SHINGLE, key: str = "doc_id") -> DataFrame:
    """key and a 60-bit fingerprint from md5 hashes: each bit set if more shingles have it than not. The SQL twin's form."""
    h = shingled(docs, n, key).select(key, F.explode("sh").alias("s")).select(key, md5_number(F.col("s")).alias("h"))
    votes = h.groupBy(key).agg(F.count("*").alias("n"), *(F.sum(F.shiftright("h", b).bitwiseAND(1)).alias(f"b{b}") for b in range(BITS60)))
    fp = F.lit(0).cast("long")
    for b in range(BITS60):
        fp = fp + F.when(2 * F.col(f"b{b}") > F.col("n"), F.lit(1 << b)).otherwise(F.lit(0)).cast("long")
    return votes.select(key, fp.alias("fp"))


_STEP, _GOLD = np.uint64(0xD6E8FEB86659FD93), 0x9E3779B97F4A7C15
#: The bits of a byte, each in a byte of its own.
_LANES = (np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").copy()).view(np.uint64).ravel()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_hashes(tokens: np.ndarray, size: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the distinct n-token shingles of each text (fewer tokens: the whole sequence), text after text and sorted
    in each, and their numbers. tokens: hashes of all tokens, text after text; size: tokens of each text."""
    owner, start = np.repeat(np.arange(len(size)), size), np.cumsum(size) - size
    left = (start + size)[owner] - np.arange(len(owner))  # tokens from here to the text's end
    many = np.flatnonzero(left >= n)
    h = np.zeros(len(many), np.uint64)
    for j in range(n):
        h = _mix(h * _STEP + tokens[many + j])
    few = np.flatnonzero((size > 0) & (size < n))
    g = np.full(len(few), n, np.uint64)
    for j in range(n - 1):
        on = size[few] > j
        g[on] = _mix(g[on] * _STEP + tokens[start[few[on]] + j])
    h, owner = np.concatenate([h, g]), np.concatenate([owner[many], few])
    order = np.lexsort((h, owner))
    h, owner = h[order], owner[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    return h[new], np.bincount(owner[new], minlength=len(size))


def _majorities(h: np.ndarray, size: np.ndarray, words: int) -> np.ndarray:
    """Words of the fingerprint of each text (none is empty): bits that more of its hashes have than not. Counts are kept in
    the bytes of a 64-bit number, for runs of up to 255 hashes."""
    runs = -(-size // 255)
    first = np.cumsum(runs) - runs
    at = np.repeat(np.cumsum(size) - size, runs) + 255 * (np.arange(runs.sum()) - np.repeat(first, runs))
    out = np.empty((len(size), words), np.uint64)
    for w in range(words):
        raw = _mix(h ^ np.uint64((w + 1) * _GOLD & 0xFFFFFFFFFFFFFFFF)).view(np.uint8).reshape(-1, 8)
        lanes = np.stack([np.add.reduceat(_LANES[raw[:, k]], at) for k in range(8)], axis=1).view(np.uint8)
        ones = np.add.reduceat(lanes.astype(np.int32), first, axis=0)
        out[:, w] = np.packbits(2 * ones > size[:, None], axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def fingerprint(docs: DataFrame, bits: int = 256, n: int = SHINGLE, key: str = "doc_id", text_col: str = "text") -> DataFrame:
    """key and a fingerprint of bits / 64 words: tokens are hashed in the JVM, shingles and votes are made in numpy by Arrow
    batch. The first words of a wide fingerprint are the narrower ones.

    Texts without words have a null fingerprint and never pair.
    """
    words = bits // 64
    hashed = docs.select(F.col(key).cast("long").alias("id"), F.transform(C.tokens(F.col(text_col)), lambda t: F.xxhash64(t)).alias("h"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            col = batch.column(1)
            size = pc.fill_null(pc.list_value_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            h, count = shingle_hashes(col.flatten().to_numpy(zero_copy_only=False).view(np.uint64), size, n)
            some = count > 0
            fp = _majorities(h, count[some], words) if some.any() else np.empty((0, words), np.uint64)
            ends = np.concatenate([[0], np.cumsum(some)]) * words
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(fp.view(np.int64).ravel()), mask=pa.array(~some))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists], [key, "fp"])

    return hashed.mapInArrow(run, f"{key} long, fp array<long>")


def distance(a: Column, b: Column) -> Column:
    """Differing bits of two fingerprints (arrays of words)."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def pairs_blocked(fps: DataFrame, d: int, bits: int = BITS60, key: str = "doc_id") -> DataFrame:
    """All pairs within d bits of 60-bit fingerprints, exactly: of d + 1 blocks of bits one must be equal. A pair is
    emitted at its first equal block only, so no distinct is needed."""
    width = -(-bits // (d + 1))
    block = lambda fp, i: F.shiftright(fp, i * width).bitwiseAND((1 << width) - 1)
    keyed = fps.select(key, "fp", F.explode(F.array(*(F.struct(F.lit(i).alias("i"), block(F.col("fp"), i).alias("v")) for i in range(d + 1)))).alias("k")).select(key, "fp", "k.*")
    a, b = keyed.select(F.col(key).alias("a"), F.col("fp").alias("fa"), "i", "v"), keyed.select(F.col(key).alias("b"), F.col("fp").alias("fb"), "i", "v")
    earlier = F.lit(False)
    for i in range(d + 1):
        earlier = earlier | ((F.col("i") > i) & (block(F.col("fa"), i) == block(F.col("fb"), i)))
    x = a.join(b, ["i", "v"]).where("a < b").withColumn("dist", F.bit_count(F.col("fa").bitwiseXOR(F.col("fb"))))
    return x.where((F.col("dist") <= d) & ~earlier).select("a", "b", F.col("dist").cast("int").alias("dist"))


def pairs_lsh(fps: DataFrame, tau: float = L.SIMILARITY, bits: int = 256, r: int = 12, tables: int | None = None, seed: int = 5, key: str = "doc_id", recall: float = 0.99, block: int = 1 << 18) -> DataFrame:
    """Pairs with similarity of tau or more among those that agree on r sampled bits in one of the tables: an approximate
    method (pairs_exact finds all). Unless given, there are so many tables that a pair at tau itself is met with
    probability recall.

    Distinct fingerprints are dealt in blocks, and a cell of two blocks makes the keys of a share of the tables where it
    compares, so that no row is exchanged for each table. A pair is emitted at the first table it meets in."""
    limit = int((1 - tau) * bits + 1e-9)
    if tables is None:
        meet = math.comb(bits - limit, r) / math.comb(bits, r)
        tables = max(1, math.ceil(math.log(1 - recall) / math.log1p(-meet))) if meet < 1 else 1
    rng = np.random.default_rng(seed)
    picks = [sorted(rng.choice(bits, r, replace=False).tolist()) for _ in range(tables)]
    masks = np.zeros((tables, bits // 64), np.uint64)
    for t, chosen in enumerate(picks):
        for bit in chosen:
            masks[t, bit // 64] |= np.uint64(1) << np.uint64(bit % 64)

    def earlier(x: np.ndarray, t: int) -> np.ndarray:
        """Which of the differences x agree on the bits of a table before t."""
        met, left = np.zeros(len(x), bool), np.arange(len(x))
        for s in range(0, t, 32):
            part = x[left]
            same = (part[:, None, 0] & masks[s : min(s + 32, t), 0]) == 0
            for w in range(1, masks.shape[1]):
                same &= (part[:, None, w] & masks[s : min(s + 32, t), w]) == 0
            hit = same.any(axis=1)
            met[left[hit]] = True
            left = left[~hit]
            if not len(left):
                break
        return met

    def run(cell: pa.Table) -> pa.Table:
        i, j, g = (cell.column(c)[0].as_py() for c in ("i", "j", "g"))
        ids, side = cell.column("id").to_numpy(), cell.column("own").to_numpy()
        words = cell.column("fp").combine_chunks().flatten().to_numpy().view(np.uint64).reshape(len(ids), -1)
        sides = [np.flatnonzero(side == x) for x in ((i,) if i == j else (i, j))]
        found = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int32))]
        for t in range(g, tables, groups):
            ordered = []  # of each side: its rows by key, their words, where each key starts
            for rows in sides:
                v = np.zeros(len(rows), np.int64)
                for k, bit in enumerate(picks[t]):
                    v |= ((words[rows, bit // 64] >> np.uint64(bit % 64)) & np.uint64(1)).astype(np.int64) << k
                order = np.argsort(v.astype(np.uint16) if r <= 16 else v, kind="stable")
                key_of, first = np.unique(v[order], return_index=True)
                ordered.append((rows[order], np.ascontiguousarray(words[rows[order]].T), key_of, np.append(first, len(rows))))
            (left, lw, lk, ls), (right, rw, rk, rs) = ordered[0], ordered[-1]
            _, p, q = np.intersect1d(lk, rk, assume_unique=True, return_indices=True)
            a, b, c, d = ls[p], ls[p + 1], rs[q], rs[q + 1]
            some = np.flatnonzero(b - a > 1) if i == j else np.arange(len(p))
            for low, high, start, stop in zip(a[some].tolist(), b[some].tolist(), c[some].tolist(), d[some].tolist()):
                step = max(1, (1 << 20) // (stop - start))
                for s in range(low, high, step):
                    e, begin = min(s + step, high), s if i == j else start
                    dist = np.bitwise_count(lw[0, s:e, None] ^ rw[0, begin:stop]).astype(np.uint16)
                    for w in range(1, len(lw)):
                        dist += np.bitwise_count(lw[w, s:e, None] ^ rw[w, begin:stop])
                    x, y = np.nonzero(dist <= limit)
                    if i == j:
                        x, y = x[y > x], y[y > x]
                    if len(x):
                        x, y, near = x + s, y + begin, dist[x, y].astype(np.int32)
                        new = ~earlier((lw[:, x] ^ rw[:, y]).T, t)
                        if new.any():
                            found.append((ids[left[x[new]]], ids[right[y[new]]], near[new]))
        x, y, dist = (np.concatenate(z) for z in zip(*found))
        return pa.table({"x": x, "y": y, "dist": dist})

    rows = _stored(fps.where(F.col("fp").isNotNull() & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), "fp"))
    nodes = _stored(rows.groupBy("fp").agg(F.min("id").alias("id")))  # an id with two fingerprints may name two nodes
    nodes = _stored(nodes.select(F.monotonically_increasing_id().alias("node"), "fp"))
    members = _stored(rows.join(nodes, "fp").select("node", "id").distinct())
    blocks = max(1, -(-nodes.count() // block))
    groups = max(1, min(tables, -(-64 // (blocks * (blocks + 1)))))
    dealt = _dealt(nodes, "node", block).withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    cells = dealt.repartition(groups * blocks * (blocks + 1), "i", "j", "g")  # a cell costs seconds, not bytes: no coalescing by size
    near = cells.groupBy("i", "j", "g").applyInArrow(run, "x long, y long, dist int")
    one, other = members.toDF("x", "a"), members.toDF("y", "b")
    unlike = near.join(one, "x").join(other, "y").where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "dist")
    like = one.join(other, F.col("x") == F.col("y")).where("a < b").select("a", "b", F.lit(0).alias("dist"))
    return unlike.unionByName(like).select("a", "b", "dist", F.round(1 - F.col("dist") / bits, 6).alias("sim")).distinct()


def _dealt(fps: DataFrame, key: str, block: int, ranged: bool = False) -> DataFrame:
    """i, j, own, id, fp: every fingerprint in the cells of its block with each block, i <= j. ranged: blocks are ranges of ids."""
    rows = fps.where(F.col("fp").isNotNull() & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), "fp")
    rows = _stored(rows)
    n = max(1, -(-rows.count() // block))
    own = F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")
    if ranged and n > 1:
        bounds = sorted(set(rows.approxQuantile("id", [k / n for k in range(1, n)], 0.05 / n)))
        n, own = len(bounds) + 1, F.size(F.filter(F.array(*map(F.lit, bounds)), lambda low: low <= F.col("id").cast("double")))
    dealt = rows.select("id", "fp", own.alias("own"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("o"))
    return dealt.select(F.least("own", "o").alias("i"), F.greatest("own", "o").alias("j"), "own", "id", "fp")


def _cells(fps: DataFrame, bits: int, key: str, limit: int, out, schema: str, block: int) -> DataFrame:
    """Compare all fingerprints, block against block. out gets (a, b, dist) of a cell's pairs within limit bits, a < b, as arrays."""
    dealt = _dealt(fps, key, block)

    def run(cell: pa.Table) -> pa.Table:
        i, j = cell.column("i")[0].as_py(), cell.column("j")[0].as_py()
        ids, side = cell.column("id").to_numpy(), cell.column("own").to_numpy()
        words = cell.column("fp").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        signs = np.unpackbits(np.ascontiguousarray(words).view(np.uint8), axis=1).astype(np.float32) * 2 - 1
        left, right, found = np.flatnonzero(side == i), np.flatnonzero(side == j), []
        for s in range(0, len(left), 512):
            part = left[s : s + 512]
            dist = (signs.shape[1] - signs[part] @ signs[right].T) / 2
            r, c = np.nonzero(dist <= limit)
            a, b, d = ids[part[r]], ids[right[c]], dist[r, c].astype(np.int32)
            if i == j:
                once = a < b
                a, b, d = a[once], b[once], d[once]
            found.append((np.minimum(a, b), np.maximum(a, b), d))
        return out(*(np.concatenate(x) for x in zip(*found))) if found else out(*(np.empty(0, t) for t in (np.int64, np.int64, np.int32)))

    return dealt.groupBy("i", "j").applyInArrow(run, schema)


def pairs_exact(fps: DataFrame, tau: float = L.SIMILARITY, bits: int = 256, key: str = "doc_id", block: int = 8192) -> DataFrame:
    """All pairs with similarity of tau or more: every fingerprint is compared with every other. At 0.7 no exact index
    has fewer candidates than a good part of all pairs."""

    def out(a: np.ndarray, b: np.ndarray, d: np.ndarray) -> pa.Table:
        return pa.table({"a": a, "b": b, "dist": d, "sim": np.round(1 - d / bits, 6)})

    return _cells(fps, bits, key, int((1 - tau) * bits + 1e-9), out, "a long, b long, dist int, sim double", block)


def links_exact(fps: DataFrame, tau: float = L.SIMILARITY, bits: int = 256, key: str = "doc_id", block: int = 8192) -> DataFrame:
    """Links (a, b) with the same components as pairs_exact: of each cell every node and the least one it is joined to."""

    def out(a: np.ndarray, b: np.ndarray, d: np.ndarray) -> pa.Table:
        node, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        x, y, root = at[: len(a)], at[len(a) :], np.arange(len(node))
        while len(a):
            low = np.minimum(root[x], root[y])
            later = root.copy()
            np.minimum.at(later, x, low)
            np.minimum.at(later, y, low)
            later = later[later]
            if (later == root).all():
                break
            root = later
        on = np.flatnonzero(root != np.arange(len(node)))
        return pa.table({"a": node[root[on]].astype(np.int64), "b": node[on].astype(np.int64)})

    return _cells(fps, bits, key, int((1 - tau) * bits + 1e-9), out, "a long, b long", block)


def sweep_widths(fps: DataFrame, taus: tuple[float, ...], widths: tuple[int, ...], key: str = "doc_id", block: int = 16384) -> DataFrame:
    """tau, pairs, removable, bits: pairs with that similarity on the first bits of the fingerprints, and their distinct later
    documents. Every fingerprint is compared with every other once for all widths, and pairs are counted where they are
    found: a cell gives its counts and, of each document, a bit for every width and threshold that it has an earlier pair at."""
    cuts = [(w, t, w - 2 * int((1 - t) * w + 1e-9)) for w in widths for t in sorted(taus)]  # least agreement less disagreement
    spans = list(zip((0, *widths), widths))
    per = len(taus)

    def run(cell: pa.Table) -> pa.Table:
        i, j = cell.column("i")[0].as_py(), cell.column("j")[0].as_py()
        ids = cell.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, side = ids[order], cell.column("own").to_numpy()[order]
        words = cell.column("fp").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)[order]
        signs = np.unpackbits(np.ascontiguousarray(words).view(np.uint8), axis=1, bitorder="little").astype(np.float32) * 2 - 1
        sides = [np.flatnonzero(side == x) for x in (i, j)]
        left, right = ([np.ascontiguousarray(signs[x, low:high]) for low, high in spans] for x in sides)
        a, b = (ids[x] for x in sides)
        counts, seen = np.zeros(len(cuts), np.int64), np.zeros(len(b), np.int32)
        for s in range(0, len(a), 512):
            for c in range(0, len(b), 2048):
                p, q, dot = a[s : s + 512], b[c : c + 2048], None
                if p[0] >= q[-1]:
                    continue
                later = None if p[-1] < q[0] else p[:, None] < q
                for k in range(len(widths)):
                    more = left[k][s : s + 512] @ right[k][c : c + 2048].T
                    dot = more if dot is None else np.add(dot, more, out=dot)
                    # the loosest threshold may be met by many pairs and is counted whole, the others from those that meet the next
                    near = dot >= cuts[k * per][2]
                    near = near if later is None else near & later
                    counts[k * per] += np.count_nonzero(near)
                    seen[c : c + 2048] |= near.any(axis=0).astype(np.int32) << (k * per)
                    if per > 1:
                        near = dot >= cuts[k * per + 1][2]
                        at = np.flatnonzero(near if later is None else near & later)
                        close, col = dot.ravel()[at], at % len(q)
                        for m in range(k * per + 1, (k + 1) * per):
                            on = close >= cuts[m][2]
                            counts[m] += np.count_nonzero(on)
                            hit = np.zeros(len(q), np.int32)
                            hit[col[on]] = 1 << m
                            seen[c : c + 2048] |= hit
        on = np.flatnonzero(seen)
        none = np.zeros(len(on), np.int64)
        found = {f"n{m}": np.concatenate([counts[m : m + 1], none]) for m in range(len(cuts))}
        return pa.table({"b": pa.array([None, *b[on].tolist()], pa.int64()), "seen": np.concatenate([np.zeros(1, np.int32), seen[on]]), **found})

    numbers = [f"n{m}" for m in range(len(cuts))]
    cells = _dealt(fps, key, block, ranged=True).groupBy("i", "j").applyInArrow(run, f"b long, seen int, {', '.join(f'{x} long' for x in numbers)}")
    per_doc = cells.groupBy("b").agg(F.bit_or("seen").alias("seen"), *(F.sum(x).alias(x) for x in numbers))
    whole = per_doc.agg(*(F.coalesce(F.sum(x), F.lit(0)).alias(x) for x in numbers), *(F.count_if(F.getbit("seen", F.lit(m)) == 1).alias(f"r{m}") for m in range(len(cuts))))
    rows = (F.struct(F.lit(t).alias("tau"), F.col(f"n{m}").alias("pairs"), F.col(f"r{m}").alias("removable"), F.lit(w).alias("bits")) for m, (w, t, _) in enumerate(cuts))
    return whole.select(F.inline(F.array(*rows)))


def sweep_exact(fps: DataFrame, taus: tuple[float, ...], bits: int = 256, key: str = "doc_id", block: int = 8192) -> DataFrame:
    """tau, pairs, removable of one width."""
    return sweep_widths(fps, taus, (bits,), key, block).drop("bits")


#: Places of the table of counts by which a prefix orders its shingles.
_PLACES = 1 << 22


def _slices(batches: Iterator[pa.RecordBatch], rows: int = 2000) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for s in range(0, len(batch), rows):
            yield batch.slice(s, rows)


def _hash_sets(col: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the shingle sets of a column of hashes of tokens, their sizes, and a name of each set."""
    size = pc.fill_null(pc.list_value_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    h, count = shingle_hashes(col.flatten().to_numpy(zero_copy_only=False).view(np.uint64), size, n)
    name = np.zeros(len(count), np.uint64)
    if len(h):
        some = count > 0
        name[some] = np.add.reduceat(_mix(h ^ np.uint64(_GOLD)), (np.cumsum(count) - count)[some])
    return h, count, name


def _hashed_tokens(docs: DataFrame, key: str, text_col: str) -> DataFrame:
    return docs.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.transform(C.tokens(F.col(text_col)), lambda t: F.xxhash64(t)).alias("h"))


def _shingle_counts(hashed: DataFrame, n: int) -> np.ndarray:
    """How many sets have a shingle, up to 255, by place of its hash: other shingles of the place are counted with it."""
    piece = 1 << 16

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(_PLACES, np.uint8)
        for batch in _slices(batches):
            h = _hash_sets(batch.column(1), n)[0]
            at, c = np.unique(h % np.uint64(_PLACES), return_counts=True)
            total[at] = np.minimum(total[at] + c, 255)
        parts = [(k, total[k * piece : (k + 1) * piece]) for k in range(_PLACES // piece)]
        parts = [(k, x.tobytes()) for k, x in parts if x.any()]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in parts], pa.int32()), pa.array([x for _, x in parts], pa.binary())], ["k", "c"])

    def merge(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, np.uint8).astype(np.int64) for x in t.column("c").to_pylist())
        return pa.table({"k": t.column("k").combine_chunks()[:1], "c": pa.array([np.minimum(total, 255).astype(np.uint8).tobytes()], pa.binary())})

    out = np.zeros(_PLACES, np.uint8)
    for r in hashed.mapInArrow(count, "k int, c binary").groupBy("k").applyInArrow(merge, "k int, c binary").collect():
        out[r.k * piece : (r.k + 1) * piece] = np.frombuffer(r.c, np.uint8)
    return out


def prefix_keys(h: np.ndarray, count: np.ndarray, counts: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Of each set its first n - ceil(percent n / 100) + 1 shingles, those of rare places first, and how many: two sets with
    that similarity share one, in whatever order all sets keep."""
    owner = np.repeat(np.arange(len(count)), count)
    h = h[np.lexsort((h, counts[h % np.uint64(_PLACES)], owner))]
    most = np.where(count > 0, count - -(-percent * count // 100) + 1, 0)
    at = np.arange(len(h)) - np.repeat(np.cumsum(count) - count, count)
    return h[at < most[owner]], most


def band_keys(h: np.ndarray, count: np.ndarray, bands: int, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """MinHash bands of each set that isn't empty, and how many."""
    some = count > 0
    if not some.any():
        return np.empty(0, np.uint64), np.zeros(len(count), np.int64)
    start, out = (np.cumsum(count) - count)[some], np.empty((some.sum(), bands), np.uint64)
    for band in range(bands):
        v = np.full(some.sum(), band, np.uint64)
        for r in range(rows):
            seed = np.uint64((101 + band * rows + r) * _GOLD & 0xFFFFFFFFFFFFFFFF)
            v = _mix(v * _STEP + np.minimum.reduceat(_mix(h ^ seed), start))
        out[:, band] = v
    return out.ravel(), np.where(some, bands, 0)


def _similar_pairs(docs: DataFrame, keys, percent: int, n: int, key: str, text_col: str = "text") -> DataFrame:
    """a, b, shared, total of the pairs of texts that have a key in common and Jaccard similarity of percent or more.

    keys: hashes of sets and their sizes -> their keys and how many each has. Shingles are 64-bit hashes. Equal sets are one node until the end; only keys, and the
    texts of nodes that have a candidate, are exchanged.
    """

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            h, count, name = _hash_sets(batch.column(1), n)
            got, many = keys(h, count)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), pa.array(got.view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(name.view(np.int64)), pa.array(count.astype(np.int32)), lists], ["id", "name", "n", "keys"])

    rows = _stored(_hashed_tokens(docs, key, text_col).mapInArrow(keyed, "id long, name long, n int, keys array<long>").where("n > 0"))
    first = rows.groupBy("name").agg(F.min("id").alias("first"), F.count("*").alias("copies")).where("copies > 1")
    copies = _stored(rows.select("name", "id").join(first.select("name", "first"), "name").where("id <> first").select("name", "id").distinct())
    nodes = rows.join(copies, ["name", "id"], "left_anti")
    k = nodes.select("name", "n", F.explode("keys").alias("k"))
    a, b = k.select(F.col("name").alias("a"), F.col("n").alias("na"), "k"), k.select(F.col("name").alias("b"), F.col("n").alias("nb"), "k")
    size = (100 * F.col("nb").cast("long") >= percent * F.col("na").cast("long")) & (100 * F.col("na").cast("long") >= percent * F.col("nb").cast("long"))
    cand = _stored(a.join(b, "k").where((F.col("a") < F.col("b")) & size).select("a", "b").distinct())
    live = _stored(cand.select(F.explode(F.array("a", "b")).alias("name")).distinct().join(rows.groupBy("name").agg(F.min("id").alias("id")), "name"))

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            (x, size, name), (y, other, mate) = (_hash_sets(batch.column(c), n) for c in (2, 3))
            ends, stops = np.cumsum(size), np.cumsum(other)
            both = np.array([len(np.intersect1d(x[e - c : e], y[f - d : f], assume_unique=True)) for e, c, f, d in zip(ends, size, stops, other)], np.int64)
            whole = size + other - both
            mine = (name.view(np.int64) == batch.column(0).to_numpy()) & (mate.view(np.int64) == batch.column(1).to_numpy())  # an id may stand for several texts
            on = mine & (100 * both >= percent * whole)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(on)), batch.column(1).filter(pa.array(on)), pa.array(both[on].astype(np.int32)), pa.array(whole[on].astype(np.int32))], ["na", "nb", "shared", "total"])

    # texts are shuffled, which take a third of the room of their hashes
    whole = docs.select(F.col(key).cast("long").alias("id"), F.col(text_col).alias("t")).join(live, "id").select("name", "t")
    full = cand.join(whole.select(F.col("name").alias("a"), F.col("t").alias("ta")), "a").join(whole.select(F.col("name").alias("b"), F.col("t").alias("tb")), "b")
    tokens = (F.transform(C.tokens(F.col(t)), lambda x: F.xxhash64(x)).alias(t) for t in ("ta", "tb"))
    near = full.select("a", "b", *tokens).mapInArrow(verify, "na long, nb long, shared int, total int").dropDuplicates(["na", "nb"])
    left, right = rows.select(F.col("name").alias("na"), F.col("id").alias("x"), "n"), rows.select(F.col("name").alias("nb"), F.col("id").alias("y"))
    unlike = near.join(left.drop("n"), "na").join(right, "nb").where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "shared", "total")
    like = left.join(right, F.col("na") == F.col("nb")).where("x < y").select(F.col("x").alias("a"), F.col("y").alias("b"), F.col("n").alias("shared"), F.col("n").alias("total"))
    return unlike.unionByName(like)


def jaccard_pairs(docs: DataFrame, percent: int = 70, n: int = SHINGLE, key: str = "doc_id") -> DataFrame:
    """All pairs of texts with Jaccard similarity of percent or more on n-word shingles, by prefix filter."""
    counts = docs.sparkSession.sparkContext.broadcast(_shingle_counts(_hashed_tokens(docs, key, "text"), n))
    return _similar_pairs(docs, lambda h, count: prefix_keys(h, count, counts.value, percent), percent, n, key)


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder that spark.checkpoint.dir names (a temporary one where it is unset and all tasks run here)."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not folder:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="formulary-")
    return f"{folder.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def _stored(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder."""
    path = scratch_path(df.sparkSession, "round")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def components(pairs: DataFrame, max_rounds: int = 50) -> DataFrame:
    """node, root of every node of pairs (a, b): least labels spread over neighbours, then labels of labels."""
    edges = pairs.select("a", "b").where("a <> b")
    both = _stored(edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = _stored(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("root")))
    for _ in range(max_rounds):
        near = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("root").alias("low"))
        nxt = labels.join(near, labels["node"] == near["a"]).select("node", F.least("root", "low").alias("root"))
        jump = nxt.select(F.col("node").alias("root"), F.col("root").alias("far"))
        nxt = _stored(nxt.join(jump, "root", "left").select("node", F.least("root", F.coalesce("far", "root")).alias("root")))
        changed = nxt.join(labels.select("node", F.col("root").alias("old")), "node").where("root <> old").limit(1).count()
        labels = nxt
        if not changed:
            return labels
    raise RuntimeError(f"labels still change after {max_rounds} rounds")


def survivors(docs: DataFrame, clusters: DataFrame, keep: str = "min_id", key: str = "doc_id", length: str = "n_chars") -> DataFrame:
    """docs without the losers of each cluster. keep: min_id or longest (ties: the lower id)."""
    if keep == "min_id":
        losers = clusters.where("node <> root").select(F.col("node").alias(key))
    else:
        sized = clusters.join(docs.select(F.col(key).alias("node"), length), "node")
        best = sized.groupBy("root").agg(F.max_by("node", F.struct(F.col(length), -F.col("node"))).alias("best"))
        losers = sized.join(best, "root").where("node <> best").select(F.col("node").alias(key))
    return docs.join(losers, key, "left_anti")


def any_previous(docs: DataFrame, pairs: DataFrame, key: str = "doc_id") -> DataFrame:
    """docs without those that have any near duplicate with a smaller id: no transitive closure."""
    return docs.join(pairs.select(F.col("b").alias(key)).distinct(), key, "left_anti")


def minhash_pairs(docs: DataFrame, percent: int = 70, bands: int = 16, rows: int = 4, n: int = SHINGLE, key: str = "doc_id") -> DataFrame:
    """Comparison method: MinHash bands, then verification by Jaccard."""
    return _similar_pairs(docs, lambda h, count: band_keys(h, count, bands, rows), percent, n, key).select("a", "b")
