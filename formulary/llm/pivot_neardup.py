"""Embedding near-duplicates by a pivot-permutation index.

A bounded sample of the vectors serves as reference points (pivots). Each vector is described by the ordered
list of its nearest pivots; inverted lists hold, for each combination of `shared` pivots, the vectors that have all
of them in their list. Vectors that meet in a list share that many pivots at least; they are verified by cosine in
double precision. Lists longer than a block are cut into blocks and compared block against block, so that no
list is bounded by one task and nothing is capped.

How many pivots there are, how long the lists are and how many pivots a list is keyed by is chosen on the sample
for the number of vectors given: of the settings that reach the recall asked for, the one with the least postings and
comparisons. More vectors thus get more and finer lists.

Equal vectors (after scaling to length 1) are one entry with a multiplicity, so a group of copies costs one entry.
Verified pairs never leave the block as pairs: a block gives each vector its number of links and its block's
component, which is linear in the rows that entered it. A pair that shares more pivots counts in the list of its
smallest shared pivots only. Entries are named by a digest of their vector, so ids may be null or repeat.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import edges_to_components, hash_sample, materialise

COSINE = 0.95
#: Numbers of pivots, lengths of the pivot lists and sizes of the keys that calibration tries, and the recall at the
#: threshold that it asks for.
PIVOTS = (256, 1024, 4096)
NEAREST = (6, 8, 12, 16, 24)
SHARED = (2, 3, 4)
RECALL = 0.985
BLOCK = 1024
PIVOT_SAMPLE = 4096
#: More than the fewest pivots are tried where there are this many vectors for the square of their number.
PER_LIST = 1
#: Costs of a posting and of a pivot's distance in comparisons of two vectors.
POSTING, DISTANCE = 40.0, 0.25
#: A key holds pivot numbers of so many bits.
_BITS = 15


def unit_rows(vectors: list | np.ndarray, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows scaled to length 1 in double precision, and which rows are valid: right length, all finite, not zero."""
    ok = np.zeros(len(vectors), bool)
    out = np.zeros((len(vectors), dim))
    if isinstance(vectors, np.ndarray) and vectors.ndim == 2:
        ok = np.isfinite(vectors).all(axis=1) & vectors.any(axis=1)
        out[ok] = vectors[ok]
        vectors = ()
    for i, v in enumerate(vectors):
        if v is not None and len(v) == dim:
            row = np.array([np.nan if x is None else x for x in v] if not isinstance(v, np.ndarray) else v, dtype=np.float64)
            if np.isfinite(row).all() and row.any():
                out[i], ok[i] = row, True
    big = np.abs(out).max(axis=1, keepdims=True)
    out /= np.where(big > 0, big, 1)  # squares of very large or small values stay finite
    length = np.sqrt((out * out).sum(axis=1, keepdims=True))
    return out / np.where(length > 0, length, 1) + 0.0, ok


def sample_rows(vectors: DataFrame, total: int, sample: int = PIVOT_SAMPLE) -> np.ndarray:
    """Of the valid vectors the `sample` with the smallest id hash, scaled: all that comes to the driver to fit on."""
    rows = vectors.where(F.col("vector").isNotNull() & (F.size("vector") > 0))
    rows = hash_sample(rows, "vec_id", sample, total).select("vector").collect()
    if not rows:
        return np.zeros((0, 0))
    sizes = Counter(len(r.vector) for r in rows)
    x, ok = unit_rows([r.vector for r in rows], min(sizes, key=lambda n: (-sizes[n], n)))
    return np.unique(x[ok], axis=0)


def fit_pivots(x: np.ndarray, pivots: int = PIVOTS[0]) -> np.ndarray:
    """Reference points: rows of x spread by farthest-first order."""
    if len(x) == 0:
        return x
    near, chosen = x @ x[0], [0]
    while len(chosen) < min(pivots, len(x)):
        nxt = int(near.argmin())
        if near[nxt] > 0.999:
            break
        chosen.append(nxt)
        near = np.maximum(near, x @ x[nxt])
    return x[chosen]


def nearest_pivots(x: np.ndarray, pivots: np.ndarray, count: int) -> np.ndarray:
    """The ordered list of each row's nearest pivots (ties: the lower number)."""
    sims = x @ pivots.T
    if count < len(pivots):
        top = np.argpartition(-sims, count - 1, axis=1)[:, :count]
    else:
        top = np.tile(np.arange(len(pivots)), (len(x), 1))
    order = np.lexsort((top, -np.take_along_axis(sims, top, axis=1)), axis=1)
    return np.take_along_axis(top, order, axis=1).astype(np.int32)


def _meetings(x: np.ndarray, cosine: float) -> list[tuple[np.ndarray, np.ndarray]]:
    """Pairs to measure recall on: partners made to lie exactly at the threshold, and the similar pairs of the sample."""
    rng = np.random.default_rng(0)
    a = x[rng.integers(0, len(x), 2000)]
    u = rng.normal(size=a.shape)
    u -= (u * a).sum(axis=1, keepdims=True) * a
    u /= np.maximum(np.linalg.norm(u, axis=1, keepdims=True), 1e-300)
    pairs = [(a, cosine * a + np.sqrt(max(0.0, 1 - cosine * cosine)) * u)]
    part = x[rng.permutation(len(x))[:2048]]
    i, j = np.nonzero(np.triu(part @ part.T >= cosine, 1))
    if len(i):
        pick = rng.integers(0, len(i), 4000)
        pairs.append((part[i[pick]], part[j[pick]]))
    return pairs


def _in_common(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    return (p[:, :, None] == q[:, None, :]).sum(axis=(1, 2))


def calibrate(x: np.ndarray, cosine: float, total: int, pivots: tuple[int, ...] = PIVOTS, lengths: tuple[int, ...] = NEAREST, keys: tuple[int, ...] = SHARED, recall: float = RECALL) -> tuple[np.ndarray, int, int]:
    """(pivots, length of the lists, pivots in a key): the cheapest setting for `total` vectors that reaches the recall.

    Recall is measured by brute force on pairs of the sample and on partners made to lie at the threshold; the number of
    comparisons is that of random pairs of the sample. If no setting reaches the recall, the one with the best is taken.
    """
    points = fit_pivots(x, max(pivots))
    if len(points) < 2:
        return points, len(points), len(points)
    rng = np.random.default_rng(1)
    pairs, others = _meetings(x, cosine), (x[rng.integers(0, len(x), 20_000)], x[rng.integers(0, len(x), 20_000)])
    best = None
    for count in sorted({min(p, len(points)) for p in pivots}):
        some = points[:count]
        for length in sorted({min(n, count) for n in lengths}):
            near = lambda v: nearest_pivots(v, some, length)  # noqa: B023, E731
            met = [_in_common(near(p), near(q)) for p, q in pairs]
            apart = np.bincount(_in_common(near(others[0]), near(others[1])), minlength=length + 1) / len(others[0])
            for shared in keys:
                if shared > length:
                    continue
                reached = min(float((m >= shared).mean()) for m in met)
                work = POSTING * comb(length, shared) + DISTANCE * count + total / 2 * sum(n * comb(c, shared) for c, n in enumerate(apart))
                rank = (-min(reached, recall), work)
                if best is None or rank < best[0]:
                    best = (rank, some, length, shared)
    return best[1:]


def _packed(row: np.ndarray) -> bytes:
    with np.errstate(over="ignore"):
        s = row.astype(np.float32)
    return s.tobytes() if (s == row).all() else row.tobytes()


def _rows_of(column: pa.Array, dim: int) -> list | np.ndarray:
    """The vectors of a list column: one matrix where all have the right length and no nulls, else a list."""
    flat = column.flatten()
    if not column.null_count and not flat.null_count and (np.diff(column.offsets.to_numpy()) == dim).all():
        return flat.to_numpy().reshape(len(column), dim)
    return column.to_pylist()


def _index(pivots: np.ndarray, nearest: int):
    dim, l = pivots.shape[1] if len(pivots) else 0, min(nearest, len(pivots))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, len(batch), 4096):
                part = batch.slice(i, 4096)
                rows = _rows_of(part.column(1), dim)
                x, ok = unit_rows(rows, dim)
                top = nearest_pivots(x, pivots, l) if l else np.zeros((len(x), 0), np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column(0),
                        pa.array([hashlib.blake2b(r.tobytes(), digest_size=16).digest() if k else None for r, k in zip(x, ok)], pa.binary()),
                        pa.array([_packed(np.asarray(v, np.float64)) if k else None for v, k in zip(rows, ok)], pa.binary()),
                        pa.array([r.tolist() if k else None for r, k in zip(top, ok)], pa.list_(pa.int32())),
                    ],
                    ["vec_id", "digest", "vec", "perm"],
                )

    return run


class _Forest:
    """Union-find over small integers."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def union(self, i: int, j: int) -> None:
        i, j = self.find(i), self.find(j)
        if i != j:
            self.up[max(i, j)] = min(i, j)


def _verify_block(key: int, ids: np.ndarray, vecs: np.ndarray, perms: np.ndarray, n: np.ndarray, side: np.ndarray, cosine: float, shared: int):
    """Links of one block: for each vector with any, (id, number of links weighted by multiplicity, least id of its block component).

    side 0 and 1 mark the two halves of a block against block comparison; 2 marks a block compared with itself.
    Pairs are counted only in the list of the smallest pivots that they share (shared 0: there is one list).
    """
    a, b = np.flatnonzero(side != 1), np.flatnonzero(side != 0)
    own = np.array([key >> _BITS * (shared - 1 - i) & ((1 << _BITS) - 1) for i in range(shared)])
    gained, found = np.zeros(len(ids), np.int64), []
    for i in range(0, len(a), 512):
        rows = a[i : i + 512]
        r, c = np.nonzero(vecs[rows] @ vecs[b].T >= cosine - 1e-9)
        r, c = rows[r], b[c]
        keep = np.where(side[r] == 2, r < c, True)
        r, c = r[keep], c[keep]
        for j in range(0, len(r), 65536):
            rr, cc = r[j : j + 65536], c[j : j + 65536]
            same = perms[rr][:, :, None] == perms[cc][:, None, :]
            value = np.where(same.any(axis=2), perms[rr], np.int32(2**30))
            value.sort(axis=1)
            good = (value[:, :shared] == own).all(axis=1)
            good &= np.einsum("ij,ij->i", vecs[rr], vecs[cc]) >= cosine
            rr, cc = rr[good], cc[good]
            np.add.at(gained, rr, n[cc])
            np.add.at(gained, cc, n[rr])
            found.append(np.stack([rr, cc], axis=1))
    hit = np.flatnonzero(gained)
    if not len(hit):
        return None
    forest = _Forest(len(ids))
    for x, y in np.concatenate(found).tolist():
        forest.union(x, y)
    least: dict[int, bytes] = {}
    roots = [forest.find(x) for x in hit.tolist()]
    for x, root in zip(hit.tolist(), roots):
        least[root] = min(least.get(root, ids[x]), ids[x])
    return [ids[x] for x in hit.tolist()], gained[hit], [least[r] for r in roots]


def _doubles(raw: list, dim: int) -> np.ndarray:
    """The unit rows again, from the bytes that the index keeps: single precision where that loses nothing."""
    return unit_rows([np.frombuffer(r, np.float32 if len(r) == 4 * dim else np.float64) for r in raw], dim)[0]


def _links(cosine: float, shared: int, dim: int):
    """Blocks in sorted runs of (key, b1, b2) -> (rep, links, root)."""

    def settle(part: list[np.ndarray], s: int, e: int) -> pa.RecordBatch | None:
        found = _verify_block(int(part[0][s, 0]), *(y[s:e] for y in part[1:]), cosine, shared) if e - s > 1 else None
        return pa.RecordBatch.from_arrays([pa.array(found[0], pa.binary()), pa.array(found[1], pa.int64()), pa.array(found[2], pa.binary())], ["rep", "links", "root"]) if found else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[np.ndarray] | None = None
        for batch in batches:
            if not len(batch):
                continue
            names = np.empty(len(batch), object)
            names[:] = batch.column(3).to_pylist()
            part = [np.stack([batch.column(i).to_numpy() for i in range(3)], axis=1).astype(np.int64), names, _doubles(batch.column(4).to_pylist(), dim), batch.column(5).flatten().to_numpy().reshape(len(batch), -1), batch.column(6).to_numpy(), batch.column(7).to_numpy()]
            if rest is not None:
                part = [np.concatenate(x) for x in zip(rest, part)]
            starts = np.flatnonzero(np.r_[True, (part[0][1:] != part[0][:-1]).any(axis=1)])
            rest = [x[starts[-1] :] for x in part]
            for s, e in zip(starts[:-1], starts[1:]):
                if (found := settle(part, s, e)) is not None:
                    yield found
        if rest is not None and (found := settle(rest, 0, len(rest[1]))) is not None:
            yield found

    return run


def _keys(nearest: int, shared: int):
    """Keys of a vector's lists: the combinations of `shared` of its pivots, the smaller numbers first."""
    if not shared:  # fewer than two reference points: one list
        return F.array(F.lit(0).cast("long"))
    at = F.lit(0).cast("long")
    picks = F.array(*(F.array(*map(F.lit, c)) for c in combinations(range(nearest), shared)))
    return F.transform(picks, lambda c: sum((F.shiftleft(F.col("low")[c[i]].cast("long"), _BITS * (shared - 1 - i)) for i in range(shared)), at))


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", cosine: float = COSINE, pivots: int | None = None, nearest: int | None = None, shared: int | None = None, block: int = BLOCK) -> DataFrame:
    """One row per input row: vec_id, n_links, component_id, kept.

    vectors: any table with a whole-number id and an array of numbers; other columns are ignored whatever their
    names. Null, zero, non-finite and wrong-length vectors link with nothing: 0 links, own component. Repeated
    rows (equal vectors) link with each other. A row with a null id takes part and is counted, but names no component:
    alone it has none (null), and its kept is null. An empty table gives an empty result. pivots, nearest, shared:
    number of reference points, length of the pivot lists and pivots in a key; what isn't given is calibrated on the
    sample.
    """
    base = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("vector"))
    total = base.count()
    tried = (pivots,) if pivots else tuple(p for p in PIVOTS if p == min(PIVOTS) or PER_LIST * p * p <= total)
    sample = sample_rows(base, total, max(PIVOT_SAMPLE, 4 * max(tried)))
    points, nearest, shared = calibrate(sample, cosine, total, tried, (nearest,) if nearest else NEAREST, (shared,) if shared else SHARED)
    shared = shared if nearest >= 2 else 0
    index = base.mapInArrow(_index(points, nearest), "vec_id long, digest binary, vec binary, perm array<int>")
    index = materialise(index, "pivot-index")
    reps = index.where("digest IS NOT NULL").groupBy("digest").agg(F.min(F.struct("vec", "perm")).alias("r"), F.min("vec_id").alias("low_id"), F.count("*").alias("n"))
    reps = materialise(reps.select(F.col("digest").alias("rep"), "low_id", F.col("r.vec").alias("vec"), F.col("r.perm").alias("perm"), "n"), "pivot-reps")

    lists = reps.select("rep", F.array_sort("perm").alias("low")).select("rep", F.explode(_keys(nearest, shared)).alias("key"))
    sizes = materialise(lists.groupBy("key").agg(F.count("*").alias("m")).where("m > 1").select("key", F.ceil(F.col("m") / block).cast("int").alias("blocks")), "pivot-lists")
    posted = lists.join(sizes, "key").withColumn("b", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("o")
    posted = posted.select("rep", "key", "b", other)
    posted = posted.select("rep", "key", F.least("b", "o").alias("b1"), F.greatest("b", "o").alias("b2"), F.when(F.col("b") == F.col("o"), 2).when(F.col("b") < F.col("o"), 0).otherwise(1).alias("side"))
    posted = posted.join(reps.select("rep", "vec", "perm", "n"), "rep").select("key", "b1", "b2", "rep", "vec", "perm", "n", "side")
    found = posted.repartition("key", "b1", "b2").sortWithinPartitions("key", "b1", "b2").mapInArrow(_links(cosine, shared, points.shape[1] if len(points) else 0), "rep binary, links long, root binary")
    found = materialise(found, "pivot-links")
    degree = found.groupBy("rep").agg(F.sum("links").alias("links"))
    comps = edges_to_components(found.select(F.col("rep").alias("a"), F.col("root").alias("b")), "pivot")
    named = reps.select("rep", "low_id", "n").join(degree, "rep", "left").join(comps, F.col("rep") == F.col("node"), "left")
    named = materialise(named.select(F.col("rep").alias("digest"), "low_id", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("c")), "pivot-named")
    least = named.groupBy("c").agg(F.min("low_id").alias("component_id"))
    named = materialise(named.join(least, "c").select("digest", "n_links", "component_id"), "pivot-final")
    out = index.select("vec_id", "digest").join(named, "digest", "left")
    own = F.when(F.col("digest").isNull(), F.col("vec_id")).otherwise(F.col("component_id"))
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"))
    return out.withColumn("kept", F.col("component_id") == F.col("vec_id"))


def op1_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return near_duplicates(table(spark, sf_dir, "embeddings"))
