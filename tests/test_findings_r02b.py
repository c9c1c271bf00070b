"""Tests for the findings of the second review that were settled later."""

import math

import numpy as np
import pyarrow as pa

from formulary.llm import column_bwt, suffix_dedup
from formulary.llm.common import mix64, powers
from formulary.operators import dedup


def test_f7_lsh_meets_in_blocks_what_its_tables_meet(spark):
    rng = np.random.default_rng(11)
    base = rng.integers(0, 2, (20, 256))
    bits = np.concatenate([base, *(base ^ (rng.random((20, 256)) < p) for p in (0, 0.1, 0.2, 0.27, 0.3)), *[base[:1]] * 20])
    words = np.packbits(bits.astype(np.uint8), axis=1, bitorder="little").view(np.int64)
    ids = rng.permutation(len(bits)) * 3
    rows = [(int(i), w.tolist()) for i, w in zip(ids, words)]
    fps = spark.createDataFrame([*rows, rows[3], (0, words[7].tolist()), (9000, None), (None, words[0].tolist())], "doc_id long, fp array<long>")  # a row twice; an id with two fingerprints
    ids, bits = np.append(ids, 0), np.concatenate([bits, bits[7:8]])
    meet = math.comb(180, 12) / math.comb(256, 12)
    tables = math.ceil(math.log(0.01) / math.log1p(-meet))
    pick, met = np.random.default_rng(5), np.zeros((len(bits), len(bits)), bool)
    for _ in range(tables):
        chosen = bits[:, np.sort(pick.choice(256, 12, replace=False))]
        met |= (chosen[:, None] == chosen[None]).all(axis=2)
    dist = (bits[:, None] != bits[None]).sum(axis=2)
    x, y = np.nonzero(met & (dist <= 76) & (ids[:, None] < ids[None]))
    want = {(int(ids[a]), int(ids[b]), int(dist[a, b])) for a, b in zip(x, y)}
    for block in (1 << 18, 30):
        got = [(r.a, r.b, r.dist) for r in dedup.pairs_lsh(fps, block=block).collect()]
        assert len(got) == len(set(got)) and set(got) == want
    assert any(d > 70 for _, _, d in want) and sum(d == 0 for _, _, d in want) > 200


def test_op3_anchors_of_many_texts_are_those_of_each_window():
    """Also: what is hashed at once is a share of a core's cache, whether texts are short or long."""
    rng = np.random.default_rng(1)
    sizes = [0, 50, 39, 40, 41, 0, 3000, 3, 120, 44, 40] * 2
    data, offsets = rng.integers(97, 99, sum(sizes)).astype(np.uint8), np.concatenate([[0], np.cumsum(sizes)])
    want = {}
    for i, size in enumerate(sizes):
        text = data[offsets[i] : offsets[i + 1]].astype(np.uint64) + np.uint64(1)
        h = np.array([int(mix64((text[p : p + 32] * powers(32)).sum(keepdims=True))[0]) for p in range(size - 31)], object)
        for w in range(size - 39):
            least = min((int(h[p]) >> 22, p) for p in range(w, w + 9))[1]
            want[i, w] = (h[least], least)
    for stretch in (1 << 15, 64):
        keep, suffix_dedup._STRETCH = suffix_dedup._STRETCH, stretch
        try:
            rows = list(zip(*(x.tolist() for x in suffix_dedup.anchors(data, offsets, 40))))
        finally:
            suffix_dedup._STRETCH = keep
        got = {(i, w): (h, a) for i, h, a, first, last in rows for w in range(first, last + 1)}
        assert got == want and len(got) == sum(last - first + 1 for *_, first, last in rows)


def test_op3_runs_of_a_column_are_those_of_each_row():
    rng = np.random.default_rng(4)
    kind = pa.list_(pa.struct([("first", pa.int32()), ("end", pa.int32())]))
    spans = [None, [], [{"first": 0, "end": 9}, {"first": 9, "end": 12}], *([{"first": int(a), "end": int(a + n)} for a, n in zip(rng.integers(0, 90, k), rng.integers(1, 20, k))] for k in rng.integers(0, 8, 60))]
    column, repeated, sizes = pa.array([[{"first": 1, "end": 2}], *spans], kind)[1:], rng.random(len(spans)) < 0.3, rng.integers(0, 200, len(spans))
    got = suffix_dedup.run_lists(*suffix_dedup.merged_rows(column, repeated, sizes, 100)).to_pylist()
    assert [[(r["first"], r["end"]) for r in row] for row in got] == [suffix_dedup.merged(s, bool(r), int(n), 100) for s, r, n in zip(spans, repeated, sizes)]
    assert suffix_dedup.run_lists(*suffix_dedup.merged_rows(column[:0], repeated[:0], sizes[:0], 100)).to_pylist() == []


def test_op3_symbols_of_one_and_two_bytes_sort_stably():
    rng = np.random.default_rng(6)
    for high in (1, 200, 256, 257, 2000, 65536):
        symbols = rng.integers(0, high, 3000).astype(np.uint16)
        assert (column_bwt._order(symbols) == np.argsort(symbols, kind="stable")).all()
    assert len(column_bwt._order(np.empty(0, np.uint16))) == 0
