"""One test for each finding of the second review."""

import re

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from formulary.functions import columns as C
from formulary.operators import dedup
from formulary.registry import QUERIES
from formulary.workloads import ORACLES


def against_sql(spark, tmp_path, name, tables):
    """The rows of a query and of its SQL on small tables: name -> (rows, schema)."""
    con = duckdb.connect()
    for t, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / f"{t}.parquet"))
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    key = lambda r: tuple((v is None, v) for v in r)
    got = QUERIES[name](spark, str(tmp_path))
    assert got.columns == [c[0] for c in con.execute(ORACLES[name]).description]
    got, want = sorted(map(tuple, got.collect()), key=key), sorted(con.execute(ORACLES[name]).fetchall(), key=key)
    assert got == want
    return got


@pytest.mark.parametrize("lines, kept", [([(1, 40.0), (2, 10.0)], [2]), ([(1, 10.0)], [None, 1, 2]), ([(1, 40.0), (None, 50.0)], []), ([(None, 5.0), (2, 31.0)], [1])])
def test_f1_not_in_joins_by_key(spark, tmp_path, lines, kept):
    orders = [(1, 7), (2, 7), (3, 8), (4, None), (None, 7)]
    got = against_sql(spark, tmp_path, "sub_in", {"orders": (orders, "o_orderkey long, o_custkey long"), "customer": ([(7, "BUILDING"), (8, "OTHER")], "c_custkey long, c_mktsegment string"), "lineitem": (lines, "l_orderkey long, l_quantity double")})
    assert [r[0] for r in got] == sorted(kept, key=lambda v: (v is None, v or 0))
    plan = QUERIES["sub_in"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "LeftAnti" in plan and "isnull((o_orderkey" not in plan  # no null-aware anti join, whose list is broadcast whole


def test_f8_ties_go_to_the_lowest_key(spark, tmp_path):
    rows = [(k, c, p) for k, (c, p) in enumerate([(1, 5.0), (1, 9.0), (1, 9.0), (2, None), (3, None), (3, 1.0), (1, 9.0)])] + [(None, 3, 7.0)]
    assert against_sql(spark, tmp_path, "agg_argmax", {"orders": (rows, "o_orderkey long, o_custkey long, o_totalprice double")}) == [(1, 1), (2, None), (3, 5)]


def test_f10_theta_counts_more_parts_than_a_sketch_holds(spark, tmp_path):
    rows = spark.range(-70_000, 130_000).selectExpr("id AS l_partkey", "if(id % 2 = 0, 'A', 'R') AS l_returnflag")
    rows = rows.unionByName(rows.limit(1000)).unionByName(spark.sql("SELECT CAST(NULL AS BIGINT) AS l_partkey, 'A' AS l_returnflag UNION ALL SELECT NULL, 'N'"))
    rows.write.parquet(str(tmp_path / "lineitem.parquet"))
    assert {tuple(r) for r in QUERIES["sketch_theta"](spark, str(tmp_path)).collect()} == {("A", 100_000), ("R", 100_000), ("N", 0)}


def test_f12_recursion_counts_orders(spark, tmp_path):
    rows = [(1.0,), (1.99,), (2.0,), (0.5,), (None,), (524_288.0,), (1_048_575.5,), (1_048_576.0,)]
    got = against_sql(spark, tmp_path, "cte_recursive", {"orders": (rows, "o_totalprice double")})
    assert [r[2] for r in got] == [2, 1] + [0] * 17 + [2] and got[19][:2] == (20, 524_288)


def test_f13_settings_are_applied_to_the_corpus(spark, tmp_path):
    rows = [("a b\nc", "x"), ("", "x"), (None, "y"), ("d", "z")]
    got = against_sql(spark, tmp_path, "hyper_parameters", {"documents": (rows, "text string, source string")})
    assert {r[7]: r[8:] for r in got} == {"x": (3, 4.9e9), "y": (0, None), "z": (1, 1.47e10), "all": (4, 3.675e9)}


def test_f2_sweep_counts_every_pair_of_all_widths_at_once(spark):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2, (30, 256))
    bits = np.concatenate([base ^ (rng.random((30, 256)) < p) for p in (0, 0.05, 0.15, 0.3, 0.4)])
    ids = rng.permutation(150) // 2 * 7  # every id twice, in no order: such rows are no pair
    words = np.packbits(bits.astype(np.uint8), axis=1, bitorder="little").view(np.int64)
    fps = spark.createDataFrame([(int(i), w.tolist()) for i, w in zip(ids, words)] + [(5000, None), (None, words[0].tolist())], "doc_id long, fp array<long>")
    got = {(r.bits, r.tau): (r.pairs, r.removable) for r in dedup.sweep_widths(fps, (0.6, 0.7, 0.8, 0.9), (64, 128, 256), block=40).collect()}
    for w in (64, 128, 256):
        dist = (bits[:, None, :w] != bits[None, :, :w]).sum(axis=2)
        for t in (0.6, 0.7, 0.8, 0.9):
            near = (dist <= int((1 - t) * w + 1e-9)) & (ids[:, None] < ids[None])
            assert got.pop((w, t)) == (near.sum(), len(set(ids[near.any(axis=0)])))
    assert not got


def test_f2_fingerprints_are_majorities_of_distinct_shingles(spark):
    texts = ["a b c a b c d", "A, b; c!", "one", "one two", "", None, " ".join(f"w{i}" for i in range(900)), "x " * 50]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    wide, narrow = ({r.doc_id: r.fp for r in dedup.fingerprint(docs, b).collect()} for b in (256, 64))
    tokens = {r.t: np.uint64(r.h % 2**64) for r in docs.select(F.explode(C.tokens(F.col("text"))).alias("t")).select("t", F.xxhash64("t").alias("h")).collect()}
    for i, text in enumerate(texts):
        w = [x for x in re.split(r"[^a-z0-9]+", (text or "").lower()) if x]
        shingles = {tuple(w[k : k + 3]) for k in range(max(1, len(w) - 2))} if w else set()
        if not shingles:
            assert wide[i] is None and narrow[i] is None
            continue
        hashes = np.array([int(dedup.shingle_hashes(np.array([tokens[x] for x in s], np.uint64), np.array([len(s)]), 3)[0][0]) for s in shingles], np.uint64)
        want = [sum(1 << b for b in range(64) if 2 * (((x := dedup._mix(hashes ^ np.uint64((k + 1) * dedup._GOLD % 2**64))) >> np.uint64(b)) & np.uint64(1)).sum() > len(x)) for k in range(4)]
        assert [v % 2**64 for v in wide[i]] == want and narrow[i] == wide[i][:1]


def _near_texts():
    """Texts whose shares of common shingles lie around 0.7, with copies, short ones and empty ones."""
    rng = np.random.default_rng(8)
    base = [[f"w{rng.integers(400)}" for _ in range(60)] for _ in range(12)]
    texts = [" ".join(w) for w in base]
    for w in base:
        for cut in (2, 6, 9, 10, 11, 14):
            texts.append(" ".join(w[: 60 - cut] + [f"v{rng.integers(400)}" for _ in range(cut)]))
    return [*texts, texts[0], texts[0].upper() + " .", texts[20], "one two", "one  two!", "one", "", None, "common words here " * 3]


def test_f6_jaccard_pairs_shuffle_keys_and_find_all(spark, tmp_path):
    texts = _near_texts()
    got = against_sql(spark, tmp_path, "jaccard_pairs", {"documents": ([(int(i) * 3, t) for i, t in enumerate(texts)], "doc_id long, text string")})
    assert any(r[2] < r[3] for r in got) and len(got) > 60
    h = np.arange(7, dtype=np.uint64)
    assert dedup.prefix_keys(h, np.array([0, 7]), np.array([9, 0, 5, 9, 9, 9, 9], np.uint8), 70)[0].tolist() == [1, 2, 0]


def test_f3_minhash_pairs_are_verified_pairs_of_one_key_each(spark, tmp_path):
    texts = _near_texts()
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    every = {(r.a, r.b) for r in dedup.jaccard_pairs(docs).collect()}
    found = [(r.a, r.b) for r in dedup.minhash_pairs(docs).collect()]
    assert len(found) == len(set(found)) and set(found) <= every and len(found) >= 0.95 * len(every)
    h, size = np.array([5, 9, 5, 9, 7], np.uint64), np.array([2, 0, 2, 1])
    keys, many = dedup.band_keys(h, size, 16, 4)
    assert many.tolist() == [16, 0, 16, 16] and (keys[:16] == keys[16:32]).all() and len(set(keys.tolist())) == 32
