import hashlib
import os
import random
import re
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import public_tokenizers
import pytest
import xxhash

from formulary.llm import byte_gru, column_bwt, matroska, mixing, ngram_join, packing, quality_gam, suffix_dedup, token_counts
from formulary.llm.common import edges_to_components, table

from .conftest import SCHEMA, documents

os.environ["TOKENIZERS_PARALLELISM"] = "false"
VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(VOCABULARY)


def strange_texts(n, seed=5):
    rng = random.Random(seed)
    odd = ["\u0085", "\x1c", "᠎", "​", " ", "\xa0", "　", "\x00", "a", "B", "'s", "'", "  ", "\n", "1", "²", "é", "́", "中", "😀", "<|endoftext|>", "<|end", "aaaa", "!!", "\t"]
    return ["".join(rng.choice(odd) for _ in range(rng.randint(0, 30))) for _ in range(n)]


# ---- components


def test_components_match_union_find(spark):
    rng = random.Random(2)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)]
    up = {}

    def find(i):
        up.setdefault(i, i)
        while up[i] != i:
            i = up[i]
        return i

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    got = {r.node: r.component for r in edges_to_components(spark.createDataFrame(edges, "a long, b long"), "t").collect()}
    real = {i for e in edges if e[0] != e[1] for i in e}
    assert got == {i: find(i) for i in real}


def test_components_of_nothing(spark):
    assert edges_to_components(spark.createDataFrame([], "a long, b long"), "t").count() == 0


# ---- token counts


def test_counts_equal_the_library(library):
    m = token_counts.RankMerger(VOCABULARY, cache=50)
    texts = [*strange_texts(800), "a" * 20_000, " " * 20_000 + "b", "ab" * 9_000]
    assert token_counts.count_batch(m, texts) == [len(e.ids) for e in library.encode_batch(texts, add_special_tokens=False)]


def test_token_query_on_odd_rows(odd, library):
    rows = token_counts.count_tokens(odd, VOCABULARY).collect()
    assert len(rows) == odd.count()
    want = sorted(((r.doc_id or -1), len((r.text or "").encode()), len(library.encode(r.text or "", add_special_tokens=False).ids)) for r in odd.collect())
    assert sorted(((r.doc_id or -1), r.n_bytes, r.n_tokens) for r in rows) == want
    assert all(r.over_limit == (r.n_tokens > 512) for r in rows)


# ---- packing


def test_ids_equal_the_library(library):
    enc = packing.Encoder(VOCABULARY)
    for t in [*strange_texts(300, 9), "x " * 700_000]:
        assert enc.ids(t).tolist() == library.encode(t, add_special_tokens=False).ids


def test_best_fit_places_as_the_rule_says():
    fit = packing.BestFit(10, open_bins=2)
    assert [fit.place(n) for n in (6, 7, 3, 4)] == [(0, 0), (1, 0), (1, 7), (0, 6)]
    assert [fit.place(n) for n in (6, 8, 9, 4)] == [(2, 0), (3, 0), (4, 0), (2, 6)]
    with pytest.raises(ValueError):
        fit.place(11)


def test_cut_makes_only_the_first_piece_short():
    assert packing.cut(1, 4) == [(0, 1)] and packing.cut(4, 4) == [(0, 4)] and packing.cut(9, 4) == [(0, 1), (1, 4), (5, 4)]


def test_packing_is_gapless_and_whole(odd, library):
    got = packing.pack_documents(odd, VOCABULARY).toPandas()
    for _, g in got.groupby("sequence_id"):
        g = g.sort_values("offset")
        assert g.length.sum() <= 1024 and (g.offset == g.length.cumsum() - g.length).all()
    ids = {r.doc_id: [*library.encode(r.text or "", add_special_tokens=False).ids, 2] for r in odd.collect() if r.doc_id is not None}
    for r in got[got.doc_id.notna()].itertuples():
        part = np.array(ids[r.doc_id][r.start : r.start + r.length], "<u4")
        assert len(part) == r.length and zlib.crc32(part.tobytes()) == r.ids_crc32
    assert got[got.doc_id == 3].length.sum() == 2 * len(ids[3])


def test_packing_is_tight(spark):
    rng = random.Random(1)
    rows = spark.createDataFrame([(i, rng.randint(1, 1024)) for i in range(4000)], "doc_id long, length long")
    got = packing.pack(rows.coalesce(1)).toPandas()
    assert got.sequence_id.nunique() <= 1.06 * got.length.sum() / 1024 + 4


# ---- repeats


def naive_repeats(texts, width):
    raws = [(x or "").encode() for x in texts]
    seen = Counter(xxhash.xxh3_128_intdigest(r[i : i + width]) for r in raws for i in range(len(r) - width + 1))
    out = []
    for r in raws:
        gone = np.zeros(len(r), bool)
        for j in range(len(r) - width + 1):
            if seen[xxhash.xxh3_128_intdigest(r[j : j + width])] > 1:
                gone[j : j + width] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((len(r), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(r, np.uint8)[~gone].tobytes()).hexdigest()))
    return out


def test_column_build_gives_order_transform_and_prefixes():
    rng = np.random.default_rng(0)
    for _ in range(40):
        s = [rng.integers(1, rng.integers(2, 5), rng.integers(0, 20)).astype(np.uint16) for _ in range(rng.integers(0, 7))]
        order = sorted(((tuple(x[o:]), k, o) for k, x in enumerate(s) for o in range(len(x) + 1)), key=lambda t: t[0])
        bwt, lcp, places = column_bwt.build(s, 1000)
        at = {int(p): (k, o) for k, x in enumerate(places) for o, p in enumerate(x)}
        assert [tuple(s[at[i][0]][at[i][1] :]) for i in range(len(order))] == [t[0] for t in order]
        for i in range(len(order)):
            k, o = at[i]
            assert bwt[i] == (s[k][o - 1] if o else 0)
            if i:
                a, b = order[i - 1][0], order[i][0]
                assert lcp[i] == len(os.path.commonprefix([a, b]))


@pytest.mark.parametrize("tuning", [{}, {"flanks": 3, "build": 10}])
def test_repeats_match_brute_force(spark, tuning):
    rng = np.random.default_rng(1)
    letters = list("abcdefgh é\n")
    text = lambda n: "".join(rng.choice(letters, n))
    shared = [text(n) for n in (390, 395, 420, 700, 1500)]
    rows = [(i, text(rng.integers(0, 600)) + shared[rng.integers(0, 5)] + text(rng.integers(0, 600)) + (shared[rng.integers(0, 5)] if i % 3 == 0 else "")) for i in range(120)]
    rows += [(1000, None), (1001, ""), (1002, "x" * 3000), (1003, "ab" * 300), (1004, shared[4]), (1005, shared[4]), (1005, "short"), (1006, "short"), (1007, "y" * 400), (1008, "z" * 399), (None, shared[3])]
    got = suffix_dedup.repeat_digest(documents(spark, rows), **tuning).collect()
    want = naive_repeats([t for _, t in rows], 400)
    assert sorted((r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == sorted(want)
    assert sorted((r.n_bytes, r.passage_bytes, r.n_passages) for r in got) == sorted(x[:3] for x in naive_repeats([t for _, t in rows], 240))
    alone = suffix_dedup.repeat_digest(documents(spark, rows), passage=None, **tuning).collect()
    assert sorted((r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in alone) == sorted(want)


def test_repeats_on_given_documents(spark, data):
    docs = table(spark, data, "documents")
    rows = docs.select("doc_id", "text").collect()
    found = suffix_dedup.repeat_digest(docs).collect()
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in found}
    assert got == dict(zip((r.doc_id for r in rows), naive_repeats([r.text for r in rows], 400)))
    passages = naive_repeats([r.text for r in rows], 240)
    assert {r.doc_id: (r.passage_bytes, r.n_passages) for r in found} == {r.doc_id: x[1:3] for r, x in zip(rows, passages)}


def test_repeats_of_odd_and_no_rows(spark, odd):
    got = suffix_dedup.repeat_digest(odd).collect()
    assert sorted((r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == sorted(naive_repeats([r.text for r in odd.collect()], 400))
    assert suffix_dedup.repeat_digest(spark.createDataFrame([], SCHEMA)).count() == 0
    kept = suffix_dedup.remove_repeats(odd, whole_characters=True)
    assert set(odd.columns) <= set(kept.columns) and kept.count() == odd.count()


# ---- Jaccard join


def naive_groups(rows, k, percent):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} or ({tuple(w)} if w else set())
    up = {i: i for i in sets}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in sets:
        for j in sets:
            if j < i and sets[i] and sets[j]:
                both = len(sets[i] & sets[j])
                if 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                    a, b = find(i), find(j)
                    up[max(a, b)] = min(a, b)
    return {i: (len(s), find(i)) for i, s in sets.items()}


@pytest.mark.parametrize("tuning", [{}, {"block": 20, "headed": 11, "frequent": 6}, {"words": 5, "percent": 60, "block": 7, "headed": 4, "frequent": 3}])
def test_join_matches_brute_force(spark, tuning):
    rng = np.random.default_rng(3)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(150):
        w = list(base)
        for j in rng.integers(0, 120, rng.integers(1, 7)):
            w[j] = f"x{i}_{j}"
        rows.append((i, " ".join(w)))
    rows += [(400 + i, " ".join(f"q{i}_{j}" for j in range(30)) + " " + " ".join(base[:8])) for i in range(40)]
    rows += [(450 + i, " ".join(base[: 20 + 3 * i])) for i in range(33)]  # prefixes of one text: many sizes in one group
    rows += [(600, None), (601, ""), (602, "a b"), (603, "A  B"), (604, "a b c d"), (605, " \n"), (606, "a b"), (607, "É"), (608, "é")]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_groups(documents(spark, rows), **tuning).collect()}
    assert got == naive_groups(rows, tuning.get("words", 4), tuning.get("percent", 85))


def test_join_of_the_same_copies_stored_in_other_orders(spark):
    texts = [" ".join(f"w{i}" for i in range(60)) + f" end{v}" for v in range(4)]
    orders = [(0, 1, 2, 3), (3, 2, 1, 0), (2, 3, 0, 1), (1, 0, 3, 2)]
    docs = spark.createDataFrame(spark.sparkContext.parallelize([(10 * k + v, texts[v]) for k, o in enumerate(orders) for v in o], 4), "doc_id long, text string")
    assert {r.component_id for r in ngram_join.jaccard_groups(docs).collect()} == {0}


def test_buckets_are_bounded():
    assert ngram_join.bucket_count(0) == 64 == ngram_join.bucket_count(10**9)
    assert all(n / ngram_join.bucket_count(n) <= 1 << 24 for n in (10**9, 10**10, 10**13))


def test_a_token_is_sent_once_a_chunk():
    tokens = np.random.default_rng(1).integers(1, 1 << 63, 500).astype(np.uint64)
    order, first, fp, at = ngram_join._blocks(np.concatenate([tokens, tokens[:100], tokens[:100]]), 7)
    assert len(fp) == 500 == at[-1] and sorted(np.diff(np.append(first, len(order))).tolist()) == [1] * 400 + [3] * 100


def test_prefix_keys_of_similar_sets_meet():
    rng = np.random.default_rng(0)
    for _ in range(200):
        n = int(rng.integers(5, 200))
        a = np.unique(rng.integers(1, 1 << 60, n).astype(np.uint64))
        swap = int(rng.integers(0, max(1, len(a) // 13)))
        b = np.unique(np.concatenate([a[swap:], rng.integers(1, 1 << 60, swap).astype(np.uint64)]))
        both = len(np.intersect1d(a, b))
        if 100 * both < 85 * (len(a) + len(b) - both):
            continue
        keys = []
        for s in (a, b):
            code = np.where(np.isin(s, a) & np.isin(s, b), (s % np.uint64(200)) + np.uint64(1), 0).astype(np.uint8)
            order = np.lexsort((s, code))
            keys.append(set(ngram_join.prefix_keys(s[order], code[order], 85, frequent=4, classes=5).tolist()))
        assert keys[0] & keys[1]


def test_join_on_odd_and_no_rows(spark, odd):
    got = ngram_join.jaccard_groups(odd).collect()
    assert len(got) == odd.count()
    assert {(r.doc_id, r.component_id) for r in got} == {(None, None), (1, 1), (2, 2), (3, 3), (4, 4), (5, 5), (6, 3), (7, 7), (8, 8)}
    assert ngram_join.jaccard_groups(spark.createDataFrame([], SCHEMA)).count() == 0


# ---- quality


def test_quality_is_learned(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    got = quality_gam.score(docs, quality_gam.train(docs, labels)).join(labels, "doc_id").where("held_out").toPandas()
    assert all(zlib.crc32(str(i).encode()) % 5 == 0 for i in got.doc_id)
    assert ((got.predicted == got.quality).mean()) > 0.98


def test_tables_learn_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((4000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    model = quality_gam.fit(x, y)
    assert (0, 1) in model.pairs and ((model.score(x) > 0.5) == y).mean() > 0.95


def test_quality_of_odd_rows_and_without_labels(spark, odd):
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    rows = quality_gam.score(odd, quality_gam.train(odd, empty)).collect()
    assert len(rows) == odd.count() and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in rows)


# ---- language


def test_gradients_match_differences():
    rng = np.random.default_rng(0)
    m = byte_gru.new_model(["a", "b", "c"], 4)
    for p in m.parameters():
        p += rng.normal(0, 0.2, p.shape).astype(np.float32)
    rows, target, weight = rng.integers(0, 256, (7, 5)).astype(np.uint8), rng.integers(0, 3, 5), np.ones((7, 5), np.float32)
    weight[5:, 2] = 0
    _, grads = byte_gru.gradients(m, rows, target, weight)
    for p, g in zip(m.parameters(), grads):
        i = tuple(np.argwhere(np.abs(g) == np.abs(g).max())[0])
        kept = p[i]
        p[i] = kept + 1e-2
        up, _ = byte_gru.gradients(m, rows, target, weight)
        p[i] = kept - 1e-2
        down, _ = byte_gru.gradients(m, rows, target, weight)
        p[i] = kept
        assert abs((up - down) / 2e-2 - g[i]) < 2e-3


def test_language_is_learned_on_held_out_documents(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    got = byte_gru.identify(docs, byte_gru.train(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang_pred == got.lang).mean() > 0.97


def test_language_of_odd_rows(spark, odd):
    model = byte_gru.fit([b"the of and " * 9, "é è ça le ".encode() * 9], ["en", "fr"], ["en", "fr"], steps=30)
    got = {r.doc_id: (r.lang_pred, r.score) for r in byte_gru.identify(odd, model).collect()}
    assert got[1] == got[2] == got[5] == got[8] == ("und", 0.0) and got[4][0] in ("en", "fr")
    assert byte_gru.train(odd) is None
    assert {r.lang_pred for r in byte_gru.identify(odd, None).collect()} == {"und"}


# ---- media


@pytest.mark.parametrize("n", [0, 1, 63, 64, 65, 511, 513, 2000, 70_000])
def test_media_round_trip(n):
    payload = matroska.padded(os.urandom(n))
    stored = matroska.write_pcm(payload)
    m = matroska.parse(stored)
    assert matroska.read_payload(stored, m) == payload and not m.truncated
    assert m.tracks[1]["codec"] == "A_PCM/INT/LIT" and len(m.cues) == m.clusters
    assert [p[1] for p in m.packets] == [i * 64 * 1_000_000_000 // 8000 for i in range(len(m.packets))]


@pytest.mark.parametrize("kind,sizes", [("xiph", [10, 255, 600, 3]), ("ebml", [500, 20, 9000, 1, 7]), ("fixed", [33, 33, 33]), ("none", [5])])
def test_lacings(kind, sizes):
    frames = [os.urandom(s) for s in sizes]
    flags, body = matroska.lace(frames, kind)
    assert [body[a : a + n] for a, n in matroska.frame_ranges(body, 0, len(body), flags >> 1)] == frames


def test_block_groups_unknown_sizes_and_cut_files():
    group = matroska.element(matroska.BLOCK_GROUP, matroska.element(matroska.BLOCK, b"\x81\x00\x05\x00abc") + matroska.unsigned(matroska.BLOCK_DURATION, 4))
    cluster = matroska.CLUSTER.to_bytes(4, "big") + b"\x01" + b"\xff" * 7 + matroska.unsigned(matroska.TIMESTAMP, 100) + group
    data = matroska.element(matroska.EBML, b"") + matroska.SEGMENT.to_bytes(4, "big") + b"\xff" + cluster + cluster
    m = matroska.parse(data)
    assert m.clusters == 2 and [(p[1], data[p[2] : p[2] + p[3]], p[4]) for p in m.packets] == [(105_000_000, b"abc", True)] * 2
    whole = matroska.write_pcm(os.urandom(4096))
    cut = matroska.parse(whole[: len(whole) // 2])
    assert cut.truncated and cut.packets
    with pytest.raises(matroska.Broken):
        matroska.parse(b"RIFF....")


def test_media_of_odd_rows(spark, odd):
    got = matroska.media_digest(odd).collect()
    for r in got:
        assert r.payload_bytes % 64 == 0 and r.payload_bytes >= 64
    want = sorted(hashlib.sha256(matroska.padded((r.text or "").encode())).hexdigest() for r in odd.collect())
    assert sorted(r.payload_sha256 for r in got) == want
    media = matroska.media_column(odd)
    packets = matroska.packet_table(media.union(spark.createDataFrame([(99, None), (98, bytearray(b"junk"))], "id long, media binary")), "id", "media")
    assert {r.status.split(":")[0] for r in packets.select("status").distinct().collect()} == {"ok", "null", "broken"}


# ---- mixing


def test_rates_meet_targets(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    got = mixing.mix(docs, labels).toPandas()
    assert (got.rate >= 0).all() and len(got) == 1000
    expected = np.array([(got.tokens * got.rate * got[f"p_{n}"]).sum() for n in mixing.DOMAINS])
    goal = np.array([mixing.TARGETS[n] for n in mixing.DOMAINS]) * got.tokens.sum()
    assert np.abs(expected - goal).max() < 2e-3 * goal.sum()


def test_step_solves_the_whole_problem_in_numpy(spark):
    rng = np.random.default_rng(0)
    p = rng.dirichlet([0.3, 0.3, 0.3], 300)
    n = rng.integers(1, 50, 300)
    members = spark.createDataFrame(pd.DataFrame({"doc_id": range(300), "tokens": n, **{f"p_{x}": p[:, j] for j, x in enumerate(mixing.DOMAINS)}}), mixing._MEMBER)
    history, now, goal = mixing.fit_rates(members, {"clean": 0.7, "junk": 0.2, "toxic": 0.1}, steps=200, tolerance=1e-9)
    r = mixing.rates(p, history)
    assert np.allclose((n * r) @ p, now) and np.abs(now - goal).max() < 1e-6 * goal.sum()


def test_mixture_meets_its_targets_in_tokens(spark):
    rng = np.random.default_rng(2)
    words = {n: [f"{n}{i}" for i in range(40)] for n in mixing.DOMAINS}
    kind = rng.choice(3, 4_000, p=[0.75, 0.11, 0.14])
    rows = [(i, " ".join(rng.choice(words[mixing.DOMAINS[k]], 30))) for i, k in enumerate(kind)]
    labels = spark.createDataFrame([(i, int(k != 1), int(k == 2)) for i, k in enumerate(kind.tolist())], "doc_id long, quality int, toxic int")
    out = mixing.resample(documents(spark, rows), labels, keep="clean").select("doc_id").toPandas()
    got = np.bincount(kind[out.doc_id], minlength=3)
    share = got / got.sum()
    assert got[0] == (kind == 0).sum()
    assert abs(share[1] - 0.04) < 0.012 and abs(share[2] - 0.005) < 0.004


def test_mixing_of_odd_rows(spark, odd):
    labels = spark.createDataFrame([(3, 1, 0), (4, 0, 0), (4, 1, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert mixing.mix(odd, labels).count() == odd.count()
    assert mixing.mix(odd, labels.limit(0)).count() == odd.count()
    assert mixing.resample(odd, labels).columns == odd.columns


def test_copies_keep_the_mean():
    rate = np.full(20_000, 1.3)
    draw = np.random.default_rng(0).random(20_000)
    assert abs(mixing.copies(rate, draw).mean() - 1.3) < 0.02
    assert mixing.copies(np.array([0.95, 0.05, 0.5]), np.array([0.0, 0.99, 0.6]), 0.1).tolist() == [1, 0, 1]


# ---- ids


def test_large_ids_stay_whole_beside_a_null(spark):
    big = 2**53 + 1
    df = documents(spark, [(big, "one two"), (None, "three"), (big + 2, None)]).coalesce(1)
    want = [None, big, big + 2]
    order = lambda rows: sorted((r[0] for r in rows), key=lambda i: i or 0)
    assert order(token_counts.count_tokens(df, VOCABULARY).collect()) == want
    assert order(packing.pack_documents(df, VOCABULARY).collect()) == want
    assert order(matroska.media_digest(df).collect()) == want
    files = matroska.media_column(df)
    assert order(files.collect()) == want
    assert order(matroska.packet_table(files, "id", "media").select("id").distinct().collect()) == want


def test_packing_keeps_columns_of_any_name(spark):
    rows = spark.createDataFrame([(1, 5, 9, 7), (2, None, 9, 7), (3, 0, 9, 7), (4, 1024, 9, 7)], "doc_id long, length long, deal int, offset int")
    got = {r.doc_id: r for r in packing.pack(rows).collect()}
    assert packing.pack(rows).columns == ["doc_id", "length", "deal", "sequence_id", "offset"] and {r.deal for r in got.values()} == {9}
    assert got[2].sequence_id is None and got[3].offset is None and got[1].offset == got[4].offset == 0


@pytest.mark.parametrize("body", [b"\x00" * 3, b"\x7f\xf8" + b"\x00" * 6, b"\x7f\x80\x00\x00"])
def test_floats_that_are_none_break_a_file_only(spark, body):
    audio = matroska.element(matroska.AUDIO, matroska.element(matroska.SAMPLING, body))
    tracks = matroska.element(matroska.TRACKS, matroska.element(matroska.TRACK_ENTRY, matroska.element(matroska.CODEC_ID, b"A_PCM/INT/LIT") + audio))
    raw = matroska.element(matroska.EBML, b"") + matroska.element(matroska.SEGMENT, tracks)
    got = matroska.packet_table(spark.createDataFrame([(1, bytearray(raw)), (2, bytearray(matroska.write_pcm(bytes(64))))], "id long, media binary"), "id", "media").collect()
    assert {r.id: r.status.split(":")[0] for r in got} == {1: "broken", 2: "ok"}
