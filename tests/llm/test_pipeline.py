"""The pipeline's stages against brute force, each on its own input, and the whole run on small and empty tables."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from formulary.llm import byte_gru, mixing

from .conftest import SCHEMA, documents
from .test_text_operators import naive_groups, naive_repeats

WORDS = {
    "en": "the of and to in is that for it as with was on by this house water people garden morning".split(),
    "fr": "le la les des une est que pour dans avec sur mais maison jardin matin où été très près".split(),
    "de": "der die und das ist nicht mit auf für eine auch haus wasser garten morgen über können schön".split(),
}


def prose(rng, lang, n):
    return " ".join(rng.choice(WORDS[lang]) + rng.choice(["", "", "s", "n"]) for _ in range(n))


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    """Documents in three languages with exact and near copies, shared passages, odd texts, null and repeated ids."""
    rng, rows = random.Random(7), []
    passage = prose(rng, "en", 90)
    for i in range(240):
        lang = ("en", "fr", "de")[i % 3]
        rows.append((i, prose(rng, lang, rng.randint(60, 160)) + (" " + passage + " " + prose(rng, lang, 40) if i % 20 == 0 else ""), lang if i % 7 else None))
    near = rows[3][1].split()
    near[5] = "changed"
    rows += [(500, rows[3][1], "en"), (501, " ".join(near), "en"), (None, rows[4][1], "fr"), (None, "only here " + prose(rng, "en", 80), "en"), (502, None, None), (503, "", "en"), (504, "123 456", "en"), (505, rows[6][1], None), (505, rows[6][1], None), (6, rows[9][1], "en")]
    folder = str(tmp_path_factory.mktemp("pipeline"))
    documents(spark, rows).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, int(i % 5 > 0), int(i % 15 == 0)) for i in range(0, 240, 2)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def docs_of(spark, folder):
    return spark.read.parquet(f"{folder}/documents.parquet")


def test_language_stage(spark, tables):
    docs = docs_of(spark, tables)
    got = pipeline.language(spark, docs, tables)
    assert got.columns == docs.columns and got.where("lang IS NULL").count() == 0
    kept = {(r.doc_id, r.text) for r in got.collect()}
    rows, model = docs.collect(), byte_gru.train(docs)
    for r in rows:
        if not any(c.isalpha() for c in r.text or ""):
            assert (r.doc_id, r.text) not in kept
            continue
        raw = np.frombuffer(r.text.encode(), np.uint8)
        whole = byte_gru.position_probabilities(model, raw[:, None])[:, 0].mean(axis=0)  # one pass over the whole text
        pooled = byte_gru.pooled(model, raw, np.array([0, len(raw)]))[0]
        assert np.abs(whole - pooled).max() < 0.1 and whole.argmax() == pooled.argmax()  # stretches start with 12 bytes of state
        if abs(whole.max() - pipeline.LANGUAGE_LEAST) > 0.1:
            assert ((r.doc_id, r.text) in kept) == (whole.max() >= pipeline.LANGUAGE_LEAST)


def test_near_duplicate_stage(spark, tables):
    docs = docs_of(spark, tables)
    got = pipeline.near_duplicates(spark, docs, tables)
    assert got.columns == docs.columns
    rows = docs.collect()
    group = naive_groups(list(enumerate(r.text for r in rows)), pipeline.WORDS, pipeline.PERCENT)
    best = {}
    for k, r in enumerate(rows):
        if group[k][0]:
            best.setdefault(group[k][1], []).append((r.doc_id is None, r.doc_id))
    want = [min(v) for v in best.values()] + [(r.doc_id is None, r.doc_id) for k, r in enumerate(rows) if not group[k][0]]
    assert sorted(((r.doc_id is None, r.doc_id) for r in got.collect()), key=str) == sorted(want, key=str)


def test_passage_stage(spark, tables):
    docs = docs_of(spark, tables)
    rows, got = docs.collect(), pipeline.repeated_passages(spark, docs, tables).collect()
    want = naive_repeats([r.text for r in rows], pipeline.REPEAT_BYTES)
    left = sorted((len((r.text or "").encode()), r.doc_id or -1) for r in got)
    assert all(r.n_chars == len(r.text or "") for r in got)
    mine = sorted((n - gone, r.doc_id or -1) for r, (n, gone, _, _) in zip(rows, want) if n - gone or not n)
    # characters that a run would cut stay whole: at most three bytes at either end of a run
    assert [i for _, i in sorted(left, key=lambda x: x[1])] == [i for _, i in sorted(mine, key=lambda x: x[1])]
    spans = sum(x[2] for x in want)
    assert 0 <= sum(n for n, _ in left) - sum(n for n, _ in mine) <= 6 * spans


def test_mixture_stage(spark, tables):
    docs = docs_of(spark, tables)
    got = pipeline.mixture(spark, docs, tables)
    assert got.columns == docs.columns
    labels = spark.read.parquet(f"{tables}/labels.parquet")
    model = mixing.train(docs, labels)
    members = mixing.memberships(docs, model)
    history, reached, goal = mixing.fit_whole_rates(members, mixing.TARGETS, 0.1, keep="clean")
    seen = got.groupBy(F.coalesce("doc_id", F.lit(-1)).alias("doc_id"), "text").count().collect()
    times = {(r.doc_id, r.text): r["count"] for r in seen}
    rows = docs.collect()
    texts = [(r.text or "").encode() for r in rows]
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    p, _ = model.posteriors(np.frombuffer(b"".join(texts), np.uint8), offsets)
    rate = mixing.rates(p, history)
    for r, x in zip(rows, rate):
        same = sum(1 for q in rows if (q.doc_id, q.text) == (r.doc_id, r.text))
        assert abs(times.get((-1 if r.doc_id is None else r.doc_id, r.text), 0) / same - x) < 1 + 0.1


def test_whole_run(spark, tables):
    got = pipeline.run(spark, tables).toPandas()
    assert set(got.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"}
    for _, s in got.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert s.offset.tolist() == [0, *s.length.cumsum().tolist()[:-1]] and s.length.sum() <= 1024


def test_empty_run(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for _, stage in pipeline.STAGES:
        assert stage(spark, docs_of(spark, str(tmp_path)), str(tmp_path)).count() == 0
    assert pipeline.run(spark, str(tmp_path)).count() == 0
