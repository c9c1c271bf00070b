import duckdb
import numpy as np
import pandas as pd
import pytest

from formulary.llm import pivot_neardup, url_rules
from formulary.llm.common import table


def naive_links(x, valid):
    unit = np.where(valid[:, None], x, 0)
    unit = unit / np.maximum(np.linalg.norm(unit, axis=1, keepdims=True), 1e-300)
    hit = (unit @ unit.T >= 0.95) & valid[:, None] & valid[None, :]
    np.fill_diagonal(hit, False)
    return hit


def naive_components(ids, hit):
    up = list(range(len(ids)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, j in np.argwhere(hit):
        a, b = find(i), find(j)
        if a != b:
            a, b = (a, b) if ids[a] < ids[b] else (b, a)
            up[b] = a
    return [ids[find(i)] for i in range(len(ids))]


@pytest.mark.parametrize("tuning", [{}, {"block": 40}])
def test_links_match_brute_force(spark, tuning):
    rng = np.random.default_rng(0)
    centres = rng.normal(size=(30, 24))
    x = np.concatenate([c + rng.normal(scale=0.08, size=(n, 24)) for c, n in zip(centres, rng.integers(1, 12, 30))] + [centres[0] + rng.normal(scale=0.1, size=(150, 24)), np.repeat(centres[3:4], 40, axis=0), 7 * centres[4:5]])
    ids = rng.permutation(len(x))
    got = pivot_neardup.near_duplicates(spark.createDataFrame(pd.DataFrame({"vec_id": ids, "embedding": x.tolist(), "label": 1, "key": 2, "rep": 3})), **tuning).toPandas().set_index("vec_id").loc[ids]
    hit = naive_links(x, np.ones(len(x), bool))
    found = got.n_links.to_numpy()
    assert (found <= hit.sum(axis=1)).all() and found.sum() >= 0.97 * hit.sum()
    if found.sum() == hit.sum():
        assert got.component_id.tolist() == naive_components(ids, hit)
    assert (got.kept == (got.index == got.component_id)).all()


def test_recall_at_the_threshold(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(1500, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    u = rng.normal(size=x.shape)
    u -= (u * x).sum(axis=1, keepdims=True) * x
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    y = 0.951 * x + np.sqrt(1 - 0.951**2) * u
    df = spark.createDataFrame(pd.DataFrame({"vec_id": range(3000), "embedding": np.concatenate([x, y]).tolist()}))
    assert pivot_neardup.near_duplicates(df).where("n_links > 0").count() >= 0.97 * 3000


def test_invalid_vectors_link_with_nothing(spark):
    good = [1.0, 2.0, 3.0]
    rows = [(1, good), (2, good), (3, None), (4, [0.0, 0.0, 0.0]), (5, [float("nan"), 1.0, 1.0]), (6, [1.0, None, 1.0]), (7, [float("inf"), 1.0, 1.0]), (8, [1.0]), (None, good), (9, [-1.0, -2.0, -3.0]), (9, [-1.0, -2.0, -3.0]), (10, [2e300, 4e300, 6e300])]
    got = pivot_neardup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    by = sorted((r.vec_id or -1, r.n_links, r.component_id or -1) for r in got)
    assert by[0] == (-1, 3, 1) and len(got) == len(rows)  # a row without an id is compared as any other
    assert by[1:] == [(1, 3, 1), (2, 3, 1), (3, 0, 3), (4, 0, 4), (5, 0, 5), (6, 0, 6), (7, 0, 7), (8, 0, 8), (9, 1, 9), (9, 1, 9), (10, 3, 1)]


def test_finer_lists_find_the_same(spark):
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(40, 32))
    x = np.concatenate([c + rng.normal(scale=0.05, size=(12, 32)) for c in centres])
    hit = naive_links(x, np.ones(len(x), bool))
    df = spark.createDataFrame(pd.DataFrame({"vec_id": range(len(x)), "embedding": x.tolist()}))
    for shared in (3, 4):
        got = pivot_neardup.near_duplicates(df, pivots=64, nearest=12, shared=shared).toPandas().set_index("vec_id").loc[range(len(x))]
        assert (got.n_links <= hit.sum(axis=1)).all() and got.n_links.sum() >= 0.97 * hit.sum()


def test_more_vectors_get_finer_lists():
    x = np.random.default_rng(4).normal(size=(4000, 32))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    few, many = pivot_neardup.calibrate(x, 0.95, 10**4, (256, 1024)), pivot_neardup.calibrate(x, 0.95, 10**9, (256, 1024))
    lists = lambda c: len(c[0]) ** c[2]
    assert lists(many) >= 16 * lists(few)
    for points, nearest, shared in (few, many):
        met = [pivot_neardup._in_common(*(pivot_neardup.nearest_pivots(v, points, nearest) for v in pair)) for pair in pivot_neardup._meetings(x, 0.95)]
        assert min((m >= shared).mean() for m in met) >= 0.9


def test_large_ids_stay_whole_beside_a_null(spark):
    big = 2**53 + 1
    rows = [(big, [1.0, 2.0, 3.0]), (big + 2, [1.0, 2.0, 3.1]), (None, [3.0, -1.0, 0.0]), (5, None)]
    got = pivot_neardup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>").coalesce(1)).collect()
    assert sorted((r.vec_id, r.component_id, r.n_links) for r in got if r.vec_id) == [(5, 5, 0), (big, big, 1), (big + 2, big, 1)]


def test_no_vectors(spark):
    assert pivot_neardup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


# ---- URLs


def naive_judge(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1].split("?")[0].split("#")[0]
        host, _, tail = rest.partition("/")
        path = "/" + tail if "/" in rest else ""
        host = "".join(c.lower() if c.isascii() else c for c in host)
    best = None
    for r in ("org/", "example.org/es/", "example.org/en/1", "com/fr/", "com/de/"):
        h, _, p = r.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(r) > len(best)):
            best = r
    return host, path, best


URLS = [None, "", "no scheme", "http://EXAMPLE.org", "http://a.Example.ORG/en/12?x=1#y", "https://example.org/es/", "ftp://xexample.org/es/1", "http://x.com/fr/1", "http://x.com/FR/1", "http://www.cheap-pills1.example.net/en/1", "http://net?://x.org/", "http://h.org#a/b", "a://b://c.org/d", "http://ÉX.org/é", "http://x.com/de", "http://site.net/user/login/"]


def test_urls_match_brute_force(spark):
    df = spark.createDataFrame([(i, u, "a", "b") for i, u in enumerate(URLS)] + [(None, "http://x.com/de/1", "a", "b"), (1, "", "a", "b")], "page_id long, url string, host string, rule string")
    got = url_rules.judge(df).collect()
    assert len(got) == df.count()
    for r in got:
        if r.page_id is not None and r.page_id != 1:
            host, path, rule = naive_judge(URLS[r.page_id])
            assert (r.host, r.path, r.rule) == (host, path, rule), r
    verdicts = {r.page_id: r.verdict for r in got}
    assert verdicts[0] == "allow" and verdicts[9] == "block" and verdicts[15] == "block" and verdicts[7] == "allow" and verdicts[None] == "block"


def test_urls_match_sql(spark):
    d = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{d}/pages.parquet'")
    want = con.execute(url_rules.ORACLE_SQL).df().sort_values("page_id").astype(object)
    got = url_rules.judge(table(spark, d, "pages")).toPandas().sort_values("page_id").astype(object)
    for c in want.columns:
        assert [x if x == x else None for x in want[c]] == [x if x == x else None for x in got[c]]


def test_rarest_token_is_the_index_entry(spark):
    tokens = spark.createDataFrame([("a",)] * 5 + [("b",)] * 2, "token string")
    rules = (url_rules.pattern("a.*b", ("a", "b")), url_rules.pattern("x", ("x", "a")), url_rules.pattern(".", ()))
    index = {r.pattern: r.token for r in url_rules.index_rules(tokens, url_rules.rule_table(spark, rules), 3).collect()}
    assert index == {"a.*b": "b", "x": "x", ".": ""}


def test_url_plan_has_no_python(spark, data):
    plan = url_rules.op4_query(spark, data)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan and "html" not in plan.split("Physical Plan")[1]


def test_no_urls(spark):
    assert url_rules.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0
