"""Analysis and evaluation workloads."""

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..fixtures import md5_number_sql
from ..functions import columns as C
from ..operators import analysis as A, language_model as lm
from ..operators.dedup import _stored
from ..registry import query
from .dedup import TOKENS_SQL, bench, docs
from .inspection import HOST_SQL

_WORDS = r"len(list_filter(regexp_split_to_array(text, '[ \t\n\r]+'), lambda x: x <> ''))"


@query("token_counts", rf"""SELECT lang, CAST(sum({_WORDS}) AS BIGINT) AS words, CAST(sum(len(regexp_extract_all(text, '([\p{{L}}\p{{N}}]+|[^\p{{L}}\p{{N}}\s])', 1))) AS BIGINT) AS parts,
CAST(sum(CAST(ceil(length(text) / 3.3) AS INT)) AS BIGINT) AS estimate FROM documents GROUP BY lang""")
def token_counts(spark, d):
    return docs(spark, d).groupBy("lang").agg(*(F.sum(A.token_count(F.col("text"), k)).alias(n) for k, n in (("words", "words"), ("parts", "parts"), ("chars", "estimate"))))


@query("size_comparison", f"SELECT CASE WHEN CAST(substr(source, 4) AS INT) < 5 THEN 'proof-like' WHEN CAST(substr(source, 4) AS INT) < 10 THEN 'ours' ELSE 'general' END AS corpus, count(*) AS n_docs, CAST(sum({_WORDS}) AS BIGINT) AS tokens FROM documents GROUP BY 1")
def sizes(spark, d):
    n = F.substring("source", 4, 9).cast("int")
    return docs(spark, d).groupBy(F.when(n < 5, "proof-like").when(n < 10, "ours").otherwise("general").alias("corpus")).agg(F.count("*").alias("n_docs"), F.sum(A.token_count(F.col("text"))).alias("tokens"))


@query("hash_sample", f"SELECT doc_id, source FROM documents ORDER BY {md5_number_sql("doc_id || '/11'")}, doc_id LIMIT 200")
def hash_sample(spark, d):
    return A.sample(docs(spark, d).select("doc_id", "source"), 200, 11, "doc_id")


_ASSIGN = """c AS (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS cluster, embedding::DOUBLE[] AS centre FROM (SELECT * FROM embeddings ORDER BY vec_id LIMIT 10)),
x AS (SELECT vec_id, label, cluster, round(list_sum(list_transform(list_zip(embedding::DOUBLE[], centre), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 9) AS dist FROM embeddings, c),
a AS (SELECT vec_id, label, cluster, dist FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY dist, cluster) AS k FROM x) WHERE k = 1)"""


def _assigned(spark, d):
    v = spark.read.parquet(f"{d}/embeddings.parquet")
    return A.assign(v, A.first_centres(v, 10)), v


@query("lloyd_step", f"""WITH {_ASSIGN}, m AS (SELECT a.cluster, i, avg(e.embedding[i]::DOUBLE) AS m FROM a JOIN embeddings e USING (vec_id), (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2)
SELECT CAST(cluster AS INT) AS cluster, CAST(i - 1 AS INT) AS i, round(m, 6) AS m FROM m""")
def lloyd(spark, d):
    got = A.recentre(_assigned(spark, d)[0])
    return got.select("cluster", F.posexplode("centre").alias("i", "m")).withColumn("m", F.round("m", 6))


@query("nearest_to_center", f"WITH {_ASSIGN} SELECT CAST(cluster AS INT) AS cluster, vec_id, CAST(k AS INT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY dist, vec_id) AS k FROM a) WHERE k <= 5")
def nearest(spark, d):
    return A.nearest(_assigned(spark, d)[0], 5).select("cluster", "vec_id", "rank")


@query("topic_shares", f"""WITH {_ASSIGN}, r AS (SELECT cluster, label FROM (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY dist, vec_id) AS k FROM a) WHERE k <= 5),
v AS (SELECT cluster, label, row_number() OVER (PARTITION BY cluster ORDER BY count(*) DESC, label) AS k FROM r GROUP BY cluster, label), s AS (SELECT cluster, count(*) AS size FROM a GROUP BY cluster)
SELECT label AS topic, CAST(sum(size) AS BIGINT) AS size, round(CAST(100.0 AS DOUBLE) * sum(size) / (SELECT sum(size) FROM s), 4) AS share FROM v JOIN s USING (cluster) WHERE k = 1 GROUP BY label""")
def topics(spark, d):
    a, v = _assigned(spark, d)
    reps = A.nearest(a, 5).join(v.select("vec_id", "label"), "vec_id")
    return A.topic_shares(reps, a.groupBy("cluster").agg(F.count("*").alias("size")))


_EMBED = f"list_transform(range(0, 60), lambda i: CAST(2 * coalesce(list_sum(list_transform(h, lambda x: (x >> i) & 1)), 0) - len(h) AS INT))"


@query("embed_documents", f"WITH t AS (SELECT doc_id, list_transform({TOKENS_SQL}, lambda x: {md5_number_sql('x')}) AS h FROM documents) SELECT doc_id, md5(array_to_string({_EMBED}, ',')) AS embedding FROM t")
def embed(spark, d):
    """Digest of every document's vector by hashed random projection."""
    x = A.embed(docs(spark, d))
    return x.select("doc_id", F.md5(F.array_join(F.transform("embedding", lambda v: v.cast("int").cast("string")), ",").cast("binary")).alias("embedding"))


@query("topic_study")
def topic_study(spark, d):
    """The study as published: 100,000 documents in hash order, their vectors, 128 clusters, the five nearest to each
    centre, the commonest label (here: language) of those, and the share of each."""
    some = A.sample(docs(spark, d).select("doc_id", "text", "lang"), 100_000, 17, "doc_id")
    v = _stored(A.embed(some).select(F.col("doc_id").alias("vec_id"), F.transform("embedding", lambda x: x.cast("double")).alias("embedding")))
    found = _stored(A.kmeans(v, 128))
    centres = A.recentre(found.select("cluster", F.col("embedding").alias("v")))
    dist = found.join(F.broadcast(centres), "cluster").select("vec_id", "cluster", A.squared_distance(F.col("embedding"), F.col("centre")).alias("dist"))
    near = A.nearest(dist, 5).join(some.select(F.col("doc_id").alias("vec_id"), "lang"), "vec_id")
    label = near.groupBy("cluster", "lang").agg(F.count("*").alias("k")).groupBy("cluster").agg(F.max_by("lang", F.struct("k", "lang")).alias("topic"))
    per = found.groupBy("cluster").agg(F.count("*").alias("size")).join(label, "cluster").groupBy("topic").agg(F.count("*").alias("clusters"), F.sum("size").alias("size"))
    return per.crossJoin(F.broadcast(per.agg(F.sum("size").alias("whole")))).select("topic", "clusters", "size", F.round(100.0 * F.col("size") / F.col("whole"), 4).alias("share"))


_RECORD = {"model_size": "1.4 B", "layers": 24, "model_dim": 2048, "heads": 16, "learning_rate": 0.0002, "batch_size": "1M", "tokens": "14.7B"}
_RUN_TOKENS = 14_700_000_000


@query("hyper_parameters", f"""SELECT '1.4 B' AS model_size, 24 AS layers, 2048 AS model_dim, 16 AS heads, 0.0002::DOUBLE AS learning_rate, '1M' AS batch_size, '14.7B' AS tokens, source, n AS corpus_tokens, round({_RUN_TOKENS}::DOUBLE / nullif(n, 0), 4) AS passes
FROM (SELECT coalesce(source, 'all') AS source, CAST(coalesce(sum({_WORDS}), 0) AS BIGINT) AS n FROM documents GROUP BY GROUPING SETS ((source), ()))""")
def hyper_parameters(spark, d):
    """The record of the published training runs (fixed values; the runs are not repeated here), and how often a run of its
    length would pass over each source of this corpus and over all of it."""
    words = docs(spark, d).select("source", A.token_count(F.col("text")).alias("n"))
    per = words.groupingSets([["source"], []], "source").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("corpus_tokens"))
    passes = F.round(F.try_divide(F.lit(float(_RUN_TOKENS)), "corpus_tokens"), 4)
    return per.select(*(F.lit(v).alias(k) for k, v in _RECORD.items()), F.coalesce("source", F.lit("all")).alias("source"), "corpus_tokens", passes.alias("passes"))


@query("cluster_purity")
def purity(spark, d):
    """Purity of k-means on vectors with planted clusters, from spread centres."""
    v = spark.read.parquet(f"{d}/embeddings.parquet")
    planted = v.withColumn("embedding", F.transform("embedding", lambda x, i: x.cast("double") + F.when(i == F.col("label"), 2.0).otherwise(0.0)))
    found = A.lloyd(planted, A.spread_centres(planted, 10)).join(v.select("vec_id", "label"), "vec_id")
    c = found.groupBy("cluster", "label").agg(F.count("*").alias("k"))
    return c.groupBy("cluster").agg(F.max("k").alias("top"), F.sum("k").alias("size")).agg(F.round(F.sum("top") / F.sum("size"), 4).alias("purity"), F.count("*").alias("clusters"))


@query("site_type_shift", f"""WITH t AS (SELECT page_id, CASE WHEN regexp_matches({HOST_SQL}, '^blog[.]') THEN 'Blog' ELSE 'Other' END AS k FROM pages),
s AS (SELECT k FROM t ORDER BY {md5_number_sql("page_id || '/13'")}, page_id LIMIT 200), a AS (SELECT k, count(*) / (SELECT count(*) FROM s)::DOUBLE AS p FROM s GROUP BY k), b AS (SELECT k, count(*) / (SELECT count(*) FROM t)::DOUBLE AS q FROM t GROUP BY k)
SELECT round(sum(abs(coalesce(p, 0) - coalesce(q, 0))) / 2, 6) AS total_variation FROM a FULL JOIN b USING (k)""")
def shift(spark, d):
    """Distance between the site types of a sample and of all pages."""
    t = spark.read.parquet(f"{d}/pages.parquet").select("page_id", C.site_type(F.col("url")).alias("k"))
    share = lambda df, n: df.groupBy("k").agg(F.count("*").alias("c")).crossJoin(F.broadcast(df.agg(F.count("*").alias("n")))).select("k", (F.col("c") / F.col("n")).alias(n))
    x = share(A.sample(t, 200, 13, "page_id"), "p").join(share(t, "q"), "k", "full")
    return x.agg(F.round(F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))) / 2, 6).alias("total_variation"))


@query("datasheet", "SELECT count(*) AS instances, count(DISTINCT source) AS sources, count(*) FILTER (text IS NULL OR text = '') AS empty_texts, min(n_chars) AS shortest, max(n_chars) AS longest, CAST(sum(n_chars) AS BIGINT) AS characters FROM documents")
def datasheet(spark, d):
    return docs(spark, d).agg(F.count("*").alias("instances"), F.countDistinct("source").alias("sources"), F.count_if(F.col("text").isNull() | (F.col("text") == "")).alias("empty_texts"), F.min("n_chars").alias("shortest"), F.max("n_chars").alias("longest"), F.sum("n_chars").alias("characters"))


# ---- evaluation

_TOK = f"t AS (SELECT doc_id, source, {_WORDS} AS n_tokens FROM documents)"
_RUN = f"sum(n_tokens) OVER (ORDER BY {md5_number_sql("doc_id || '/3'")}, doc_id)"


@query("token_budget", f"WITH {_TOK}, r AS (SELECT doc_id, CAST({_RUN} AS BIGINT) AS running FROM t) SELECT doc_id, running FROM r WHERE running <= 100000")
def token_budget(spark, d):
    x = docs(spark, d).select("doc_id", A.token_count(F.col("text")).alias("n_tokens"))
    return A.budget(x, 100_000, 3).select("doc_id", "running")


_PART = lambda low, high: f"SELECT doc_id, CAST({_RUN} AS BIGINT) AS running FROM t WHERE CAST(substr(source, 4) AS INT) BETWEEN {low} AND {high}"


@query("mixture", f"WITH {_TOK}, a AS ({_PART(0, 4)}), b AS ({_PART(5, 9)}) SELECT 0 AS part, doc_id FROM a WHERE running <= 25000 UNION ALL SELECT 1, doc_id FROM b WHERE running <= 25000")
def mixture(spark, d):
    """Half and half of two corpora by tokens."""
    x = docs(spark, d).select("doc_id", F.substring("source", 4, 9).cast("int").alias("s"), A.token_count(F.col("text")).alias("n_tokens"))
    return A.mixture([(x.where("s BETWEEN 0 AND 4"), 0.5), (x.where("s BETWEEN 5 AND 9"), 0.5)], 50_000, 3).select("part", "doc_id")


_ANSWERS = r"""g AS (SELECT item_id, regexp_extract(text, '(\S+)\s*$', 1) AS gold FROM benchmark),
ans AS (SELECT item_id, gold, j, CASE WHEN (item_id * 7 + j * 5) % 16 < item_id % 17 THEN gold ELSE 'wrong' || (j % 3) END AS answer FROM g, (SELECT unnest(range(0, 16)) AS j))"""


def _answers(spark, d):
    g = bench(spark, d).select("item_id", F.regexp_extract("text", r"(\S+)\s*$", 1).alias("gold"))
    j = g.select("item_id", "gold", F.explode(F.sequence(F.lit(0), F.lit(15))).alias("j"))
    return j.withColumn("answer", F.when((F.col("item_id") * 7 + F.col("j") * 5) % 16 < F.col("item_id") % 17, F.col("gold")).otherwise(F.concat(F.lit("wrong"), (F.col("j") % 3).cast("string"))))


@query("accuracy", f"WITH {_ANSWERS} SELECT item_id % 8 AS subject, count(*) AS n, round(100.0 * avg(CAST(answer = gold AS INT)), 4) AS accuracy FROM ans WHERE j = 0 GROUP BY 1")
def accuracy(spark, d):
    return _answers(spark, d).where("j = 0").groupBy((F.col("item_id") % 8).alias("subject")).agg(F.count("*").alias("n"), F.round(100.0 * F.avg((F.col("answer") == F.col("gold")).cast("int")), 4).alias("accuracy"))


@query("majority_vote", f"""WITH {_ANSWERS}, v AS (SELECT item_id, answer, count(*) AS votes FROM ans GROUP BY 1, 2), m AS (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY votes DESC, answer) AS k FROM v)
SELECT item_id, answer, votes, answer = gold AS correct FROM m JOIN g USING (item_id) WHERE k = 1""")
def majority(spark, d):
    a = _answers(spark, d)
    return A.majority(a).join(a.where("j = 0").select("item_id", "gold"), "item_id").select("item_id", "answer", "votes", (F.col("answer") == F.col("gold")).alias("correct"))


_CORPORA = {"general": (0, 99), "proof-like": (0, 4), "ours": (5, 9)}


def _ppl_sql(name: str, low: int, high: int) -> str:
    return f"""SELECT '{name}' AS corpus, item_id % 8 AS subject, round(exp(-avg(ln((coalesce(c, 0) + 0.1::DOUBLE) / (total + 0.1::DOUBLE * v)))), 4) AS ppl FROM
 (SELECT item_id, unnest(list_concat({TOKENS_SQL}, ['</s>'])) AS w FROM benchmark) q LEFT JOIN (SELECT w, count(*) AS c FROM (SELECT unnest(list_concat({TOKENS_SQL}, ['</s>'])) AS w FROM documents WHERE CAST(substr(source, 4) AS INT) BETWEEN {low} AND {high}) GROUP BY w) u USING (w),
 (SELECT count(*) AS total, count(DISTINCT w) + 1 AS v FROM (SELECT unnest(list_concat({TOKENS_SQL}, ['</s>'])) AS w FROM documents WHERE CAST(substr(source, 4) AS INT) BETWEEN {low} AND {high})) GROUP BY 2"""


@query("ppl_matrix", " UNION ALL ".join(_ppl_sql(n, a, b) for n, (a, b) in _CORPORA.items()))
def ppl_matrix(spark, d):
    """Perplexity of the benchmark's subjects under a model of each corpus."""
    items, out = bench(spark, d).select((F.col("item_id") % 8).alias("subject"), "text"), None
    for name, (low, high) in _CORPORA.items():
        train = docs(spark, d).where(F.substring("source", 4, 9).cast("int").between(low, high)).select("text")
        x = lm.add_k_perplexity(train, items, key="subject").select(F.lit(name).alias("corpus"), "subject", F.round("ppl", 4).alias("ppl"))
        out = x if out is None else out.unionByName(x)
    return out


@query("rank_table", f"WITH p AS ({' UNION ALL '.join(_ppl_sql(n, a, b) for n, (a, b) in _CORPORA.items())}) SELECT corpus, subject, CAST(rank() OVER (PARTITION BY subject ORDER BY ppl) AS INT) AS place FROM p")
def rank_table(spark, d):
    return ppl_matrix(spark, d).select("corpus", "subject", F.rank().over(W.partitionBy("subject").orderBy("ppl")).alias("place"))


@query("conversation_docs", "SELECT conv_id, string_agg(role || ': ' || text, chr(10) ORDER BY turn, role, text) AS text, count(*) AS turns FROM conversations GROUP BY conv_id")
def conversations(spark, d):
    """Threads rebuilt as one document each, turns in order."""
    c = spark.read.parquet(f"{d}/conversations.parquet").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("t"), F.count("*").alias("turns"))
    return c.select("conv_id", F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), "\n").alias("text"), "turns")


@query("kmeans_clusters")
def kmeans(spark, d):
    """Sizes of library k-means clusters over all vectors, with the paper's number of clusters."""
    v = spark.read.parquet(f"{d}/embeddings.parquet")
    return A.kmeans(v, 128).groupBy("cluster").agg(F.count("*").alias("size"))
