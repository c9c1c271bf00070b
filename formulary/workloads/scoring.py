"""Language, math score, language model and filter workloads."""

from pyspark.sql import functions as F

from .. import lexicon as L
from ..fixtures import MATH_DOCS_SQL, math_docs, md5_number_sql
from ..functions import columns as C
from ..operators import classify, language_model as lm
from ..registry import query
from .dedup import TOKENS_SQL, docs
from .prefilter import _LIST, commands_sql

_VOTE = ", ".join(f"{{'k': len(list_filter(t, lambda x: x IN ({', '.join(map(L.sql_quote, ws))}))), 'lang': '{lang}'}}" for lang, ws in sorted(L.STOP_WORDS.items(), reverse=True))
_VOTE_SQL = f"""t AS (SELECT doc_id, lang, {TOKENS_SQL} AS t FROM documents), v AS (SELECT doc_id, lang, list_sort([{_VOTE}], 'DESC')[1] AS b FROM t),
p AS (SELECT doc_id, lang, CASE WHEN b.k > 0 THEN b.lang ELSE 'und' END AS lang_pred FROM v)"""


@query("lang_stopword_vote", f"WITH {_VOTE_SQL} SELECT doc_id, lang_pred FROM p")
def vote(spark, d):
    return docs(spark, d).select("doc_id", classify.stop_word_vote(F.col("text")).alias("lang_pred"))


@query("lang_confusion", f"WITH {_VOTE_SQL} SELECT lang, lang_pred, count(*) AS n FROM p GROUP BY ALL")
def confusion(spark, d):
    return docs(spark, d).groupBy("lang", classify.stop_word_vote(F.col("text")).alias("lang_pred")).agg(F.count("*").alias("n"))


@query("math_label", f"WITH {MATH_DOCS_SQL} SELECT doc_id, CAST(list_has_any({commands_sql('text')}, {_LIST}) AS INT) AS label, has_math FROM math_docs")
def math_label(spark, d):
    return math_docs(spark, d).select("doc_id", C.has_common_command(F.col("text")).cast("int").alias("label"), "has_math")


_STRIP = r"regexp_replace(regexp_replace(regexp_replace(text, '(?s)\\begin\{([a-z]+\*?)\}.*?\\end\{[a-z]+\*?\}', ' ', 'g'), '\$\$?[^$]*\\[A-Za-z][^$]*\$\$?', ' ', 'g'), '\\[A-Za-z]+', ' ', 'g')"


@query("strip_latex", f"WITH {MATH_DOCS_SQL} SELECT doc_id, md5({_STRIP}) AS stripped, len({commands_sql(_STRIP)}) AS commands_left FROM math_docs")
def strip_latex(spark, d):
    s = classify.strip_latex(F.col("text"))
    return math_docs(spark, d).select("doc_id", F.md5(s.cast("binary")).alias("stripped"), F.size(C.commands_in(s)).cast("long").alias("commands_left"))


_TEST = f"{md5_number_sql('CAST(doc_id AS VARCHAR)')} % 5 = 4"
_NB = f"""tr AS (SELECT q.doc_id, quality AS label, unnest({TOKENS_SQL}) AS token FROM documents q JOIN labels USING (doc_id) WHERE NOT ({_TEST.replace('doc_id', 'q.doc_id')})),
nc AS (SELECT token, count(*) FILTER (label = 0) AS c0, count(*) FILTER (label = 1) AS c1 FROM tr GROUP BY token),
tot AS (SELECT sum(c0) AS t0, sum(c1) AS t1, count(*) AS v FROM nc), r AS (SELECT token, ln((c1 + 1) / (t1 + v)) - ln((c0 + 1) / (t0 + v)) AS r FROM nc, tot),
x AS (SELECT doc_id, unnest({TOKENS_SQL}) AS token FROM documents),
s AS (SELECT doc_id, 1 / (1 + exp(-sum(coalesce(r, 0.0)) / count(*))) AS score FROM x LEFT JOIN r USING (token) GROUP BY doc_id)"""


def _labelled(spark, d):
    return docs(spark, d).join(spark.read.parquet(f"{d}/labels.parquet").select("doc_id", F.col("quality").alias("label")), "doc_id")


def _nb_scores(spark, d):
    return classify.nb_score(docs(spark, d), classify.naive_bayes(_labelled(spark, d).where(~classify.held_out(F.col("doc_id"))), "label"))


@query("nb_token_counts", f"WITH {_NB} SELECT token, CAST(c0 AS BIGINT) AS c0, CAST(c1 AS BIGINT) AS c1 FROM nc")
def nb_counts(spark, d):
    t, _ = classify.naive_bayes(_labelled(spark, d).where(~classify.held_out(F.col("doc_id"))), "label")
    return t.groupBy("token").agg(F.coalesce(F.sum(F.when(F.col("label") == 0, F.col("c"))), F.lit(0)).alias("c0"), F.coalesce(F.sum(F.when(F.col("label") == 1, F.col("c"))), F.lit(0)).alias("c1"))


@query("nb_score", f"WITH {_NB} SELECT doc_id, round(score, 6) AS score FROM s")
def nb_score(spark, d):
    return _nb_scores(spark, d).select("doc_id", F.round("score", 6).alias("score"))


@query("score_histogram", f"WITH {_NB} SELECT CAST(floor(round(score, 6) * 20) AS BIGINT) AS bin, count(*) AS n FROM s GROUP BY 1")
def histogram(spark, d):
    return _nb_scores(spark, d).groupBy(F.floor(F.round("score", 6) * 20).alias("bin")).agg(F.count("*").alias("n"))


@query("auc", f"""WITH {_NB}, y AS (SELECT round(score, 6) AS s, quality AS q FROM s JOIN labels USING (doc_id) WHERE {_TEST}),
g AS (SELECT s, sum(q) AS pos, count(*) - sum(q) AS neg FROM y GROUP BY s), w AS (SELECT pos, neg, coalesce(sum(neg) OVER (ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM g)
SELECT round(CAST(sum(pos * (below + neg / 2.0)) AS DOUBLE) / (sum(pos) * sum(neg)), 6) AS auc FROM w""")
def auc(spark, d):
    """Quality from words alone, on held-out documents."""
    held = _labelled(spark, d).where(classify.held_out(F.col("doc_id"))).select("doc_id", "label").join(_nb_scores(spark, d), "doc_id")
    return classify.auc(held.withColumn("score", F.round("score", 6)), "score", "label").select(F.round("auc", 6).alias("auc"))


_LEX = "least((" + " + ".join(f"CAST(contains(lower(text), '{w}') AS INT)" for w in L.MATH_WORDS) + ") / 5.0, 1.0)"
_SCORED_SQL = f"{MATH_DOCS_SQL}, sc AS (SELECT doc_id, lang, list_has_any({commands_sql('text')}, {_LIST}) AS has_latex, CAST({_LEX} AS DOUBLE) AS math_score FROM math_docs)"


def _scored(spark, d):
    t = F.col("text")
    return math_docs(spark, d).select("doc_id", "lang", C.has_common_command(t).alias("has_latex"), C.lexicon_score(t).alias("math_score"))


@query("math_filter", f"WITH {_SCORED_SQL} SELECT doc_id, round(math_score, 6) AS math_score FROM sc WHERE math_score > CASE WHEN has_latex THEN {L.CUT_WITH_TEX} ELSE {L.CUT_WITHOUT_TEX} END")
def math_filter(spark, d):
    cut = F.when(F.col("has_latex"), L.CUT_WITH_TEX).otherwise(L.CUT_WITHOUT_TEX)
    return _scored(spark, d).where(F.col("math_score") > cut).select("doc_id", F.round("math_score", 6).alias("math_score"))


@query("score_cut_sweep", f"WITH {_SCORED_SQL} SELECT cut, count(*) FILTER (math_score > cut) AS kept, count(*) FILTER (math_score > cut AND has_latex) AS kept_with_latex FROM sc, (SELECT unnest([0.17, 0.2, 0.8]::DOUBLE[]) AS cut) GROUP BY cut")
def cut_sweep(spark, d):
    one = _scored(spark, d).agg(*(x for i, c in enumerate((0.17, 0.2, 0.8)) for x in (F.count_if(F.col("math_score") > c).alias(f"k{i}"), F.count_if((F.col("math_score") > c) & F.col("has_latex")).alias(f"l{i}"))))
    return one.select(F.inline(F.array(*(F.struct(F.lit(c).alias("cut"), F.col(f"k{i}").alias("kept"), F.col(f"l{i}").alias("kept_with_latex")) for i, c in enumerate((0.17, 0.2, 0.8))))))


# ---- language model

_TRAIN = "SELECT doc_id, text FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND lang = 'en'"


def _train(spark, d):
    return docs(spark, d).where("lang = 'en'").join(spark.read.parquet(f"{d}/labels.parquet").where("quality = 1").select("doc_id"), "doc_id", "left_semi").select("doc_id", "text")


def _bigrams_sql(source: str, name: str) -> str:
    return f"""{name}_w AS (SELECT doc_id, list_concat(list_concat(['<s>'], {TOKENS_SQL}), ['</s>']) AS w FROM ({source})),
{name} AS (SELECT doc_id, w[i] AS ctx, w[i + 1] AS w FROM (SELECT doc_id, w, unnest(range(1, len(w))) AS i FROM {name}_w))"""


@query("bigram_counts", f"WITH {_bigrams_sql(_TRAIN, 'g')} SELECT ctx, w, count(*) AS c FROM g GROUP BY ctx, w")
def bigram_counts(spark, d):
    return lm.counts(_train(spark, d), 2)


@query("continuation_counts", f"WITH {_bigrams_sql(_TRAIN, 'g')} SELECT w, count(DISTINCT ctx) AS cont FROM g GROUP BY w")
def continuation(spark, d):
    return lm.fit_bigram_kn(_train(spark, d))["cont"]


_KN = f"""{_bigrams_sql(_TRAIN, 'g')}, bi AS (SELECT ctx, w, count(*) AS c FROM g GROUP BY ctx, w), cx AS (SELECT ctx, sum(c) AS total, count(*) AS kinds FROM bi GROUP BY ctx),
co AS (SELECT w, count(*) AS cont FROM bi GROUP BY w), ty AS (SELECT count(*) AS types FROM bi), vo AS (SELECT count(*) + 1 AS v FROM co), {_bigrams_sql('SELECT doc_id, text FROM documents', 'q')},
lp AS (SELECT doc_id, total, CAST(coalesce(c, 0) AS DOUBLE) AS c, CAST(kinds AS DOUBLE) AS kinds, greatest(CAST(coalesce(cont, 0) AS DOUBLE) - 0.75, 0.0) / types + (0.75::DOUBLE * (v - 1) / types) / v AS lower FROM q LEFT JOIN bi USING (ctx, w) LEFT JOIN cx USING (ctx) LEFT JOIN co USING (w), ty, vo),
pp AS (SELECT doc_id, count(*) AS n_tokens, exp(-avg(ln(CASE WHEN total IS NULL THEN lower ELSE (greatest(c - 0.75, 0.0) + 0.75::DOUBLE * kinds * lower) / total END))) AS ppl FROM lp GROUP BY doc_id)"""


@query("kn_bigram_perplexity", f"WITH {_KN} SELECT doc_id, n_tokens, round(ppl, 3) AS ppl FROM pp")
def kn(spark, d):
    return lm.perplexity(lm.kn_log_probabilities(docs(spark, d), lm.fit_bigram_kn(_train(spark, d)))).select("doc_id", "n_tokens", F.round("ppl", 3).alias("ppl"))


@query("ppl_filter", f"WITH {_KN} SELECT doc_id FROM pp WHERE round(ppl, 3) <= {L.MAX_PERPLEXITY}")
def ppl_filter(spark, d):
    return kn(spark, d).where(F.col("ppl") <= L.MAX_PERPLEXITY).select("doc_id")


_ADDK = f"""tr AS (SELECT unnest(list_concat({TOKENS_SQL}, ['</s>'])) AS w FROM ({_TRAIN})), u AS (SELECT w, count(*) AS c FROM tr GROUP BY w), t AS (SELECT sum(c) AS total, count(*) + 1 AS v FROM u),
q AS (SELECT doc_id, unnest(list_concat({TOKENS_SQL}, ['</s>'])) AS w FROM documents)"""


@query("addk_perplexity", f"WITH {_ADDK} SELECT doc_id, count(*) AS n_tokens, round(exp(-avg(ln((coalesce(c, 0) + 0.1::DOUBLE) / (total + 0.1::DOUBLE * v)))), 4) AS ppl FROM q LEFT JOIN u USING (w), t GROUP BY doc_id")
def add_k(spark, d):
    return lm.add_k_perplexity(_train(spark, d), docs(spark, d)).select("doc_id", "n_tokens", F.round("ppl", 4).alias("ppl"))


@query("mkn3_perplexity")
def mkn(spark, d):
    m = lm.ModifiedKneserNey(_train(spark, d), 3)
    return lm.perplexity(m.log_probabilities(docs(spark, d))).select("doc_id", "n_tokens", F.round("ppl", 3).alias("ppl"))


_CHAIN_SQL = f"""WITH {_SCORED_SQL}, {_KN},
c AS (SELECT doc_id, CASE WHEN lang <> 'en' THEN 'language' WHEN NOT math_score > CASE WHEN has_latex THEN {L.CUT_WITH_TEX} ELSE {L.CUT_WITHOUT_TEX} END THEN 'math' WHEN NOT round(ppl, 3) <= {L.MAX_PERPLEXITY} THEN 'perplexity' ELSE 'keep' END AS verdict, lang FROM sc JOIN pp USING (doc_id))"""


def _chain(spark, d, **kw):
    return classify.verdicts(_scored(spark, d).join(kn(spark, d).select("doc_id", "ppl"), "doc_id", "left"), **kw)


@query("filter_chain", f"{_CHAIN_SQL} SELECT doc_id, verdict FROM c")
def chain(spark, d):
    return _chain(spark, d).select("doc_id", "verdict")


@query("filter_funnel", f"{_CHAIN_SQL} SELECT coalesce(lang, 'all') AS lang, coalesce(verdict, 'all') AS verdict, count(*) AS n FROM c GROUP BY ROLLUP (lang, verdict)")
def funnel(spark, d):
    got = _chain(spark, d).rollup("lang", "verdict").agg(F.count("*").alias("n"))
    return got.select(F.coalesce("lang", F.lit("all")).alias("lang"), F.coalesce("verdict", F.lit("all")).alias("verdict"), "n")


_ABLATE = f"""{_CHAIN_SQL}, k AS (SELECT sc.doc_id, sc.lang = 'en' AS l, math_score > CASE WHEN has_latex THEN {L.CUT_WITH_TEX} ELSE {L.CUT_WITHOUT_TEX} END AS m, round(ppl, 3) <= {L.MAX_PERPLEXITY} AS p FROM sc JOIN pp USING (doc_id))
SELECT 'all' AS config, count(*) FILTER (l AND m AND p) AS kept FROM k UNION ALL SELECT 'no language', count(*) FILTER (m AND p) FROM k UNION ALL SELECT 'no math', count(*) FILTER (l AND p) FROM k UNION ALL SELECT 'no perplexity', count(*) FILTER (l AND m) FROM k"""


@query("filter_ablation", _ABLATE)
def ablation(spark, d):
    base, out = _scored(spark, d).join(kn(spark, d).select("doc_id", "ppl"), "doc_id"), None
    for name, order in (("all", classify.FILTERS), *((f"no {f}", tuple(x for x in classify.FILTERS if x != f)) for f in classify.FILTERS)):
        x = classify.verdicts(base, order).agg(F.lit(name).alias("config"), F.count_if(F.col("verdict") == "keep").alias("kept"))
        out = x if out is None else out.unionByName(x)
    return out


@query("backoff_perplexity", f"""WITH {_bigrams_sql(_TRAIN, 'g')}, bi AS (SELECT ctx, w, count(*) AS c FROM g GROUP BY ctx, w), cx AS (SELECT ctx, sum(c) AS total FROM bi GROUP BY ctx),
u AS (SELECT w, sum(c) AS uc FROM bi GROUP BY w), a AS (SELECT sum(uc) + count(*) + 1 AS n FROM u), {_bigrams_sql('SELECT doc_id, text FROM documents', 'q')}
SELECT doc_id, count(*) AS n_tokens, round(exp(-avg(ln(CASE WHEN c IS NOT NULL THEN CAST(c AS DOUBLE) / total ELSE 0.4::DOUBLE * (coalesce(uc, 0) + 1) / n END))), 4) AS ppl
FROM q LEFT JOIN bi USING (ctx, w) LEFT JOIN cx USING (ctx) LEFT JOIN u USING (w), a GROUP BY doc_id""")
def backoff(spark, d):
    return lm.backoff_perplexity(_train(spark, d), docs(spark, d)).select("doc_id", "n_tokens", F.round("ppl", 4).alias("ppl"))


_CUTS = (0.17, 0.2, 0.8)


@query("classifier_report", f"""WITH {_NB}, y AS (SELECT round(score, 6) AS s, quality AS q FROM s JOIN labels USING (doc_id) WHERE {_TEST}), c AS (SELECT unnest([0.17, 0.2, 0.8]::DOUBLE[]) AS cut)
SELECT cut, round(avg(CAST((s > cut) = (q = 1) AS INT)), 6) AS accuracy, round(avg(q) FILTER (s > cut), 6) AS precision, round(avg(CAST(s > cut AS INT)) FILTER (q = 1), 6) AS recall FROM y, c GROUP BY cut""")
def classifier_report(spark, d):
    """Measures of the naive Bayes quality score on held-out documents at the published cuts."""
    held = _labelled(spark, d).where(classify.held_out(F.col("doc_id"))).select("doc_id", "label").join(_nb_scores(spark, d), "doc_id")
    got = classify.report(held.withColumn("score", F.round("score", 6)), _CUTS)
    return got.select("cut", *(F.round(c, 6).alias(c) for c in ("accuracy", "precision", "recall")))


@query("lang_linear")
def lang_linear(spark, d):
    """The language of every document by the trained character model, with its probability; held_out rows taught nothing."""
    x = docs(spark, d).select("doc_id", "text", "lang")
    model = classify.train_language(x.where(~classify.held_out(F.col("doc_id"))))
    got = classify.predict_language(x, model, "lang_pred")
    return got.select("doc_id", "lang", classify.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", F.round("lang_score", 4).alias("score"))


@query("math_score_linear")
def linear(spark, d):
    """The trained linear classifier on stripped text, scored on every document."""
    labelled = classify.math_labels(math_docs(spark, d))
    model = classify.train_linear(labelled.where(~classify.held_out(F.col("doc_id"))))
    return classify.linear_score(labelled, model).select("doc_id", "label", F.round("score", 4).alias("score"))
