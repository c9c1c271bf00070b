"""LaTeX extraction workloads: patterns by encoding, shares, dollar policies, missed mathematics."""

from pyspark.sql import functions as F

from .. import lexicon as L
from ..fixtures import MATH_PAGES_SQL, math_pages
from ..functions import columns as C
from ..registry import query
from .prefilter import _LIST, commands_sql, quick_text_sql


def _spans_sql(name: str) -> str:
    pattern, group = L.ENCODINGS[name]
    return f"regexp_extract_all(html, {L.sql_quote(pattern)}, {group})"


_INLINE_SQL = f"regexp_extract_all(regexp_replace(html, {L.sql_quote(L.DISPLAY_STRIP)}, ' ', 'g'), {L.sql_quote(L.INLINE_PATTERN)}, 1)"


def _one_encoding(name: str):
    sql = f"WITH {MATH_PAGES_SQL}, s AS (SELECT page_id, {_spans_sql(name)} AS a FROM math_pages) SELECT page_id, CAST(i - 1 AS INT) AS ord, a[i] AS latex FROM s, (SELECT unnest(range(1, 500)) AS i) WHERE i <= len(a)"

    @query(f"latex_{name}", sql)
    def run(spark, d):
        return math_pages(spark, d).select("page_id", F.posexplode(C.spans(F.col("html"), name)).alias("ord", "latex"))


for _name in L.ENCODINGS:
    _one_encoding(_name)


@query("latex_inline", f"WITH {MATH_PAGES_SQL} SELECT page_id, unnest({_INLINE_SQL}) AS latex FROM math_pages WHERE contains(html, 'MathJax')")
def inline(spark, d):
    return math_pages(spark, d).where(F.col("html").contains("MathJax")).select("page_id", F.explode(C.dollar_spans(F.col("html"))).alias("latex"))


@query("renderer_active", f"WITH {MATH_PAGES_SQL} SELECT page_id, contains(html, 'MathJax') OR list_has_any({commands_sql(quick_text_sql('html'))}, {_LIST}) AS active FROM math_pages")
def renderer(spark, d):
    return math_pages(spark, d).select("page_id", C.renderer_active(F.col("html")).alias("active"))


@query("configured_delimiters", rf"""WITH {MATH_PAGES_SQL}, c AS (SELECT page_id, regexp_extract(html, 'inlineMath: \[\[(.*?)\]\]', 1) AS body FROM math_pages)
SELECT page_id, regexp_extract(body, '''([^'']*)'',''([^'']*)''', 1) AS open, regexp_extract(body, '''([^'']*)'',''([^'']*)''', 2) AS close FROM c WHERE body <> ''""")
def configured(spark, d):
    body = F.regexp_extract("html", r"inlineMath: \[\[(.*?)\]\]", 1)
    pair = r"'([^']*)','([^']*)'"
    return math_pages(spark, d).select("page_id", body.alias("body")).where("body <> ''").select("page_id", F.regexp_extract("body", pair, 1).alias("open"), F.regexp_extract("body", pair, 2).alias("close"))


_SHARE_ROWS = " UNION ALL ".join(f"SELECT page_id, '{n}' AS encoding FROM math_pages WHERE len({_spans_sql(n)}) > 0" for n in L.ENCODINGS)


@query("encoding_share", f"""WITH {MATH_PAGES_SQL}, e AS ({_SHARE_ROWS}), n AS (SELECT count(*) AS n FROM math_pages)
SELECT coalesce(encoding, 'any') AS encoding, count(DISTINCT page_id) AS n_pages, round(100.0 * count(DISTINCT page_id) / any_value(n.n), 4) AS share FROM e, n GROUP BY GROUPING SETS ((encoding), ())""")
def encoding_share(spark, d):
    """Pages with at least one equation of each encoding; a page may have several."""
    pages = math_pages(spark, d)
    found = F.filter(F.array(*(F.when(F.size(C.spans(F.col("html"), n)) > 0, F.lit(n)) for n in L.ENCODINGS)), lambda x: x.isNotNull())
    marked = pages.select(found.alias("found"))
    per = marked.select(F.explode("found").alias("encoding")).groupBy("encoding").agg(F.count("*").alias("n_pages"))
    total = marked.agg(F.count("*").alias("n"), F.count_if(F.size("found") > 0).alias("any_math"))
    rows = per.unionByName(total.select(F.lit("any").alias("encoding"), F.col("any_math").alias("n_pages")))
    return rows.crossJoin(F.broadcast(total.select("n"))).select("encoding", "n_pages", F.round(100.0 * F.col("n_pages") / F.col("n"), 4).alias("share"))


_BASE = f"len({_spans_sql('script')}) + len({_spans_sql('annotation')})"


@query("baseline_script_annotation", f"WITH {MATH_PAGES_SQL} SELECT page_id, CAST({_BASE} AS INT) AS found FROM math_pages WHERE {_BASE} > 0")
def baseline(spark, d):
    """The closed predecessor's rules: math scripts and annotated math tags only."""
    n = F.size(C.spans(F.col("html"), "script")) + F.size(C.spans(F.col("html"), "annotation"))
    return math_pages(spark, d).select("page_id", n.alias("found")).where("found > 0")


@query("missed_math", f"""WITH {MATH_PAGES_SQL} SELECT CAST(variant AS INT) AS variant, substr(html, strpos(html, '\\frac') - 10, 16) AS context, count(*) AS n_pages FROM math_pages
WHERE contains(html, '\\frac') AND {_BASE} = 0 GROUP BY ALL""")
def missed(spark, d):
    """Pages with a fraction from which the baseline extracts nothing, by the context of the fraction."""
    html = F.col("html")
    probe = math_pages(spark, d).where(html.contains("\\frac") & (F.size(C.spans(html, "script")) + F.size(C.spans(html, "annotation")) == 0))
    return probe.select("variant", F.substring(html, F.instr(html, "\\frac") - 10, F.lit(16)).alias("context")).groupBy("variant", "context").agg(F.count("*").alias("n_pages"))


_POLICY = f"""p AS (SELECT page_id, variant, contains(html, 'MathJax') AS has_script, {_INLINE_SQL} AS spans, {quick_text_sql('html')} AS q FROM math_pages),
w AS (SELECT *, len(list_filter(spans, lambda x: list_has_any({commands_sql('x')}, {_LIST}))) AS with_cmd FROM p)"""
_HIT = {"naive": "len(spans)", "script": "CASE WHEN has_script THEN len(spans) ELSE 0 END", "command": "CASE WHEN with_cmd > 0 THEN len(spans) ELSE 0 END", "score": "CASE WHEN {s} > 0.8 THEN len(spans) ELSE 0 END"}
_HIT["cascade"] = f"CASE WHEN has_script OR with_cmd > 0 THEN len(spans) ELSE {_HIT['score']} END"


def _policy_sql() -> str:
    from .prefilter import score_sql

    rows = " UNION ALL ".join(f"SELECT '{k}' AS policy, variant, {v.replace('{s}', score_sql('q'))} AS n FROM w" for k, v in _HIT.items())
    return f"""WITH {MATH_PAGES_SQL}, {_POLICY}, r AS ({rows})
SELECT policy, CAST(sum(n) AS BIGINT) AS n_spans, count(*) FILTER (n > 0) AS n_pages, CAST(coalesce(sum(n) FILTER (variant NOT IN (0, 2, 12, 13, 17)), 0) AS BIGINT) AS false_spans FROM r GROUP BY policy"""


@query("dollar_policy_counts", _policy_sql())
def dollar_policies(spark, d):
    """Spans that each dollar policy takes for mathematics, and those on pages whose dollars are none."""
    html = F.col("html")
    with_cmd = F.size(F.filter("spans", lambda x: C.has_common_command(x)))
    p = math_pages(spark, d).select("variant", html.contains("MathJax").alias("has_script"), C.dollar_spans(html).alias("spans"), (C.lexicon_score(C.quick_text(html)) > L.PREFILTER_CUT).alias("mathy"))
    p = p.withColumn("with_cmd", with_cmd > 0).withColumn("n", F.size("spans"))
    rules = {"naive": F.lit(True), "script": F.col("has_script"), "command": F.col("with_cmd"), "score": F.col("mathy"), "cascade": F.col("has_script") | F.col("with_cmd") | F.col("mathy")}
    rows = p.select("variant", F.inline(F.array(*(F.struct(F.lit(k).alias("policy"), F.when(v, F.col("n")).otherwise(0).alias("n")) for k, v in rules.items()))))
    trap = ~F.col("variant").isin(0, 2, 12, 13, 17)
    return rows.groupBy("policy").agg(F.sum("n").alias("n_spans"), F.count_if(F.col("n") > 0).alias("n_pages"), F.sum(F.when(trap, F.col("n")).otherwise(0)).alias("false_spans"))
