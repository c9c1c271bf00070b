"""Prefilter workloads over pages with known mathematics."""

from pyspark.sql import functions as F

from .. import lexicon as L
from ..fixtures import MATH_PAGES_SQL, STAGE_SQL, EXPECTED_STAGE, literal_rows, math_pages
from ..functions import columns as C
from ..operators import prefilter
from ..registry import query

_KW = " OR ".join(f"contains(html, {L.sql_quote(k)})" for k in L.MATH_KEYWORDS)
_LIST = "[" + ", ".join(L.sql_quote("\\" + c) for c in L.COMMANDS) + "]"


def quick_text_sql(html: str) -> str:
    kept = rf"""regexp_replace({html}, '(?s)<script type="math/[^"]*">(.*?)</script>', ' \1 ', 'g')"""
    kept = f"regexp_replace({kept}, '(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->', ' ', 'g')"
    return rf"trim(regexp_replace(regexp_replace({kept}, '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g'))"


def commands_sql(text: str) -> str:
    return rf"regexp_extract_all({text}, '(\\[A-Za-z]+)', 1)"


def score_sql(text: str) -> str:
    return "least((" + " + ".join(f"CAST(contains(lower({text}), '{w}') AS INT)" for w in L.MATH_WORDS) + ") / 5.0, 1.0)"


GATED_SQL = f"""{MATH_PAGES_SQL},
quick AS (SELECT page_id, url, html, variant, {quick_text_sql('html')} AS q FROM math_pages),
gated AS (SELECT *, CASE WHEN {_KW} THEN 'kw' WHEN regexp_matches(html, '\\\\[A-Za-z]+') AND list_has_any({commands_sql('q')}, {_LIST}) THEN 'cmd'
                    WHEN {score_sql('q')} > {L.PREFILTER_CUT} THEN 'score' ELSE 'drop' END AS pf_stage FROM quick)"""


@query("prefilter_keyword", f"WITH {MATH_PAGES_SQL} SELECT page_id, {_KW} AS has_keyword FROM math_pages")
def keyword(spark, d):
    return math_pages(spark, d).select("page_id", C.has_keyword(F.col("html")).alias("has_keyword"))


@query("prefilter_keyword_hits", f"WITH {MATH_PAGES_SQL} SELECT page_id, k AS keyword FROM math_pages, (SELECT unnest([{', '.join(map(L.sql_quote, L.MATH_KEYWORDS))}]) AS k) WHERE contains(html, k)")
def keyword_hits(spark, d):
    return math_pages(spark, d).select("page_id", F.explode(C.keyword_hits(F.col("html"))).alias("keyword"))


@query("prefilter_command", f"""WITH {GATED_SQL} SELECT page_id, regexp_matches(html, '\\\\[A-Za-z]+') AS has_command, list_has_any({commands_sql('q')}, {_LIST}) AS has_common FROM gated""")
def command(spark, d):
    html = F.col("html")
    return math_pages(spark, d).select("page_id", C.has_backslash_command(html).alias("has_command"), C.has_common_command(C.quick_text(html)).alias("has_common"))


@query("top_commands", f"""WITH {MATH_PAGES_SQL}, c AS (SELECT page_id, unnest({commands_sql('html')}) AS cmd FROM math_pages)
SELECT cmd, count(DISTINCT page_id) AS docs, count(*) AS occurrences FROM c GROUP BY cmd ORDER BY docs DESC, cmd LIMIT 100""")
def top_commands(spark, d):
    return prefilter.top_commands(math_pages(spark, d), "html", "page_id").select("cmd", "docs", F.col("occurrences").cast("long").alias("occurrences"))


@query("prefilter_funnel", f"WITH {GATED_SQL} SELECT coalesce(pf_stage, 'total') AS pf_stage, count(*) AS n_pages, CAST(sum(length(html)) AS BIGINT) AS chars FROM gated GROUP BY ROLLUP (pf_stage)")
def funnel(spark, d):
    got = prefilter.cascade(math_pages(spark, d)).rollup("pf_stage").agg(F.count("*").alias("n_pages"), F.sum(F.length("html")).alias("chars"))
    return got.select(F.coalesce("pf_stage", F.lit("total")).alias("pf_stage"), "n_pages", "chars")


@query("prefilter_recall", f"WITH {GATED_SQL} SELECT g.variant, e.expected, g.pf_stage, count(*) AS n_pages FROM gated g JOIN (SELECT * FROM {STAGE_SQL}) e USING (variant) GROUP BY ALL")
def recall(spark, d):
    expected = literal_rows(spark, list(EXPECTED_STAGE.items()), ["variant", "expected"], ["int", "string"])
    return prefilter.cascade(math_pages(spark, d)).join(F.broadcast(expected), "variant").groupBy("variant", "expected", "pf_stage").agg(F.count("*").alias("n_pages"))


@query("prefilter_lexicon_gate", f"WITH {GATED_SQL} SELECT page_id, round({score_sql('q')}, 6) AS math_score FROM gated WHERE pf_stage IN ('score', 'drop')")
def lexicon_gate(spark, d):
    return prefilter.cascade(math_pages(spark, d)).where("pf_stage IN ('score', 'drop')").select("page_id", F.round("math_score", 6).alias("math_score"))


_SAVING_SQL = f"""WITH {GATED_SQL}
SELECT count(*) AS n_pages, count(*) FILTER (pf_stage <> 'drop') AS passed, count(*) FILTER (pf_stage IN ('score', 'drop')) AS scored,
       round(CAST(count(*) AS DOUBLE) / count(*) FILTER (pf_stage <> 'drop'), 6) AS extraction_saving,
       round(CAST(count(*) AS DOUBLE) / count(*) FILTER (pf_stage IN ('score', 'drop')), 6) AS scoring_saving FROM gated"""


@query("cascade_saving", _SAVING_SQL)
def saving(spark, d):
    """How many times less the costly steps run because of the cascade."""
    passed, scored = F.count_if(F.col("pf_stage") != "drop"), F.count_if(F.col("pf_stage").isin("score", "drop"))
    got = prefilter.cascade(math_pages(spark, d)).agg(F.count("*").alias("n_pages"), passed.alias("passed"), scored.alias("scored"))
    return got.withColumn("extraction_saving", F.round(F.col("n_pages") / F.col("passed"), 6)).withColumn("scoring_saving", F.round(F.col("n_pages") / F.col("scored"), 6))


_VARIANTS_SQL = f"""WITH {GATED_SQL} SELECT s.config, count(*) FILTER (s.keep) AS passed FROM (
 SELECT 'kw' AS config, ({_KW}) AS keep FROM gated UNION ALL
 SELECT 'kw+cmd', pf_stage IN ('kw', 'cmd') FROM gated UNION ALL
 SELECT 'score', {score_sql('q')} > {L.PREFILTER_CUT} FROM gated UNION ALL
 SELECT 'kw+cmd+score', pf_stage <> 'drop' FROM gated) s GROUP BY 1"""


@query("prefilter_variants", _VARIANTS_SQL)
def variants(spark, d):
    """Keyword only, without the classifier, classifier only, and the whole cascade."""
    pages, out = math_pages(spark, d), None
    for config in (("kw",), ("kw", "cmd"), ("score",), ("kw", "cmd", "score")):
        got = prefilter.cascade(pages, stages=config).agg(F.lit("+".join(config)).alias("config"), F.count_if(F.col("pf_stage") != "drop").alias("passed"))
        out = got if out is None else out.unionByName(got)
    return out


@query("prefilter_cut_sweep", f"WITH {GATED_SQL} SELECT cut, count(*) FILTER ({score_sql('q')} > cut) AS passed FROM gated, (SELECT unnest([0.17, 0.2, 0.4, 0.6, 0.8]::DOUBLE[]) AS cut) GROUP BY cut")
def cut_sweep(spark, d):
    scored = math_pages(spark, d).select(C.lexicon_score(C.quick_text(F.col("html"))).alias("s"))
    cuts = (0.17, 0.2, 0.4, 0.6, 0.8)
    one = scored.agg(*(F.count_if(F.col("s") > c).alias(f"c{i}") for i, c in enumerate(cuts)))
    return one.select(F.inline(F.array(*(F.struct(F.lit(c).alias("cut"), F.col(f"c{i}").alias("passed")) for i, c in enumerate(cuts)))))
