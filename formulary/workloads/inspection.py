"""Inspection workloads: domains, longest documents, blacklist, URL rules, and the line stage."""

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .. import lexicon as L
from ..fixtures import md5_number, md5_number_sql
from ..functions import columns as C
from ..operators import domains, lines
from ..registry import query

HOST_SQL = "lower(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1))"
DOMAIN_SQL = f"CASE WHEN {HOST_SQL} <> '' THEN array_to_string(string_split({HOST_SQL}, '.')[-2:], '.') END"
DOMAIN3_SQL = f"CASE WHEN {HOST_SQL} <> '' THEN array_to_string(string_split({HOST_SQL}, '.')[-3:], '.') END"


def _pages(spark, d):
    return spark.read.parquet(f"{d}/pages.parquet")


def _docs(spark, d):
    return spark.read.parquet(f"{d}/documents.parquet")


def _top_sql(measure: str) -> str:
    return f"""WITH g AS (SELECT {DOMAIN3_SQL} AS domain, count(*) AS n_docs, CAST(sum(length(html)) AS BIGINT) AS n_chars FROM pages GROUP BY 1)
SELECT domain, n_docs, n_chars, round(100.0 * {measure} / sum({measure}) OVER (), 4) AS share FROM g ORDER BY {measure} DESC, domain LIMIT 20"""


@query("top_domains_docs", _top_sql("n_docs"))
def top_docs(spark, d):
    return domains.top(domains.totals(_pages(spark, d), "html", labels=3), "n_docs", 20)


@query("top_domains_chars", _top_sql("n_chars"))
def top_chars(spark, d):
    return domains.top(domains.totals(_pages(spark, d), "html", labels=3), "n_chars", 20)


@query("domain_concentration", f"""WITH g AS (SELECT {DOMAIN3_SQL} AS domain, sum(length(html)) AS c FROM pages GROUP BY 1),
r AS (SELECT c, row_number() OVER (ORDER BY c DESC, domain) AS k FROM g)
SELECT count(*) AS n_domains, round(CAST(100.0 AS DOUBLE) * sum(c) FILTER (k <= 10) / sum(c), 4) AS top_share FROM r""")
def concentration(spark, d):
    return domains.concentration(domains.totals(_pages(spark, d), "html", labels=3), 10)


@query("domain_lorenz", f"""WITH g AS (SELECT {DOMAIN3_SQL} AS domain, sum(length(html)) AS c FROM pages GROUP BY 1)
SELECT domain, row_number() OVER w AS k, round(CAST(100.0 AS DOUBLE) * sum(c) OVER w / sum(c) OVER (), 4) AS running_share FROM g WINDOW w AS (ORDER BY c DESC, domain)""")
def lorenz(spark, d):
    """Running share of the characters over domains from large to small; the window holds domains, not documents."""
    g, w = domains.totals(_pages(spark, d), "html", labels=3), W.orderBy(F.desc("n_chars"), "domain")
    return g.select("domain", F.row_number().over(w).cast("long").alias("k"), F.round(100.0 * F.sum("n_chars").over(w) / F.sum("n_chars").over(W.partitionBy()), 4).alias("running_share"))


@query("source_totals", "SELECT source, count(*) AS n_docs, CAST(sum(n_chars) AS BIGINT) AS n_chars FROM documents GROUP BY source")
def source_totals(spark, d):
    return _docs(spark, d).groupBy("source").agg(F.count("*").alias("n_docs"), F.sum("n_chars").alias("n_chars"))


@query("longest_docs", "SELECT doc_id, n_chars, source FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25")
def longest(spark, d):
    return _docs(spark, d).select("doc_id", "n_chars", "source").orderBy(F.desc("n_chars"), "doc_id").limit(25)


_SPAM_SQL = f"regexp_matches({HOST_SQL}, '(^|[.])({'|'.join(L.SPAM_HOSTS)})[0-9]*[.]')"


@query("blacklist_filter", f"SELECT page_id, {HOST_SQL} AS host FROM pages WHERE NOT {_SPAM_SQL}")
def blacklist(spark, d):
    pages = _pages(spark, d).select("page_id", C.host(F.col("url")).alias("host"))
    listed = pages.where(F.col("host").rlike(rf"(^|\.)({'|'.join(L.SPAM_HOSTS)})[0-9]*\.")).select("host").distinct()
    return domains.drop_blacklisted(pages, listed)


@query("url_rules", "SELECT page_id, CASE WHEN regexp_matches(url, '/(?:user|profile|members?)/') THEN 'profile' WHEN regexp_matches(url, '[?&](?:q|query|search|page)=') THEN 'listing' WHEN regexp_matches(url, '/abs/') THEN 'abstract' END AS rule FROM pages")
def url_rules(spark, d):
    return _pages(spark, d).select("page_id", C.url_rule(F.col("url")).alias("rule"))


_T = "|".join(L.TRACKING)


@query("url_canonical", rf"""WITH a AS (SELECT page_id, regexp_replace(regexp_replace(url, '#.*$', ''), '([?&])(?:{_T})=[^&]*', '\1', 'g') AS u FROM pages),
b AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(u, '[?&]+$', ''), '\?&+', '?', 'g'), '&&+', '&', 'g') AS u FROM a) SELECT page_id, regexp_replace(u, '/$', '') AS url FROM b""")
def url_canonical(spark, d):
    return _pages(spark, d).select("page_id", C.canonical(F.col("url")).alias("url"))


@query("review_sample", f"""WITH r AS (SELECT page_id, {DOMAIN3_SQL} AS domain, row_number() OVER (PARTITION BY {DOMAIN3_SQL} ORDER BY {md5_number_sql("page_id || '/1'")}, page_id) AS k FROM pages)
SELECT page_id, domain, k FROM r WHERE k <= 5""")
def review(spark, d):
    return domains.review_sample(_pages(spark, d), per=5, seed=1, labels=3).select("page_id", "domain", F.col("k").cast("long").alias("k"))


@query("site_types", f"""SELECT CASE WHEN regexp_matches(url, 'forum|thread|topic|question') THEN 'Forum' WHEN regexp_matches(url, 'arxiv|/pdf/|/abs/|doi') THEN 'Paper' WHEN regexp_matches({HOST_SQL}, '^blog[.]') THEN 'Blog'
WHEN regexp_matches({HOST_SQL}, '^(?:wiki|docs)[.]') OR regexp_matches(url, 'dictionary') THEN 'Reference' WHEN regexp_matches(url, 'course|lecture|lesson|[.]edu/') THEN 'Educational' ELSE 'Other' END AS site_type, count(*) AS n_pages FROM pages GROUP BY 1""")
def site_types(spark, d):
    return _pages(spark, d).groupBy(C.site_type(F.col("url")).alias("site_type")).agg(F.count("*").alias("n_pages"))


# ---- lines

_LINES_SQL = "l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)"


@query("repeated_lines", f"WITH {_LINES_SQL} SELECT line, count(DISTINCT doc_id) AS n_docs, count(*) AS n FROM l WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 10")
def repeated(spark, d):
    return lines.repeated(_docs(spark, d), "doc_id", "text", 10)


_TRIGGER_SQL = f"1 + {md5_number_sql("doc_id || '/3'")} % 3"
_HITS_SQL = " + ".join(f"CAST(contains(lower(x), {L.sql_quote(p)}) AS INT)" for p in L.PHRASES)


@query("boilerplate_removed", f"SELECT doc_id, array_to_string(list_filter(string_split(text, chr(10)), lambda x: {_HITS_SQL} < {_TRIGGER_SQL}), chr(10)) AS text FROM documents")
def boilerplate(spark, d):
    trigger = (F.pmod(md5_number(F.concat(F.col("doc_id").cast("string"), F.lit("/3"))), F.lit(3)) + 1).cast("int")
    return _docs(spark, d).select("doc_id", lines.drop_boilerplate(F.col("text"), trigger).alias("text"))


@query("extract_params", f"SELECT page_id, CASE WHEN {md5_number_sql("page_id || '/7'")} % 2 = 0 THEN 'plain' ELSE 'markdown' END AS output_format, CAST(1 + {md5_number_sql("page_id || '/8'")} % 3 AS INT) AS boilerplate_trigger FROM pages")
def params(spark, d):
    return _pages(spark, d).select("page_id", *lines.parameters(F.col("page_id"), 7))


@query("escape_dollars", r"SELECT doc_id, regexp_replace(text, '\$', '\\$', 'g') AS text FROM documents WHERE contains(text, '$')")
def escape(spark, d):
    return _docs(spark, d).where(F.col("text").contains("$")).select("doc_id", lines.escape_dollars(F.col("text")).alias("text"))


@query("empty_headers", r"""WITH h AS (SELECT page_id, list_concat(['# A', '## B', ''], string_split(url, '/'), ['# End']) AS a FROM pages)
SELECT page_id, array_to_string(list_filter(a, lambda x, i: NOT (regexp_matches(x, '^#+ ') AND len(list_filter(a[i + 1:], lambda y: trim(y) <> '')) > 0 AND regexp_matches(list_filter(a[i + 1:], lambda y: trim(y) <> '')[1], '^#+ ')
 OR regexp_matches(x, '^#+ ') AND len(list_filter(a[i + 1:], lambda y: trim(y) <> '')) = 0)), chr(10)) AS text FROM h""")
def empty_headers(spark, d):
    made = F.concat(F.array(F.lit("# A"), F.lit("## B"), F.lit("")), F.split("url", "/"), F.array(F.lit("# End")))
    return _pages(spark, d).select("page_id", lines.drop_empty_headers(F.array_join(made, "\n")).alias("text"))
