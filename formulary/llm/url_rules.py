"""URL filtering by pattern rules indexed by their rarest literal token, in DataFrame operations only.

A rule is a pattern over `host + path` with the literal tokens that every matching URL must contain. Token counts
over all URLs decide which of a rule's tokens is its index entry: the one that the fewest URLs have. Each URL's
tokens fetch candidate rules, and only those run their pattern. Of the rules that match, the one with the highest
rank wins: listed host and path rules before patterns, longer before shorter.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A rule set beyond this many rows isn't broadcast; the join is then left to Spark.
BROADCAST_RULES = 100_000
TOKENS = r"[^a-z0-9]+"


@dataclass(frozen=True)
class Rule:
    """name: shown for listed rules (null for patterns); tokens: literal, lower case, each a whole token of any match."""

    name: str | None
    pattern: str
    tokens: tuple[str, ...]
    verdict: str
    rank: int


def listed(host: str, path: str, verdict: str) -> Rule:
    """The host and all its subdomains, paths that start with `path`."""
    whole = re.split(TOKENS, (host + path).lower())
    if path and path[-1].isascii() and path[-1].isalnum():
        whole = whole[:-1]  # the last token may go on in the URL
    quoted = re.sub(r"([^A-Za-z0-9/_-])", r"\\\1", host) + re.sub(r"([^A-Za-z0-9/_-])", r"\\\1", path)
    return Rule(host + path, rf"^(?:[^/]*\.)?{quoted}", tuple(t for t in whole if t), verdict, 1_000 + len(host + path))


def pattern(regex: str, tokens: tuple[str, ...], verdict: str = "block") -> Rule:
    return Rule(None, regex, tokens, verdict, len(regex))


LISTED = (listed("org", "/", "allow"), listed("example.org", "/es/", "block"), listed("example.org", "/en/1", "block"), listed("com", "/fr/", "allow"), listed("com", "/de/", "block"))
#: What judges a URL that no listed rule fits; a URL that nothing fits is allowed.
PATTERNS = (
    pattern(r"(?:^|\.)cheap-pills[0-9]*\.", ("cheap",)),
    pattern(r"(?:^|\.)casino-win[0-9]*\.", ("casino",)),
    pattern(r"(?:^|\.)free-bets[0-9]*\.", ("free",)),
    pattern(r"(?:^|\.)adult-x[0-9]*\.", ("adult",)),
    pattern(r"(?:^|\.)spam-farm[0-9]*\.", ("spam",)),
    pattern(r"(?:^|\.)ads-track[0-9]*\.", ("ads",)),
    pattern(r"^[^/]*/(?:[^/]+/)*(?:login|signup)/?$", ()),
)


def split_url(urls: DataFrame, url_col: str = "url") -> DataFrame:
    """Adds host (after the first :// up to /, ?, # or the end; A-Z lower-cased) and path (from there up to ?, # or the end)."""
    out = urls.withColumn("_url", F.col(url_col).cast("string"))
    out = out.withColumn("_rest", F.when(F.instr("_url", "://") > 0, F.substring_index(F.substring_index(F.expr("substring(_url, instr(_url, '://') + 3)"), "?", 1), "#", 1)))
    host = F.translate(F.substring_index("_rest", "/", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.when(F.instr("_rest", "/") > 0, F.expr("substring(_rest, instr(_rest, '/'))")).otherwise("")
    return out.withColumn("host", F.coalesce(host, F.lit(""))).withColumn("path", F.coalesce(path, F.lit(""))).drop("_url", "_rest")


def rule_table(spark: SparkSession, rules: tuple[Rule, ...]) -> DataFrame:
    rows = [F.struct(F.lit(i).alias("rule_id"), F.lit(r.name).cast("string").alias("rule"), F.lit(r.pattern).alias("pattern"), F.array(*map(F.lit, dict.fromkeys(r.tokens))).cast("array<string>").alias("tokens"), F.lit(r.verdict).alias("rule_verdict"), F.lit(r.rank).alias("rank")) for i, r in enumerate(rules)]
    return spark.range(1).select(F.inline(F.array(*rows)))


def _small(rules: DataFrame, n: int) -> DataFrame:
    return F.broadcast(rules) if n <= BROADCAST_RULES else rules


def url_tokens(host: Column, path: Column) -> Column:
    """Distinct lower-case tokens, and the empty one, under which rules without a literal token are indexed."""
    return F.array_distinct(F.array_append(F.split(F.lower(F.concat(host, path)), TOKENS), F.lit("")))


def index_rules(tokens: DataFrame, rules: DataFrame, n_rules: int) -> DataFrame:
    """rule rows with `token`, the rarest of their tokens over all URLs (ties: the first in order); '' if they have none."""
    wanted = rules.select("rule_id", F.explode("tokens").alias("token"))
    seen = tokens.join(_small(wanted.select("token").distinct(), n_rules), "token", "left_semi").groupBy("token").agg(F.count("*").alias("df"))
    rare = wanted.join(_small(seen, n_rules), "token", "left").groupBy("rule_id").agg(F.min(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "token")).alias("least"))
    return rules.join(_small(rare, n_rules), "rule_id", "left").withColumn("token", F.coalesce("least.token", F.lit(""))).drop("least", "tokens")


def judge(urls: DataFrame, rules: tuple[Rule, ...] = LISTED + PATTERNS, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row per input row: page_id, host, path, rule, verdict.

    Null URLs and those without :// have empty host and path, no rule, and are allowed; repeated rows are judged
    each; a null id keeps its row; other columns are ignored whatever their names; an empty table gives an empty
    result. With equal ranks the rule that comes first wins.
    """
    spark = urls.sparkSession
    parts = split_url(urls.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"))).drop("url")
    distinct = parts.groupBy("host", "path").agg(F.count("*").alias("n"))  # a URL that repeats is judged once
    posted = distinct.select("host", "path", F.explode(url_tokens(F.col("host"), F.col("path"))).alias("token"))
    index = index_rules(posted.select("token"), rule_table(spark, rules), len(rules))
    hits = posted.join(_small(index, len(rules)), "token").where(F.expr("regexp_like(concat(host, path), pattern)"))
    best = hits.groupBy("host", "path").agg(F.max(F.struct("rank", (-F.col("rule_id")).alias("first"), "rule", "rule_verdict")).alias("best"))
    out = parts.join(best, ["host", "path"], "left")
    return out.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.rule_verdict", F.lit("allow")).alias("verdict"))


def op4_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return judge(table(spark, sf_dir, "pages"))


_CASES = "\n".join(f"           WHEN regexp_matches(host || path, '{r.pattern}') THEN '{r.name}|{r.verdict}'" for r in sorted(LISTED, key=lambda r: -r.rank))
_SPAM = " OR ".join(f"regexp_matches(host || path, '{r.pattern}')" for r in PATTERNS)
ORACLE_SQL = f"""
WITH a AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS r FROM pages),
b AS (SELECT page_id, split_part(split_part(r, '?', 1), '#', 1) AS r FROM a),
c AS (SELECT page_id, coalesce(translate(split_part(r, '/', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
             coalesce(CASE WHEN strpos(r, '/') > 0 THEN substr(r, strpos(r, '/')) ELSE '' END, '') AS path FROM b),
d AS (SELECT *, CASE
{_CASES} END AS won FROM c)
SELECT page_id, host, path, split_part(won, '|', 1) AS rule,
       CASE WHEN won IS NOT NULL THEN split_part(won, '|', 2) WHEN {_SPAM} THEN 'block' ELSE 'allow' END AS verdict
FROM d
"""
