"""Stage 1: the cascade of prefilters, from cheap to costly."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import lexicon as L
from ..functions import columns as C

STAGES = ("kw", "cmd", "score")


def gate_stage(html: Column, stages=STAGES, commands=L.COMMANDS) -> Column:
    """The first JVM gate that a page passes: kw, cmd, or null. The command gate looks at the raw page, then at its quick text."""
    out = F.lit(None).cast("string")
    if "cmd" in stages:
        out = F.when(C.has_backslash_command(html) & C.has_common_command(C.quick_text(html), commands), F.lit("cmd"))
    return F.when(C.has_keyword(html), F.lit("kw")).otherwise(out) if "kw" in stages else out


def score_gate(df: DataFrame, score: Column | Callable[[DataFrame], DataFrame], cut: float = L.PREFILTER_CUT) -> DataFrame:
    """Decide the pages that no gate decided. A costly scorer gets only those: the filter stands below it, and the
    decided branch joins by union, since a Python scorer inside CASE would run for every row."""
    decided, open_ = df.where("pf_stage IS NOT NULL"), df.where("pf_stage IS NULL")
    scored = score(open_) if callable(score) and not isinstance(score, Column) else open_.withColumn("math_score", score)
    scored = scored.withColumn("pf_stage", F.when(F.col("math_score") > cut, "score").otherwise("drop"))
    return decided.withColumn("math_score", F.lit(None).cast("double")).unionByName(scored)


def cascade(pages: DataFrame, score: Column | Callable[[DataFrame], DataFrame] | None = None, cut: float = L.PREFILTER_CUT, stages=STAGES) -> DataFrame:
    """pages with pf_stage (kw, cmd, score, drop) and math_score (of those that were scored). Null html is dropped."""
    gated = pages.withColumn("pf_stage", F.when(F.col("html").isNull(), "drop").otherwise(gate_stage(F.col("html"), stages)))
    if "score" not in stages:
        return gated.withColumn("pf_stage", F.coalesce("pf_stage", F.lit("drop"))).withColumn("math_score", F.lit(None).cast("double"))
    return score_gate(gated, C.lexicon_score(C.quick_text(F.col("html"))) if score is None else score, cut)


def cascade_once(pages: DataFrame, scorer: Callable[[DataFrame], DataFrame], cut: float = L.PREFILTER_CUT) -> DataFrame:
    """As cascade with a scorer that stays in the JVM (text -> math_score): one scan, since pages that a gate decided
    give the scorer no text. Null html is dropped."""
    gated = pages.withColumn("pf_stage", F.when(F.col("html").isNull(), "drop").otherwise(gate_stage(F.col("html"))))
    open_ = F.col("pf_stage").isNull()
    scored = scorer(gated.withColumn("text", F.when(open_, C.quick_text(F.col("html"))))).drop("text")
    found = F.when(F.col("math_score") > cut, "score").otherwise("drop")
    return scored.withColumn("math_score", F.when(open_, F.col("math_score"))).withColumn("pf_stage", F.coalesce("pf_stage", found))


def top_commands(texts: DataFrame, text_col: str, key_col: str, n: int = 100) -> DataFrame:
    """The n commands that most documents have: cmd, docs, occurrences, rank."""
    seen = texts.select(key_col, F.explode(C.commands_in(F.col(text_col))).alias("cmd")).groupBy(key_col, "cmd").agg(F.count("*").alias("k"))
    per = seen.groupBy("cmd").agg(F.count("*").alias("docs"), F.sum("k").alias("occurrences"))
    return per.orderBy(F.desc("docs"), "cmd").limit(n)
