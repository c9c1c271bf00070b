"""The whole plan: prefilter, extraction, filters, deduplication, domain rules, with a ledger of rows in and out."""

from __future__ import annotations

import hashlib
import json
from collections.abc import Callable
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import lexicon as L
from ..functions import columns as C
from ..operators import classify, dedup, extract, prefilter


@dataclass(frozen=True)
class Config:
    prefilter_cut: float = L.PREFILTER_CUT
    cut_with_tex: float = L.CUT_WITH_TEX
    cut_without_tex: float = L.CUT_WITHOUT_TEX
    max_ppl: float = L.MAX_PERPLEXITY
    keep_lang: str = "en"
    tau: float = L.SIMILARITY
    fp_bits: int = 256
    dollar_policy: str = "cascade"
    seed: int = 7

    @property
    def config_id(self) -> str:
        """Names the configuration in stage tables and in the ledger, so that a restart knows finished work."""
        return hashlib.md5(json.dumps(asdict(self), sort_keys=True).encode()).hexdigest()[:12]


@dataclass(frozen=True)
class Models:
    """What is fitted once and used at every site. language: rows with text -> lang; math: rows with text -> math_score;
    perplexity: (page_id, text) -> (page_id, ppl). A vote of stop words and a word list stand in for the first two where
    they are not given; without the third its filter is off."""

    language: Callable[[DataFrame], DataFrame] | None = None
    math: Callable[[DataFrame], DataFrame] | None = None
    perplexity: Callable[[DataFrame], DataFrame] | None = None

    def with_language(self, df: DataFrame) -> DataFrame:
        return self.language(df) if self.language else df.withColumn("lang", classify.stop_word_vote(F.col("text")))

    def with_score(self, df: DataFrame) -> DataFrame:
        """Scored by the text without its LaTeX, which the label of the training rows is taken from."""
        bare = df.withColumn("_text", F.col("text")).withColumn("text", classify.strip_latex(F.col("text")))
        scored = self.math(bare) if self.math else bare.withColumn("math_score", C.lexicon_score(F.col("text")))
        return scored.withColumn("text", F.col("_text")).drop("_text")


@dataclass
class Result:
    docs: DataFrame
    dropped: DataFrame
    ledger: DataFrame


def run(spark: SparkSession, pages: DataFrame, cfg: Config, models: Models = Models()) -> Result:
    """pages (page_id, url, html) -> corpus, dropped rows with a verdict, and the ledger. No row goes without a verdict.

    html is scanned once: the prefilter's decisions are stored, with the html of what passes. One math score serves the
    prefilter, the dollar cascade and the filter. Each stage is written to the shared folder, which cuts lineage;
    the language model sees only what language and math keep.
    """
    gated = prefilter.cascade_once(pages.select("page_id", "url", "html"), models.with_score, cfg.prefilter_cut)
    gated = dedup._stored(gated.withColumn("html", F.when(F.col("pf_stage") != "drop", F.col("html"))))
    passed = gated.where("pf_stage <> 'drop'").select("page_id", "url", "html", C.quick_text(F.col("html")).alias("text")).repartition(F.xxhash64("page_id"))
    passed = models.with_score(passed).drop("text")
    docs = dedup._stored(extract.pages(passed, cfg.seed, cfg.dollar_policy))
    scored = models.with_score(models.with_language(docs))
    judged = classify.verdicts(scored, classify.FILTERS[:2], cfg.keep_lang, cfg.cut_with_tex, cfg.cut_without_tex, cfg.max_ppl)
    judged = judged.withColumn("verdict", F.when(F.col("status") != "ok", F.col("status")).when(F.coalesce(F.trim("text"), F.lit("")) == "", "empty").otherwise(F.col("verdict")))
    judged = dedup._stored(judged.select("page_id", "url", "text", "equations", "has_latex", "output_format", "status", "lang", "math_score", "verdict"))
    if models.perplexity is None:
        judged = judged.withColumn("ppl", F.lit(None).cast("double"))
    else:
        ppl = models.perplexity(judged.where("verdict = 'keep'").select("page_id", "text"))
        high = (F.col("verdict") == "keep") & ~F.coalesce(F.col("ppl") <= cfg.max_ppl, F.lit(False))
        judged = dedup._stored(judged.join(ppl.select("page_id", "ppl"), "page_id", "left").withColumn("verdict", F.when(high, "perplexity").otherwise(F.col("verdict"))))
    kept = judged.where("verdict = 'keep'")
    near = dedup.links_exact(dedup.fingerprint(kept, cfg.fp_bits, key="page_id"), cfg.tau, cfg.fp_bits, key="page_id")
    losers = dedup.components(near).where("node <> root").select(F.col("node").alias("page_id"))
    spam = C.host(F.col("url")).rlike(rf"(^|\.)({'|'.join(L.SPAM_HOSTS)})[0-9]*\.")
    final = judged.join(losers.withColumn("_dup", F.lit(True)), "page_id", "left")
    final = dedup._stored(final.withColumn("verdict", F.when((F.col("verdict") == "keep") & F.col("_dup"), "duplicate").when((F.col("verdict") == "keep") & spam, "blacklist").when((F.col("verdict") == "keep") & C.url_rule(F.col("url")).isNotNull(), "url_rule").otherwise(F.col("verdict"))).drop("_dup"))
    early = gated.where("pf_stage = 'drop'").select("page_id", "url", F.lit("prefilter").alias("verdict"))
    dropped = early.unionByName(final.where("verdict <> 'keep'").select("page_id", "url", "verdict"))
    everything = early.select("verdict").unionByName(final.select("verdict"))
    ledger = everything.groupBy("verdict").agg(F.count("*").alias("rows")).withColumn("config_id", F.lit(cfg.config_id))
    return Result(final.where("verdict = 'keep'").drop("verdict"), dropped, ledger)
