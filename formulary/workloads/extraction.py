"""Workloads of the full extractor and its baselines, and the whole corpus pipeline."""

from pyspark.sql import functions as F

from ..fixtures import MATH_PAGES_SQL, math_docs, math_pages, truth
from ..functions import columns as C
from ..operators import classify, extract, language_model as lm
from ..plans import corpus
from ..registry import query
from .prefilter import quick_text_sql


@query("extract_pages")
def pages(spark, d):
    x = extract.pages(math_pages(spark, d).select("page_id", "url", "html"))
    return x.select("page_id", "output_format", "has_latex", F.size("equations").alias("n_equations"), F.md5(F.col("text").cast("binary")).alias("text_md5"), "status")


@query("extract_plain_strip", f"WITH {MATH_PAGES_SQL} SELECT page_id, md5({quick_text_sql('html')}) AS text_md5 FROM math_pages")
def plain(spark, d):
    return math_pages(spark, d).select("page_id", F.md5(C.quick_text(F.col("html")).cast("binary")).alias("text_md5"))


@query("extract_article_regex", f"""SELECT page_id, md5({quick_text_sql("regexp_extract(html, '(?s)<article>(.*?)</article>', 1)")}) AS text_md5 FROM pages""")
def article(spark, d):
    p = spark.read.parquet(f"{d}/pages.parquet")
    return p.select("page_id", F.md5(C.quick_text(F.regexp_extract("html", r"(?s)<article>(.*?)</article>", 1)).cast("binary")).alias("text_md5"))


@query("extraction_recall")
def recall(spark, d):
    """Share of the words of a page's document that the extractor finds, and of its words that are the document's."""
    p = spark.read.parquet(f"{d}/pages.parquet")
    got = extract.pages(p).select("page_id", F.regexp_extract("url", "/[a-z]{2}/([0-9]+)", 1).cast("long").alias("doc_id"), F.array_distinct(C.tokens(F.col("text"))).alias("found"))
    x = got.join(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", F.array_distinct(C.tokens(F.col("text"))).alias("true")), "doc_id")
    both = F.size(F.array_intersect("found", "true"))
    return x.agg(F.count("*").alias("n_pages"), F.round(F.avg(both / F.size("true")), 4).alias("recall"), F.round(F.avg(both / F.size("found")), 4).alias("precision"))


@query("interplay")
def interplay(spark, d):
    """Pages that the math filter keeps after extraction that loses LaTeX, against the full extractor."""
    p = math_pages(spark, d).select("page_id", "url", "html")
    full = extract.pages(p).select("page_id", F.lit("ours").alias("extractor"), "text", "has_latex")
    bare = p.select("page_id", F.lit("plain_strip").alias("extractor"), C.quick_text(F.col("html")).alias("text"), F.lit(False).alias("has_latex"))
    x = full.unionByName(bare).withColumn("s", C.lexicon_score(F.col("text")))
    keep = F.col("s") > F.when(F.col("has_latex"), 0.17).otherwise(0.8)
    return x.groupBy("extractor").agg(F.count("*").alias("n_pages"), F.count_if("has_latex").alias("with_latex"), F.count_if(F.coalesce(keep, F.lit(False))).alias("kept"))


def fitted_models(spark, d, order: int = 5) -> corpus.Models:
    """Language from documents.lang, math from common commands in texts that are then stripped of them, and a language
    model of the clean English documents with mathematics planted; all on rows that are not held out."""
    x = math_docs(spark, d)
    learn = x.where(~classify.held_out(F.col("doc_id")))
    language = classify.train_language(learn)
    math = classify.train_linear(classify.math_labels(learn))
    clean = spark.read.parquet(f"{d}/labels.parquet").where("quality = 1").select("doc_id")
    model = lm.ModifiedKneserNey(learn.where("lang = 'en'").join(clean, "doc_id", "left_semi").select("doc_id", "text"), order)
    return corpus.Models(
        lambda df: classify.predict_language(df, language),
        lambda df: classify.linear_score(df, math, "math_score"),
        lambda df: lm.perplexity(model.log_probabilities(df, "page_id"), "page_id"),
    )


@query("equation_prf")
def equation_prf(spark, d):
    """Precision, recall and F1 of the extractor's equations against those planted, by encoding and over all. Equal
    equations of a page count as often as they occur; those in removed elements are not to be found."""
    p = math_pages(spark, d)
    found = extract.pages(p).select("page_id", F.explode("equations").alias("e")).groupBy("page_id", F.col("e.encoding").alias("encoding"), F.col("e.latex").alias("latex")).agg(F.count("*").alias("f"))
    planted = p.select("page_id", "variant").join(F.broadcast(truth(spark)), "variant").groupBy("page_id", "encoding", "latex").agg(F.count("*").alias("t"))
    x = found.join(planted, ["page_id", "encoding", "latex"], "full").na.fill(0, ["f", "t"]).withColumn("hit", F.least("f", "t"))
    s = x.groupingSets([["encoding"], []], "encoding").agg(F.sum("f").alias("n_found"), F.sum("t").alias("n_true"), F.sum("hit").alias("n_hit"))
    return s.select(
        F.coalesce("encoding", F.lit("any")).alias("encoding"), "n_found", "n_true", F.round(F.try_divide("n_hit", "n_found"), 4).alias("precision"),
        F.round(F.try_divide("n_hit", "n_true"), 4).alias("recall"), F.round(F.try_divide(2 * F.col("n_hit"), F.col("n_found") + F.col("n_true")), 4).alias("f1"),
    )


@query("pipeline_funnel")
def funnel(spark, d):
    """The whole plan with its fitted models: language, math score and a language model of order 5."""
    return corpus.run(spark, math_pages(spark, d), corpus.Config(), fitted_models(spark, d)).ledger
