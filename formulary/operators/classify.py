"""Language identification, the math score, and the ordered filters."""

from __future__ import annotations

from pyspark.ml import Pipeline, PipelineModel
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import IDF, HashingTF, NGram, Normalizer, RegexTokenizer, SQLTransformer, StringIndexer
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import lexicon as L
from ..fixtures import md5_number
from ..functions import columns as C


def held_out(key: Column, parts: int = 5) -> Column:
    return F.pmod(md5_number(key.cast("string")), F.lit(parts)) == parts - 1


def stop_word_vote(text: Column) -> Column:
    """The language most of whose stop words occur among the tokens; ties by name; und if none does."""

    def of(t: Column) -> Column:
        count = lambda words: F.size(F.filter(t, lambda x: x.isin(*words)))
        votes = F.array(*(F.struct(count(words).alias("k"), F.lit(lang).alias("lang")) for lang, words in sorted(L.STOP_WORDS.items(), reverse=True)))
        return C.bind(F.array_max(votes), lambda best: F.when(best["k"] > 0, best["lang"]).otherwise("und"))

    return C.bind(C.tokens(text), of)


def naive_bayes(docs: DataFrame, label: str) -> tuple[DataFrame, DataFrame]:
    """(token, label, c) counts of document tokens, and (label, docs, total) of the classes."""
    t = docs.select(label, F.explode(C.tokens(F.col("text"))).alias("token")).groupBy("token", label).agg(F.count("*").alias("c"))
    return t, t.groupBy(label).agg(F.sum("c").alias("total"))


def nb_score(docs: DataFrame, model: tuple[DataFrame, DataFrame], key: str = "doc_id", label: str = "label") -> DataFrame:
    """key, score of class 1 against 0: logistic of the mean log ratio of add-one estimates over the tokens; 0.5 for a
    text without tokens."""
    t, totals = model
    v = t.select("token").distinct().agg(F.count("*").alias("v"))
    wide = t.groupBy("token").pivot(label, [0, 1]).agg(F.sum("c")).na.fill(0).toDF("token", "c0", "c1")
    tot = totals.agg(F.sum(F.when(F.col(label) == 0, F.col("total"))).alias("t0"), F.sum(F.when(F.col(label) == 1, F.col("total"))).alias("t1"))
    ratio = wide.crossJoin(F.broadcast(tot)).crossJoin(F.broadcast(v)).select("token", (F.log((F.col("c1") + 1) / (F.col("t1") + F.col("v"))) - F.log((F.col("c0") + 1) / (F.col("t0") + F.col("v")))).alias("r"))
    x = docs.select(key, F.explode_outer(C.tokens(F.col("text"))).alias("token")).groupBy(key, "token").agg(F.count("*").alias("k")).join(ratio, "token", "left")
    return x.groupBy(key).agg((1 / (1 + F.exp(-F.sum(F.col("k") * F.coalesce("r", F.lit(0.0))) / F.sum("k")))).alias("score"))


def strip_latex(text: Column) -> Column:
    """Without environments, delimited spans that hold a command, and loose commands: no common command is left."""
    out = F.regexp_replace(text, r"(?s)\\begin\{([a-z]+\*?)\}.*?\\end\{[a-z]+\*?\}", " ")
    out = F.regexp_replace(out, r"\$\$?[^$]*\\[A-Za-z][^$]*\$\$?", " ")
    return F.regexp_replace(out, r"\\[A-Za-z]+", " ")


def math_labels(docs: DataFrame) -> DataFrame:
    """doc_id, label (has a common command), text without LaTeX."""
    return docs.select("doc_id", C.has_common_command(F.col("text")).cast("int").alias("label"), strip_latex(F.col("text")).alias("text"))


def train_linear(labelled: DataFrame, features: int = 1 << 18, iterations: int = 30, reg: float = 1e-4):
    """Hashed words and word pairs into a logistic regression; gradients are summed by treeAggregate.

    Words and pairs share one hashed vector (a pair holds a space, a word none) with `features` places for each kind: an
    assembled vector would name each of its features in the schema, which every task of every iteration would then carry.
    """
    stages = [
        RegexTokenizer(inputCol="text", outputCol="words", pattern=r"[^\p{L}\p{N}]+", toLowercase=True), NGram(n=2, inputCol="words", outputCol="pairs"),
        SQLTransformer(statement="SELECT *, concat(words, pairs) AS grams FROM __THIS__"), HashingTF(inputCol="grams", outputCol="f", numFeatures=2 * features, binary=True),
        Normalizer(inputCol="f", outputCol="x", p=2.0), LogisticRegression(featuresCol="x", labelCol="label", maxIter=iterations, regParam=reg),
    ]
    return Pipeline(stages=stages).fit(labelled.where("text IS NOT NULL"))


def linear_score(docs: DataFrame, model, out: str = "score") -> DataFrame:
    kept = docs.columns
    return model.transform(docs.withColumn("text", F.coalesce("text", F.lit("")))).withColumn(out, vector_to_array("probability")[1]).select(*kept, out)


def train_language(docs: DataFrame, label: str = "lang", features: int = 1 << 16, iterations: int = 30, reg: float = 1e-4):
    """Hashed triples of neighbouring characters into a multinomial regression on the known languages of docs (text, label).
    Rows without a text or a language teach nothing; labels rank by frequency, then name."""
    stages = [
        StringIndexer(inputCol=label, outputCol="y", stringOrderType="frequencyDesc"), RegexTokenizer(inputCol="text", outputCol="chars", pattern=".", gaps=False, toLowercase=True), NGram(n=3, inputCol="chars", outputCol="triples"),
        HashingTF(inputCol="triples", outputCol="counts", numFeatures=features), IDF(inputCol="counts", outputCol="weighted"), Normalizer(inputCol="weighted", outputCol="x", p=2.0),
        LogisticRegression(featuresCol="x", labelCol="y", maxIter=iterations, regParam=reg, family="multinomial"),
    ]
    model = Pipeline(stages=stages).fit(docs.select("text", label).where(F.col("text").isNotNull() & F.col(label).isNotNull()))
    return model.stages[0].labels, PipelineModel(stages=model.stages[1:])


def predict_language(docs: DataFrame, model, out: str = "lang") -> DataFrame:
    """docs with the predicted language and its probability (lang_score); und with 0 for a text without a letter."""
    names, fitted = model
    kept = [c for c in docs.columns if c not in (out, "lang_score")]
    letters = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))
    p = vector_to_array("probability")
    x = fitted.transform(docs.select(*kept).withColumn("_text", F.col("text")).withColumn("text", F.coalesce("text", F.lit(""))))
    x = x.withColumn("text", F.col("_text"))
    lang = F.element_at(F.array(*map(F.lit, names)), F.col("prediction").cast("int") + 1)
    return x.select(*kept, F.when(letters, lang).otherwise("und").alias(out), F.when(letters, F.array_max(p)).otherwise(0.0).alias("lang_score"))


def report(scored: DataFrame, cuts: tuple[float, ...], score: str = "score", label: str = "label") -> DataFrame:
    """cut, accuracy, precision and recall of class 1 at score > cut, in one aggregation; a measure over no rows is null."""
    hit, true = [F.col(score) > c for c in cuts], F.col(label) == 1
    got = scored.agg(F.count("*").alias("n"), F.count_if(true).alias("pos"), *(x for i, h in enumerate(hit) for x in (F.count_if(h).alias(f"h{i}"), F.count_if(h & true).alias(f"t{i}"))))
    row = lambda i, c: F.struct(
        F.lit(c).alias("cut"), F.try_divide(F.col("n") - F.col("pos") - F.col(f"h{i}") + 2 * F.col(f"t{i}"), F.col("n")).alias("accuracy"),
        F.try_divide(F.col(f"t{i}"), F.col(f"h{i}")).alias("precision"), F.try_divide(F.col(f"t{i}"), F.col("pos")).alias("recall"),
    )
    return got.select(F.inline(F.array(*(row(i, c) for i, c in enumerate(cuts)))))


def auc(scored: DataFrame, score: str, label: str, bins: int | None = None) -> DataFrame:
    """Area under the curve by mean ranks of ties; with bins, from a histogram (for very many rows)."""
    s = F.floor(F.col(score) * bins) if bins else F.col(score)
    per = scored.groupBy(s.alias("s")).agg(F.sum(label).cast("long").alias("pos"), F.count("*").alias("n"))
    from pyspark.sql import Window as W

    before = F.coalesce(F.sum(F.col("n") - F.col("pos")).over(W.orderBy("s").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    x = per.select("pos", (F.col("n") - F.col("pos")).alias("neg"), before.alias("below"))
    return x.agg((F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2.0)) / (F.sum("pos") * F.sum("neg"))).alias("auc"))


FILTERS = ("language", "math", "perplexity")


def verdicts(df: DataFrame, order=FILTERS, lang: str = "en", with_tex: float = L.CUT_WITH_TEX, without_tex: float = L.CUT_WITHOUT_TEX, max_ppl: float = L.MAX_PERPLEXITY) -> DataFrame:
    """df (lang, math_score, has_latex, ppl) with verdict: the first filter that rejects a row, or keep. Strict cuts; a null
    score or perplexity is rejected by its filter; an empty text is 'empty'."""
    cut = F.when(F.col("has_latex"), with_tex).otherwise(without_tex)
    passes = {"language": F.col("lang") == lang, "math": F.col("math_score") > cut, "perplexity": F.col("ppl") <= max_ppl}
    out = F.lit("keep")
    for name in reversed(order):
        out = F.when(F.coalesce(passes[name], F.lit(False)), out).otherwise(name)
    return df.withColumn("verdict", out)
