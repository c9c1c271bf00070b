"""Corpus analysis: tokens, samples, clusters and their topics, datasheet facts; and evaluation: budgets, mixtures, votes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..fixtures import md5_number
from ..functions import columns as C


def token_count(text: Column, tokenizer: str = "words") -> Column:
    """words: runs without white space; parts: words and single marks; chars: an estimate of one token per 3.3 characters."""
    if tokenizer == "words":
        return F.size(F.filter(F.split(text, r"[ \t\n\r]+"), lambda x: x != ""))
    if tokenizer == "parts":
        return F.size(F.regexp_extract_all(text, F.lit(r"([\p{L}\p{N}]+|[^\p{L}\p{N}\s])"), 1))
    return F.ceil(F.length(text) / 3.3).cast("int")


def sample(df: DataFrame, n: int, seed: int, key: str) -> DataFrame:
    """n rows in the order of a hash of their key: exact, reproducible, independent of partitioning."""
    return df.orderBy(C.hash_order(F.col(key), seed), key).limit(n)


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def assign(vectors: DataFrame, centres: DataFrame, key: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """key, cluster, dist of the nearest centre (ties: the lower number). Centres are few by definition and broadcast."""
    v = vectors.select(key, F.transform(vec, lambda x: x.cast("double")).alias("v"))
    all_centres = centres.agg(F.array_sort(F.collect_list(F.struct("cluster", "centre"))).alias("cs"))
    best = F.array_min(F.transform("cs", lambda c: F.struct(F.round(squared_distance(F.col("v"), c["centre"]), 9).alias("d"), c["cluster"].alias("k"))))
    got = v.crossJoin(F.broadcast(all_centres)).select(key, "v", best.alias("b"))
    return got.select(key, "v", F.col("b.k").alias("cluster"), F.col("b.d").alias("dist"))


def first_centres(vectors: DataFrame, k: int, key: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """The k vectors with the lowest ids as centres 0 to k - 1."""
    low = vectors.orderBy(key).limit(k).select(key, F.transform(vec, lambda x: x.cast("double")).alias("centre"))
    return low.select((F.row_number().over(W.orderBy(key)) - 1).alias("cluster"), "centre")


def recentre(assigned: DataFrame) -> DataFrame:
    """One Lloyd step's centres."""
    long = assigned.select("cluster", F.posexplode("v").alias("i", "x")).groupBy("cluster", "i").agg(F.avg("x").alias("m"))
    return long.groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("centre"))


def nearest(assigned: DataFrame, m: int, key: str = "vec_id") -> DataFrame:
    """The m members nearest to each centre, ranked."""
    r = F.row_number().over(W.partitionBy("cluster").orderBy("dist", key))
    return assigned.withColumn("rank", r).where(F.col("rank") <= m)


def kmeans(vectors: DataFrame, k: int, seed: int = 1, iterations: int = 20, vec: str = "embedding") -> DataFrame:
    """vectors with cluster, by the library's k-means with parallel seeding: the form for many vectors and centres."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    x = vectors.withColumn("_x", array_to_vector(F.transform(vec, lambda v: v.cast("double"))))
    return KMeans(featuresCol="_x", predictionCol="cluster", k=k, seed=seed, maxIter=iterations).fit(x).transform(x).drop("_x")


def spread_centres(vectors: DataFrame, k: int, key: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """k centres, each the vector farthest from those before (the first: the lowest id; ties: the lower id). One scan a
    centre; the driver holds k vectors."""
    spark = vectors.sparkSession
    v = vectors.select(F.col(key).alias("id"), F.transform(vec, lambda x: x.cast("double")).alias("v"))
    chosen = [list(v.orderBy("id").first().v)]
    while len(chosen) < k:
        gap = F.least(*(squared_distance(F.col("v"), F.array(*map(F.lit, c))) for c in chosen), F.lit(float("inf")))
        chosen.append(list(v.select("id", "v", gap.alias("g")).orderBy(F.desc("g"), "id").first().v))
    return spark.createDataFrame(list(enumerate(chosen)), "cluster int, centre array<double>")


def lloyd(vectors: DataFrame, centres: DataFrame, steps: int = 5, key: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """key, cluster, dist after some Lloyd steps from given centres; between steps the k centres pass the driver."""
    spark = vectors.sparkSession
    for _ in range(steps):
        moved = recentre(assign(vectors, centres, key, vec)).collect()
        centres = spark.createDataFrame([(r.cluster, list(r.centre)) for r in moved], "cluster int, centre array<double>")
    return assign(vectors, centres, key, vec).drop("v")


def topic_shares(representatives: DataFrame, sizes: DataFrame) -> DataFrame:
    """topic, size, share: clusters take the commonest label of their representatives (ties: the lower), weighted by size."""
    votes = representatives.groupBy("cluster", "label").agg(F.count("*").alias("k"))
    topic = votes.groupBy("cluster").agg(F.max(F.struct("k", (-F.col("label")).alias("l"))).alias("b")).select("cluster", (-F.col("b.l")).alias("topic"))
    per = topic.join(sizes, "cluster").groupBy("topic").agg(F.sum("size").alias("size"))
    return per.crossJoin(F.broadcast(per.agg(F.sum("size").alias("whole")))).select("topic", "size", F.round(100.0 * F.col("size") / F.col("whole"), 4).alias("share"))


def embed(docs: DataFrame, key: str = "doc_id", text_col: str = "text", dims: int = 60) -> DataFrame:
    """key, embedding: hashed random projection, where each token votes 1 or -1 in every dimension by a bit of its digest
    (at most 60). Null and empty texts give zeros. A trained encoder takes its place where one is at hand."""
    if not 0 < dims <= 60:
        raise ValueError("dims must lie between 1 and 60")
    hashes = F.transform(F.coalesce(C.tokens(F.col(text_col)), F.array().cast("array<string>")), md5_number)
    ones = lambda h, i: F.aggregate(h, F.lit(0), lambda s, x: s + F.shiftright(x, i).bitwiseAND(F.lit(1)).cast("int"))
    vector = C.bind(hashes, lambda h: F.array(*((2 * ones(h, i) - F.size(h)).cast("double") for i in range(dims))))
    return docs.select(key, vector.alias("embedding"))


def budget(docs: DataFrame, tokens: int, seed: int, key: str = "doc_id", count: str = "n_tokens", buckets: int = 4096) -> DataFrame:
    """Documents in hash order while their running token sum stays within the budget.

    Two passes: sums of hash ranges (at most `buckets` rows), their running sum, then a running sum inside a range; no
    window ever holds the corpus.
    """
    h = docs.withColumn("_h", C.hash_order(F.col(key), seed)).withColumn("_b", F.shiftright("_h", 60 - buckets.bit_length() + 1))
    per = h.groupBy("_b").agg(F.sum(count).alias("_s"))
    before = per.select("_b", F.coalesce(F.sum("_s").over(W.orderBy("_b").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = F.sum(count).over(W.partitionBy("_b").orderBy("_h", key).rowsBetween(W.unboundedPreceding, 0))
    x = h.join(F.broadcast(before), "_b").withColumn("running", F.col("_before") + inside)
    return x.where(F.col("running") <= tokens).drop("_h", "_b", "_before")


def mixture(parts: list[tuple[DataFrame, float]], tokens: int, seed: int) -> DataFrame:
    """Budgets of several corpora by weight, with the part's number."""
    out = None
    for i, (df, weight) in enumerate(parts):
        x = budget(df, int(tokens * weight), seed).withColumn("part", F.lit(i))
        out = x if out is None else out.unionByName(x)
    return out


def majority(answers: DataFrame) -> DataFrame:
    """item_id, answer, votes: the commonest answer of each item (ties: the lower answer)."""
    per = answers.groupBy("item_id", "answer").agg(F.count("*").alias("votes"))
    r = F.row_number().over(W.partitionBy("item_id").orderBy(F.desc("votes"), "answer"))
    return per.withColumn("r", r).where("r = 1").drop("r")
