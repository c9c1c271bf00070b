"""The training-data pipeline over `documents`: five stages, each one of the operators of formulary.llm."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from formulary.llm import byte_gru, mixing, ngram_join, packing, suffix_dedup
from formulary.llm.common import discard, materialise, table

#: A document whose language is less probable than this is rejected; so is one without a letter.
LANGUAGE_LEAST = 0.4
#: Near copies: shingles of five words, similarity of 80 per cent or more.
WORDS, PERCENT = 5, 80
#: A passage of some fifty words.
REPEAT_BYTES = 240
VOCABULARY = "byte_bpe_50k.json"


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep documents whose language is found; a null lang is filled with it.

    Null, empty and letterless texts go (`und`); rows without an id and repeated rows are judged as any other. Where no
    document has a lang there is nothing to learn from, and every document goes; an empty table stays empty.
    """
    found = byte_gru.with_language(docs, byte_gru.train(docs))
    kept = found.where((F.col("_lang") != byte_gru.UNKNOWN) & (F.col("_lang_score") >= LANGUAGE_LEAST))
    return kept.withColumn("lang", F.coalesce("lang", "_lang")).drop("_lang", "_lang_score")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep of each group of near copies the document with the least id (rows without an id come last, ties by a hash of
    the row). Texts without words are in no group and stay; an empty table stays empty."""
    return ngram_join.first_of_groups(docs, words=WORDS, percent=PERCENT)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cut passages that also start elsewhere out of the texts; documents of which nothing is left go.

    Null and empty texts stay as they are; texts that occur in several rows, long enough, are wholly repeats. n_chars
    follows the text where it was cut. An empty table stays empty.
    """
    cut = suffix_dedup.remove_repeats(docs, "text", REPEAT_BYTES, whole_characters=True)
    cut = cut.where((F.octet_length("_kept") > 0) | (F.col("_n_bytes") == 0))
    cut = cut.withColumn("text", F.when(F.size("_removed") > 0, F.decode("_kept", "UTF-8")).otherwise(F.col("text")))
    return cut.withColumn("n_chars", F.when(F.size("_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).drop("_kept", "_removed", "_n_bytes")


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sample the domains to their target shares of the tokens, with the clean domain's tokens as they are.

    Null and empty texts have no tokens and the posteriors of an empty text; equal ids draw alike, rows without an id
    share one draw. Without labels all domains are alike likely. An empty table stays empty.
    """
    return mixing.resample(docs, table(spark, sf_dir, "labels"), mixing.TARGETS, keep="clean")


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into sequences: one row per piece. A null or empty text is a piece of one token; rows without an
    id and repeated rows are packed each; an empty table gives none."""
    return packing.pack_documents(docs, public_tokenizers.path(VOCABULARY))


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("repeated_passages", repeated_passages), ("mixture", mixture), ("packing", packed)]

#: No SQL: a trained network, trained posteriors and online packing; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per packed piece of what the stages keep; each stage's table is written and read by the next."""
    docs, before = table(spark, sf_dir, "documents"), []
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
        discard(*before)
        before = [docs]
    return STAGES[-1][1](spark, docs, sf_dir)
