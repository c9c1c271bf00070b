"""Stage 5: domains of URLs, their totals, concentration, blacklists and review samples."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import columns as C

#: A blacklist with more hosts isn't broadcast.
BROADCAST_HOSTS = 1_000_000


def totals(pages: DataFrame, text_col: str, url_col: str = "url", labels: int = 2) -> DataFrame:
    """domain, n_docs, n_chars; partial sums make a giant domain one row per task before the shuffle."""
    return pages.select(C.domain(F.col(url_col), labels).alias("domain"), F.length(text_col).alias("c")).groupBy("domain").agg(F.count("*").alias("n_docs"), F.sum("c").cast("long").alias("n_chars"))


def top(per_domain: DataFrame, measure: str, k: int) -> DataFrame:
    """The k largest domains with their share in per cent of all."""
    whole = per_domain.agg(F.sum(measure).alias("whole"))
    return per_domain.crossJoin(F.broadcast(whole)).select("domain", "n_docs", "n_chars", F.round(100.0 * F.col(measure) / F.col("whole"), 4).alias("share")).orderBy(F.desc(measure), "domain").limit(k)


def concentration(per_domain: DataFrame, k: int) -> DataFrame:
    """Number of domains, and the share of all characters that the k largest hold."""
    whole = per_domain.agg(F.count("*").alias("n_domains"), F.sum("n_chars").alias("whole"))
    head = per_domain.orderBy(F.desc("n_chars"), "domain").limit(k).agg(F.sum("n_chars").alias("head"))
    return whole.crossJoin(head).select("n_domains", F.round(100.0 * F.col("head") / F.col("whole"), 4).alias("top_share"))


def drop_blacklisted(pages: DataFrame, hosts: DataFrame, host_col: str = "host") -> DataFrame:
    """Anti-join; Spark broadcasts the list while it is small by its own statistics, and shuffles beyond."""
    return pages.join(hosts, host_col, "left_anti")


def review_sample(pages: DataFrame, per: int, seed: int, key: str = "page_id", url_col: str = "url", labels: int = 2) -> DataFrame:
    """A reproducible sample of `per` pages of each domain. Only keys are ranked, never texts."""
    keys = pages.select(key, C.domain(F.col(url_col), labels).alias("domain"), C.hash_order(F.col(key), seed).alias("h"))
    ranked = keys.withColumn("k", F.row_number().over(W.partitionBy("domain").orderBy("h", key)))
    return ranked.where(F.col("k") <= per).drop("h")
