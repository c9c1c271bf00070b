"""Writers of the corpus: partitioned Parquet, JSON lines for release, bucketed fingerprints."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def partitioned(df: DataFrame, path: str, *by: str) -> None:
    """Parquet by directory; rows are rebalanced first, so that a large value has several files and a small one few."""
    df.hint("rebalance", *(F.col(c) for c in by)).write.mode("overwrite").partitionBy(*by).parquet(path)


def jsonl(df: DataFrame, path: str, text: str = "text", url: str = "url") -> None:
    """One JSON object a line: url, text, and every other column under metadata."""
    rest = [c for c in df.columns if c not in (text, url)]
    meta = F.to_json(F.struct(*rest)) if rest else F.lit("{}")
    df.select(F.col(url).alias("url"), F.col(text).alias("text"), meta.alias("metadata")).write.mode("overwrite").option("compression", "gzip").json(path)


def bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key: later joins on it need no shuffle of this side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)
