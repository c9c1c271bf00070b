"""Streams of newly crawled pages: the batch columns on unbounded input, bounded state, near duplicates against history."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import columns as C
from ..operators import dedup, prefilter

PAGES = "page_id long, url string, html string, crawled timestamp"


def read_pages(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(PAGES).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def gated(pages: DataFrame) -> DataFrame:
    """The prefilter's JVM gates, as in batch."""
    return pages.withColumn("pf_stage", F.coalesce(prefilter.gate_stage(F.col("html")), F.lit("drop")))


def without_copies(pages: DataFrame, within: str = "1 day") -> DataFrame:
    """First of equal pages within the watermark; state older than it is dropped."""
    return pages.withColumn("digest", F.md5(F.col("html").cast("binary"))).withWatermark("crawled", within).dropDuplicatesWithinWatermark(["digest"])


def counts(pages: DataFrame, window: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pages by window and gate; rows later than the watermark are dropped, and counted in the query's progress."""
    return gated(pages).withWatermark("crawled", late).groupBy(F.window("crawled", window), "pf_stage").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def without_blocked(pages: DataFrame, hosts: DataFrame) -> DataFrame:
    """Pages whose host is not in the list (host), which is read anew each trigger. Null urls stay."""
    return pages.join(hosts.select(F.col("host").alias("_host")).distinct(), C.host(F.col("url")) == F.col("_host"), "left_anti")


def followed_by(first: DataFrame, second: DataFrame, key: str, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Rows of first (key, ts) with those of second of the same key that come at most `within` after: key, ts, next_ts.
    Both sides have a watermark and the interval bounds how long a row is kept."""
    a = first.select(F.col(key), "ts").withWatermark("ts", late)
    b = second.select(F.col(key).alias("_key"), F.col("ts").alias("next_ts")).withWatermark("next_ts", late)
    on = (F.col(key) == F.col("_key")) & (F.col("next_ts") > F.col("ts")) & (F.col("next_ts") <= F.col("ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).drop("_key")


def late_rows(query) -> int:
    """Rows that a query's watermark dropped, over the progress it still remembers. A batch's rows are judged by the
    watermark of the batch before, so a late row right behind the one that moved it is still counted in its window."""
    return sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])


def near_pairs(fps: DataFrame, d: int = 3, key: str = "doc_id", ttl_ms: int = 86_400_000, late: str = "1 hour") -> DataFrame:
    """Stream of (key, fp, crawled) with 60-bit fingerprints -> a, b, dist: each arriving row with every earlier distinct
    fingerprint within d bits. State is kept for each of d + 1 blocks of bits; a pair is emitted at its first equal block.

    Of equal fingerprints the first id stands for all, so a group of copies takes one entry; a block's state is dropped
    once the watermark is ttl_ms past its last row (event time, so that a replay gives the same). Rows without an id or a fingerprint meet nothing.
    """
    width = -(-dedup.BITS60 // (d + 1))
    mask = (1 << width) - 1
    block: Column = F.explode(F.array(*(F.struct(F.lit(i).alias("i"), F.shiftright("fp", i * width).bitwiseAND(F.lit(mask)).alias("v")) for i in range(d + 1))))
    keyed = fps.where(F.col(key).isNotNull() & F.col("fp").isNotNull()).withWatermark("crawled", late).select("crawled", F.col(key).cast("long").alias("id"), F.col("fp").cast("long").alias("fp"), block.alias("k")).select("crawled", "id", "fp", "k.*")

    def run(group: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        i = int(group[0])
        ids, seen = map(list, state.get) if state.exists else ([], [])
        at = {f: n for n, f in enumerate(seen)}
        out: list[tuple[int, int, int]] = []
        last = state.getCurrentWatermarkMs()
        for frame in frames:
            if frame["crawled"].notna().any():
                last = max(last, int(frame["crawled"].max().timestamp() * 1000))
            for b, fp in zip(frame["id"].tolist(), frame["fp"].tolist()):
                if seen:
                    diff = np.array(seen, np.int64) ^ np.int64(fp)
                    dist = np.array([int(x).bit_count() for x in diff])
                    first = np.ones(len(seen), bool)
                    for j in range(i):
                        first &= (diff >> (j * width)) & mask != 0
                    out += [(ids[n], b, int(dist[n])) for n in np.flatnonzero((dist <= d) & first).tolist() if ids[n] != b]
                if fp not in at:
                    at[fp] = len(seen)
                    ids.append(b)
                    seen.append(fp)
        state.update((ids, seen))
        state.setTimeoutTimestamp(max(last, 0) + ttl_ms)
        yield pd.DataFrame(out, columns=["a", "b", "dist"])

    return keyed.groupBy("i", "v").applyInPandasWithState(run, "a long, b long, dist int", "ids array<long>, fps array<long>", "append", "EventTimeTimeout")


def near_duplicate_sink(history: str, key: str = "page_id", text_col: str = "text"):
    """A foreachBatch function: appends to `history` the fingerprints of rows that are near none of it nor of an earlier
    row of the batch. A batch that runs again replaces its own rows, since they are stored by batch number."""

    def put(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        fps = dedup.fingerprint(batch, key=key, text_col=text_col).withColumn("old", F.lit(False))
        try:
            past = spark.read.parquet(history).where(F.col("batch") != number).select(key, "fp").withColumn("old", F.lit(True))
        except Exception as e:  # noqa: BLE001
            if "PATH_NOT_FOUND" not in str(e) and "UNABLE_TO_INFER_SCHEMA" not in str(e):
                raise
            past = fps.where("false")
        near = dedup.pairs_lsh(past.select(key, "fp").unionByName(fps.select(key, "fp")), key=key)
        known = past.select(F.col(key).alias("k"))
        losers = near.select(F.col("b").alias(key)).unionByName(near.join(known, near["b"] == known["k"], "left_semi").select(F.col("a").alias(key))).distinct()
        fps.join(losers, key, "left_anti").drop("old").write.mode("overwrite").parquet(f"{history}/batch={number}")

    return put
