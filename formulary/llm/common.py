"""What several operators share: scratch tables, UTF-8 views of Arrow columns, hashing, connected components."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """The cluster's shared folder (spark.checkpoint.dir); a temporary one only where that is unset and all tasks run here."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if shared:
        return shared.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "dir" not in _LOCAL:
        _LOCAL["dir"] = tempfile.mkdtemp(prefix="formulary-")
    return "file://" + _LOCAL["dir"]


#: On a mounted disk Hadoop starts a `chmod` process for each folder and file, and one more for the checksum file beside it;
#: for a moment each shares, and doubles in any count, the memory of the executor that starts it. The raw file system writes
#: no checksum files. Other kinds of shared folders take no notice.
WRITE_OPTIONS = {"fs.file.impl": "org.apache.hadoop.fs.RawLocalFileSystem", "fs.file.impl.disable.cache": "true"}


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write df as a table in the shared folder and read it again: cuts lineage, survives lost executors and forgets partitioning."""
    path = f"{scratch_dir(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    df.write.options(**WRITE_OPTIONS).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Delete the files behind tables made by materialise() that no later step reads."""
    if not tables:
        return
    spark = tables[0].sparkSession
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rsplit("/", 1)[0] for df in tables for f in df.inputFiles()}:
        where = jvm.org.apache.hadoop.fs.Path(folder)
        where.getFileSystem(conf).delete(where, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hash_sample(df: DataFrame, key: str, n: int, total: int) -> DataFrame:
    """About the n rows of df with the least hash of their key (ties: by all columns), where df has at most `total` rows.

    Rows above a hash threshold go before the sort, so that what the tasks send together is bounded by n, not by
    n for each task. If much fewer than `total` rows are in df, fewer than n may come.
    """
    h = F.pmod(F.xxhash64(F.col(key).cast("string"), F.lit(5)), F.lit(1 << 30))
    share = min(1.0, (1.5 * n + 100) / max(total, 1))
    return df.withColumn("_h", h).where(F.col("_h") < int(share * (1 << 30)) + 1).orderBy("_h", *df.columns).limit(n).drop("_h")


#: 64-bit words of the filter (2 MB, whatever the input) that spares most texts without a partner a shuffle.
FILTER_WORDS = 1 << 18


def membership_bits(nodes: DataFrame, words: int = FILTER_WORDS) -> np.ndarray:
    """A bit set of fixed size with the bit of every node set: a filter that lets all nodes through, and some others."""
    got = nodes.select((F.shiftright("node", 6) % words).alias("w"), F.expr("shiftleft(1L, int(node % 64))").alias("b")).groupBy("w").agg(F.bit_or("b").alias("b")).toArrow()
    out = np.zeros(words, np.uint64)
    out[got.column("w").to_numpy()] = got.column("b").to_numpy().view(np.uint64)
    return out


def utf8_view(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary column end to end, and the offsets of its rows; nulls are empty."""
    if column.null_count:
        column = pc.fill_null(column, pa.scalar(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "", column.type))
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, at, raw = column.buffers()
    if len(column) == 0:
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(at, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.empty(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def byte_slabs(offsets: np.ndarray, limit: int) -> Iterator[tuple[int, int]]:
    """Ranges of rows that hold about limit bytes each; a longer row is alone."""
    first, n = 0, len(offsets) - 1
    while first < n:
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + limit, "right")) - 1)
        yield first, last
        first = last


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words whose output bits all depend on all input bits."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


_BASE = 0x9E3779B97F4A7C15 | 1


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """0th to (n-1)th power modulo 2**64 of a fixed odd number, or of its inverse."""
    out = np.full(max(n, 1), pow(_BASE, -1, 1 << 64) if inverse else _BASE, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)[:n]


def _is_star_forest(e: DataFrame) -> bool:
    """Whether every node has one edge to a lower one and no lower end has an edge of its own: nothing is left to do."""
    if e.groupBy("u").agg(F.count("*").alias("c")).where("c > 1").limit(1).count():
        return False
    return e.join(e.select(F.col("v").alias("u")).distinct(), "u", "left_semi").limit(1).count() == 0


def edges_to_components(edges: DataFrame, tag: str, max_rounds: int = 60) -> DataFrame:
    """Connected components of edges (a, b): rows (node, component), component the smallest node reached.

    Alternating large-star and small-star steps, O(log n) rounds of two equi-joins each; every round is written
    to the shared folder, and stops when the edges are stars. Nothing is collected but whether a row is left. Nodes without an edge to another
    node don't appear; null ends are ignored.
    """
    e = edges.where("a IS NOT NULL AND b IS NOT NULL AND a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = materialise(e, f"{tag}-edges")
    for _ in range(max_rounds):
        if _is_star_forest(e):
            return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")), f"{tag}-low")
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large = materialise(large, f"{tag}-large")
        small_low = materialise(large.groupBy("u").agg(F.min("v").alias("m")), f"{tag}-slow")
        small = large.join(small_low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small_low.select("u", F.col("m").alias("v")))
        nxt = materialise(small.where("u <> v").distinct(), f"{tag}-edges")
        discard(e, low, large, small_low)
        e = nxt
    raise RuntimeError(f"components did not converge in {max_rounds} rounds")
