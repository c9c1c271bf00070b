"""SQL names, sinks, and streaming with history."""

from pyspark.sql import functions as F

from formulary.fixtures import math_pages
from formulary.functions import columns as C, sql
from formulary.operators import dedup
from formulary.sources import sinks
from formulary.streaming import incremental

SF = "/root/testdata/sf0.001"


def test_sql_names(spark):
    sql.register(spark)
    pages = math_pages(spark, SF)
    pages.createOrReplaceTempView("p")
    assert spark.sql("SELECT count(*) AS n FROM p WHERE has_math_keyword(html)").first().n == pages.where(C.has_keyword(F.col("html"))).count()
    assert spark.sql("SELECT passes_math(0.17, true) AS a, passes_math(0.171, true) AS b, simhash_similarity(5, 5) AS c, url_host('http://A.org/x') AS d").first()[:] == (False, True, 1.0, "a.org")
    got = spark.sql("SELECT variant, count(*) AS n FROM p, LATERAL equations(html) GROUP BY variant").collect()
    assert {r.variant: r.n for r in got}[0] % 2 == 0
    assert spark.sql("SELECT count(*) AS n FROM p, LATERAL dom_nodes(html) WHERE tag = 'article'").first().n == pages.count()


def test_sinks_give_back_what_they_took(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    sinks.partitioned(docs, str(tmp_path / "p"), "lang")
    back = spark.read.parquet(str(tmp_path / "p")).select(*docs.columns)
    assert back.exceptAll(docs).count() == 0 and docs.exceptAll(back).count() == 0
    sinks.jsonl(docs.withColumn("url", F.lit("u")), str(tmp_path / "j"))
    got = spark.read.json(str(tmp_path / "j"))
    assert sorted(got.columns) == ["metadata", "text", "url"] and got.count() == docs.count()


def test_near_duplicates_against_history(spark, tmp_path):
    put = incremental.near_duplicate_sink(str(tmp_path / "h"))
    text = lambda i: " ".join(f"w{i}x{j}" for j in range(60))
    rows = lambda *ids: spark.createDataFrame([(k, t) for k, t in ids], "page_id long, text string")
    put(rows((1, text(1)), (2, text(2)), (3, text(1))), 0)
    put(rows((4, text(2) + " more"), (5, text(3))), 1)
    put(rows((4, text(2) + " more"), (5, text(3))), 1)
    assert sorted(r.page_id for r in spark.read.parquet(str(tmp_path / "h")).collect()) == [1, 2, 5]


def test_stream_drops_copies_and_late_rows(spark, tmp_path):
    base = math_pages(spark, SF).select("page_id", "url", "html")
    at = lambda minutes: (F.lit(1_700_000_000) + minutes * 60).cast("timestamp")
    base.withColumn("crawled", at(F.col("page_id"))).unionByName(base.withColumn("crawled", at(F.col("page_id") + 1))).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = incremental.without_copies(incremental.read_pages(spark, str(tmp_path / "in"))).select("page_id")
    q = stream.writeStream.format("memory").queryName("once").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("once").count() == base.select(F.md5("html")).distinct().count()


def test_longest_survives(spark):
    docs = spark.createDataFrame([(1, 5), (2, 9), (3, 1)], "doc_id long, n_chars long")
    clusters = spark.createDataFrame([(1, 1), (2, 1)], "node long, root long")
    assert sorted(r.doc_id for r in dedup.survivors(docs, clusters, "longest").collect()) == [2, 3]
    assert sorted(r.doc_id for r in dedup.survivors(docs, clusters).collect()) == [1, 3]
