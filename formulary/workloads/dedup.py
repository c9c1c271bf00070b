"""Deduplication workloads on documents."""

from pyspark.sql import functions as F

from ..fixtures import md5_number_sql
from ..functions import columns as C
from ..operators import dedup
from ..registry import query

TOKENS_SQL = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '')"


def shingles_sql(n: int, table: str = "documents", key: str = "doc_id", name: str = "sh") -> str:
    return f"""{name}_t AS (SELECT {key}, {TOKENS_SQL} AS t FROM {table}),
{name} AS (SELECT {key}, unnest(CASE WHEN len(t) >= {n} THEN list_distinct(list_transform(range(1, len(t) - {n - 2}), lambda i: array_to_string(t[i:i + {n - 1}], ' '))) WHEN len(t) > 0 THEN [array_to_string(t, ' ')] ELSE [] END) AS s FROM {name}_t)"""


def docs(spark, d):
    return spark.read.parquet(f"{d}/documents.parquet")


def bench(spark, d):
    return spark.read.parquet(f"{d}/benchmark.parquet")


@query("exact_dups", "SELECT md5(text) AS digest, min(doc_id) AS first_id, count(*) AS copies FROM documents GROUP BY 1 HAVING count(*) > 1")
def exact(spark, d):
    return dedup.exact(docs(spark, d))


@query("shingles", f"WITH {shingles_sql(3)} SELECT doc_id, count(*) AS n_shingles, min(s) AS first_shingle FROM sh GROUP BY doc_id")
def shingles(spark, d):
    long = dedup.shingled(docs(spark, d)).select("doc_id", F.explode("sh").alias("s"))
    return long.groupBy("doc_id").agg(F.count("*").alias("n_shingles"), F.min("s").alias("first_shingle"))


_VOTES = ", ".join(f"sum((h >> {b}) & 1) AS b{b}" for b in range(60))
_BITS = " + ".join(f"CASE WHEN 2 * b{b} > n THEN CAST({1 << b} AS BIGINT) ELSE 0 END" for b in range(60))
_FP_SQL = f"{shingles_sql(3)}, v AS (SELECT doc_id, count(*) AS n, {_VOTES} FROM (SELECT doc_id, {md5_number_sql('s')} AS h FROM sh) GROUP BY doc_id), fp AS (SELECT doc_id, CAST({_BITS} AS BIGINT) AS fp FROM v)"


@query("simhash_fp", f"WITH {_FP_SQL} SELECT doc_id, fp FROM fp")
def simhash_fp(spark, d):
    return dedup.fingerprint60(docs(spark, d))


_PAIRS_SQL = f"{_FP_SQL}, pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, CAST(bit_count(xor(a.fp, b.fp)) AS INT) AS dist FROM fp a JOIN fp b ON a.doc_id < b.doc_id WHERE bit_count(xor(a.fp, b.fp)) <= 3)"


@query("simhash_pairs_blocked", f"WITH {_PAIRS_SQL} SELECT a, b, dist FROM pairs")
def simhash_blocked(spark, d):
    """All pairs within three bits, by pigeonhole blocks; the SQL compares every pair."""
    return dedup.pairs_blocked(dedup.fingerprint60(docs(spark, d)), 3)


_COMP_SQL = f"""WITH RECURSIVE {_PAIRS_SQL}, e AS (SELECT a, b FROM pairs UNION SELECT b, a FROM pairs),
r AS (SELECT a AS node, a AS root FROM e UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.node AND r.root < e.b)"""


@query("dup_components", f"{_COMP_SQL} SELECT node, min(root) AS root FROM r GROUP BY node")
def dup_components(spark, d):
    return dedup.components(dedup.pairs_blocked(dedup.fingerprint60(docs(spark, d)), 3))


@query("dedup_survivors", f"{_COMP_SQL}, c AS (SELECT node, min(root) AS root FROM r GROUP BY node) SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT node FROM c WHERE node <> root)")
def dedup_survivors(spark, d):
    x = docs(spark, d)
    return dedup.survivors(x.select("doc_id", "n_chars"), dedup.components(dedup.pairs_blocked(dedup.fingerprint60(x), 3)))


@query("dedup_any_previous", f"WITH {_PAIRS_SQL} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT b FROM pairs)")
def dedup_any_previous(spark, d):
    x = docs(spark, d)
    return dedup.any_previous(x.select("doc_id"), dedup.pairs_blocked(dedup.fingerprint60(x), 3))


@query("simhash_pairs")
def simhash_pairs(spark, d):
    """All pairs with similarity of 0.7 or more on 256 bits."""
    return dedup.pairs_exact(dedup.fingerprint(docs(spark, d)))


@query("simhash_pairs_60", f"WITH {_FP_SQL} SELECT a.doc_id AS a, b.doc_id AS b, CAST(bit_count(xor(a.fp, b.fp)) AS INT) AS dist FROM fp a JOIN fp b ON a.doc_id < b.doc_id WHERE bit_count(xor(a.fp, b.fp)) <= 18")
def simhash_pairs_60(spark, d):
    """All pairs with similarity of 0.7 or more on the 60-bit fingerprints that SQL can make: the whole comparison checked by SQL."""
    fps = dedup.fingerprint60(docs(spark, d)).select("doc_id", F.array("fp").alias("fp"))
    return dedup.pairs_exact(fps, bits=dedup.BITS60).select("a", "b", "dist")


@query("simhash_pairs_by_tenth", f"""WITH {_FP_SQL} SELECT CAST(least(9, (60 - bit_count(xor(a.fp, b.fp))) // 6) AS INT) AS tenth, count(*) AS pairs FROM fp a JOIN fp b ON a.doc_id < b.doc_id WHERE bit_count(xor(a.fp, b.fp)) <= 18 GROUP BY 1""")
def pairs_by_tenth(spark, d):
    """Pairs by similarity (in tenths) of the exact comparison: the denominators of an approximate method's recall."""
    return simhash_pairs_60(spark, d).groupBy(F.least(F.lit(9), F.floor((60 - F.col("dist")) / 6)).cast("int").alias("tenth")).agg(F.count("*").alias("pairs"))


@query("dup_components_070")
def dup_components_070(spark, d):
    return dedup.components(dedup.links_exact(dedup.fingerprint(docs(spark, d))))


@query("dedup_survivors_070")
def dedup_survivors_070(spark, d):
    x = docs(spark, d)
    return dedup.survivors(x.select("doc_id", "n_chars"), dedup.components(dedup.links_exact(dedup.fingerprint(x))))


@query("dedup_any_previous_070")
def dedup_any_previous_070(spark, d):
    x = docs(spark, d)
    return dedup.any_previous(x.select("doc_id"), dedup.pairs_exact(dedup.fingerprint(x)))


@query("simhash_lsh")
def simhash_lsh(spark, d):
    return dedup.pairs_lsh(dedup.fingerprint(docs(spark, d)))


@query("dedup_sweep")
def dedup_sweep(spark, d):
    """All pairs and the documents they touch at each threshold and width, in one comparison."""
    return dedup.sweep_widths(dedup.fingerprint(docs(spark, d)), (0.6, 0.7, 0.8, 0.9), (64, 128, 256))


_JACCARD_SQL = f"""WITH {shingles_sql(3)}, n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM sh x JOIN sh y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2)
SELECT a, b, CAST(shared AS INT) AS shared, CAST(na.n + nb.n - shared AS INT) AS total FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * shared >= 70 * (na.n + nb.n - shared)"""


@query("jaccard_pairs", _JACCARD_SQL)
def jaccard(spark, d):
    return dedup.jaccard_pairs(docs(spark, d))


@query("minhash_pairs")
def minhash(spark, d):
    return dedup.minhash_pairs(docs(spark, d))


_HALF = "CAST(substr(source, 4) AS INT) < 5"


@query("corpus_overlap", f"""WITH l AS (SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line, md5(text) AS h FROM documents),
a AS (SELECT * FROM l WHERE {_HALF}), b AS (SELECT * FROM l WHERE NOT {_HALF})
SELECT 'document' AS unit, count(DISTINCT h) AS shared FROM a WHERE h IN (SELECT h FROM b) UNION ALL SELECT 'line', count(DISTINCT line) FROM a WHERE line IN (SELECT line FROM b)""")
def overlap(spark, d):
    """Distinct texts and lines that two parts of the corpus share."""
    half = F.substring("source", 4, 9).cast("int") < 5
    x, out = docs(spark, d), None
    for unit, col in (("document", F.md5(F.col("text").cast("binary"))), ("line", F.explode(F.split("text", "\n")))):
        y = x.select(half.alias("first"), col.alias("v"))
        both = y.where("first").select("v").distinct().join(y.where("NOT first").select("v").distinct(), "v", "left_semi").agg(F.lit(unit).alias("unit"), F.count("*").alias("shared"))
        out = both if out is None else out.unionByName(both)
    return out


@query("contamination", f"""WITH {shingles_sql(8)}, {shingles_sql(8, 'benchmark', 'item_id', 'bs')}
SELECT doc_id, count(DISTINCT sh.s) AS shared, count(DISTINCT item_id) AS items FROM sh JOIN bs ON sh.s = bs.s WHERE len(string_split(bs.s, ' ')) = 8 GROUP BY doc_id""")
def contamination(spark, d):
    """Documents that share 8-word shingles with benchmark items."""
    items = dedup.shingled(bench(spark, d), 8, "item_id").select("item_id", F.explode("sh").alias("s")).where(F.size(F.split("s", " ")) == 8)
    x = dedup.shingled(docs(spark, d), 8).select("doc_id", F.explode("sh").alias("s")).join(items, "s")
    return x.groupBy("doc_id").agg(F.countDistinct("s").alias("shared"), F.countDistinct("item_id").alias("items"))


@query("recrawl_pages", "SELECT regexp_extract(url, '/[a-z]{2}/([0-9]+)', 1) AS doc, count(*) AS crawls, min(page_id) AS first_page FROM pages GROUP BY 1 HAVING count(*) > 1")
def recrawls(spark, d):
    p = spark.read.parquet(f"{d}/pages.parquet")
    return p.groupBy(F.regexp_extract("url", "/[a-z]{2}/([0-9]+)", 1).alias("doc")).agg(F.count("*").alias("crawls"), F.min("page_id").alias("first_page")).where("crawls > 1")
