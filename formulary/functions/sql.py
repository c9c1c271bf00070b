"""Names for SQL users: one-line functions that the optimiser inlines, and table functions over pages and texts."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .. import lexicon as L


@udtf(returnType="ord: int, latex: string, encoding: string, display: boolean")
class Equations:
    """equations(html): the equations of a page that extraction keeps."""

    def eval(self, html: str):
        from ..operators.extract import extract

        for i, e in enumerate(extract(html).equations):
            yield i, e.latex, e.encoding, e.display


@udtf(returnType="node_id: int, parent: int, tag: string, cls: array<string>, id: string, text: string")
class DomNodes:
    """dom_nodes(html): the elements of a page in document order."""

    def eval(self, html: str):
        from ..operators.extract import parse

        if html is None:
            return
        root, number = parse(html), {}
        for n in root.walk():
            number[id(n)] = len(number)
            yield number[id(n)], number.get(id(n.parent)), n.tag, n.classes(), n.attrs.get("id"), "".join(c for c in n.children if isinstance(c, str)).strip()


def register(spark: SparkSession) -> None:
    """has_math_keyword, url_host, simhash_similarity, passes_math (temporary SQL functions); equations, dom_nodes (table functions)."""
    any_of = " OR ".join(f"contains(html, {L.sql_quote(k)})" for k in L.MATH_KEYWORDS)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION has_math_keyword(html STRING) RETURNS BOOLEAN RETURN {any_of}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION url_host(url STRING) RETURNS STRING RETURN lower(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION simhash_similarity(a BIGINT, b BIGINT) RETURNS DOUBLE RETURN 1 - bit_count(a ^ b) / 64D")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION passes_math(score DOUBLE, has_latex BOOLEAN) RETURNS BOOLEAN RETURN score > CASE WHEN has_latex THEN {L.CUT_WITH_TEX}D ELSE {L.CUT_WITHOUT_TEX}D END")
    spark.udtf.register("equations", Equations)
    spark.udtf.register("dom_nodes", DomNodes)
