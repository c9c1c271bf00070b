"""Views over the given tables with known mathematics, as DataFrames and as SQL with the same bytes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .lexicon import sql_quote

VARIANTS = 18
_RENDERER = '<script src="https://cdn.example.net/MathJax.js"></script>'
SNIPPETS = {
    0: _RENDERER + r"<p>We have $\frac{a}{b}$ and $x_1+y$ here.</p>",
    1: _RENDERER + r"<p>So $$\int_0^1 x dx = \frac{1}{2}$$ follows.</p>",
    2: "<script>MathJax.Hub.Config({tex2jax: {inlineMath: [['@@','@@']]}});</script>" + r"<p>Put @@\alpha+1@@ and \(\beta\) and \[\gamma=2\] down.</p>",
    3: r'<p><img src="https://latex.codecogs.com/gif.latex?%5Cfrac%7B1%7D%7B3%7D"/> and <img class="latex" alt="\sqrt{2}" src="/img/eq2.png"/></p>',
    4: r'<p><span class="math-container">\sum_{i=1}^n i</span></p>',
    5: "<p><math><mfrac><mi>a</mi><mi>b</mi></mfrac><mo>+</mo><msup><mi>x</mi><mn>2</mn></msup><mo>-</mo><msub><mi>y</mi><mn>1</mn></msub><mo>+</mo><msqrt><mn>3</mn></msqrt></math></p>",
    6: r'<p><math><semantics><mrow><mi>x</mi></mrow><annotation encoding="application/x-tex">\lim_{x\to 0} x</annotation></semantics></math></p>',
    7: r"<p><mathjax>\theta + \pi</mathjax></p>",
    8: r"<p>\begin{align} a &= \frac{b}{c} \end{align}</p>",
    9: r"<p>\begin{equation} e = \lambda c^2 \end{equation}</p>",
    10: r'<p><script type="math/tex; mode=display">\omega = 2\pi f</script> and <script type="math/asciimath">sum_(i=1)^n i</script></p>',
    11: r'<p><math alttext="\rho_0"><mi>r</mi></math> and <span class="tex">\sigma^2</span></p>',
    12: r'<p><img src="/wp/latex.php?latex=%5Cphi+%3D+1"/> and $latex \mu = 3$</p>',
    13: r"<p>Then $\frac{x}{y}$ and $\nu$ hold.</p>",
    14: "<p>It costs $5 to $10 or $20 now.</p>",
    15: "",
    16: "<p>Let the theorem prove that every polynomial equation has a root in the field; the proof uses an integral and a matrix.</p>",
    17: r'<div style="display:none">$\eta$ hidden</div><button>$\psi$</button><div><a href="#">$\zeta$</a> <a href="#">two</a> <a href="#">three</a> <a href="#">four</a></div>',
}
#: (variant, order, encoding, display, latex): what an extractor should find. Variant 17's equations are in removed elements.
TRUTH = (
    (0, 0, "inline", False, r"\frac{a}{b}"), (0, 1, "inline", False, "x_1+y"), (1, 0, "display", True, r"\int_0^1 x dx = \frac{1}{2}"),
    (2, 0, "configured", False, r"\alpha+1"), (2, 1, "inline", False, r"\beta"), (2, 2, "display", True, r"\gamma=2"),
    (3, 0, "image", False, r"\frac{1}{3}"), (3, 1, "image", False, r"\sqrt{2}"), (4, 0, "container", False, r"\sum_{i=1}^n i"),
    (5, 0, "mathml", False, r"\frac{a}{b}+{x}^{2}-{y}_{1}+\sqrt{3}"), (6, 0, "annotation", False, r"\lim_{x\to 0} x"), (7, 0, "tag", False, r"\theta + \pi"),
    (8, 0, "align", True, r"\begin{align} a &= \frac{b}{c} \end{align}"), (9, 0, "equation", True, r"\begin{equation} e = \lambda c^2 \end{equation}"),
    (10, 0, "script", True, r"\omega = 2\pi f"), (10, 1, "script", False, "sum_(i=1)^n i"), (11, 0, "alttext", False, r"\rho_0"), (11, 1, "alttext", False, r"\sigma^2"),
    (12, 0, "plugin", False, r"\phi = 1"), (12, 1, "plugin", False, r"\mu = 3"), (13, 0, "inline", False, r"\frac{x}{y}"), (13, 1, "inline", False, r"\nu"),
)
#: What the cascade should decide for each variant.
EXPECTED_STAGE = {**{v: "kw" for v in (0, 1, 2, 3, 4, 5, 6, 7, 11, 12)}, **{v: "cmd" for v in (8, 9, 10, 13, 17)}, 16: "score", 14: "drop", 15: "drop"}


def _values(rows, names: str) -> str:
    return f"(VALUES {', '.join(rows)}) AS t({names})"


SNIPPET_SQL = _values([f"({v}, {sql_quote(s)})" for v, s in SNIPPETS.items()], "variant, snippet")
STAGE_SQL = _values([f"({v}, {sql_quote(s)})" for v, s in sorted(EXPECTED_STAGE.items())], "variant, expected")
#: SQL of the view math_pages: page_id, url, html, variant.
MATH_PAGES_SQL = f"""math_pages AS (
  SELECT p.page_id, p.url, replace(p.html, '<article>', '<article>' || s.snippet) AS html, s.variant
  FROM pages p JOIN (SELECT * FROM {SNIPPET_SQL}) s ON s.variant = p.page_id % {VARIANTS})"""


def literal_rows(spark: SparkSession, rows: list[tuple], names: list[str], types: list[str]) -> DataFrame:
    """A small constant relation, inlined in the plan."""
    return spark.range(1).select(F.inline(F.array(*(F.struct(*(F.lit(v).cast(t).alias(n) for v, n, t in zip(r, names, types))) for r in rows))))


def math_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """pages with the snippet of variant page_id % 18 after the opening article tag."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    snippets = literal_rows(spark, list(SNIPPETS.items()), ["variant", "snippet"], ["int", "string"])
    joined = pages.withColumn("variant", (F.col("page_id") % VARIANTS).cast("int")).join(F.broadcast(snippets), "variant")
    return joined.select("page_id", "url", F.replace("html", F.lit("<article>"), F.concat(F.lit("<article>"), "snippet")).alias("html"), "variant")


def truth(spark: SparkSession) -> DataFrame:
    return literal_rows(spark, list(TRUTH), ["variant", "ord", "encoding", "display", "latex"], ["int", "int", "string", "boolean", "string"])


_MATH_LINES = ("The proof of the theorem uses an integral.", "Let the polynomial equation have a root.", "The matrix of the vector field is given.", "By the lemma the function is continuous.", "The derivative of the function is zero.", "A probability is a measure on the algebra.", "We prove the equation by induction.", "The sum of the series is the integral.")
_EQUATION = r" Hence $\frac{a}{b} = \alpha$."
_PRICES = " The bread was sold for $5 and the milk for $3 at the market."


def math_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents where every fourth English one gets mathematical prose and an equation, and another fourth gets prices."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    line = F.element_at(F.array(*map(F.lit, _MATH_LINES)), F.expr("CAST((doc_id DIV 4) % 8 AS INT) + 1"))
    with_math = (F.col("doc_id") % 4 == 0) & (F.col("lang") == "en")
    more = F.when(with_math, F.concat(F.lit("\n"), line, F.lit(_EQUATION))).when(F.col("doc_id") % 4 == 1, F.lit(_PRICES)).otherwise("")
    return docs.select("doc_id", F.concat("text", more).alias("text"), with_math.cast("int").alias("has_math"), "lang", "source")


MATH_DOCS_SQL = f"""math_docs AS (
  SELECT doc_id, text || CASE WHEN doc_id % 4 = 0 AND lang = 'en' THEN chr(10) || ([{', '.join(map(sql_quote, _MATH_LINES))}])[1 + (doc_id // 4) % 8] || {sql_quote(_EQUATION)}
                              WHEN doc_id % 4 = 1 THEN {sql_quote(_PRICES)} ELSE '' END AS text,
         CAST(doc_id % 4 = 0 AND lang = 'en' AS INT) AS has_math, lang, source FROM documents)"""


def md5_number(text: Column) -> Column:
    """The first 60 bits of the md5 of a text."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def md5_number_sql(expr: str) -> str:
    return f"CAST('0x' || substr(md5({expr}), 1, 15) AS BIGINT)"
