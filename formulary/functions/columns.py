"""Column functions: gates, LaTeX patterns, URLs and lines. All stay in the JVM."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from .. import lexicon as L


def has_keyword(html: Column, keywords=L.MATH_KEYWORDS) -> Column:
    return reduce(lambda a, b: a | b, (html.contains(k) for k in keywords))


def keyword_hits(html: Column, keywords=L.MATH_KEYWORDS) -> Column:
    return F.filter(F.array(*(F.when(html.contains(k), F.lit(k)) for k in keywords)), lambda x: x.isNotNull())


def has_backslash_command(html: Column) -> Column:
    return html.rlike(L.COMMAND_PATTERN)


def commands_in(text: Column) -> Column:
    """Names of all backslash commands in order, with the backslash."""
    return F.regexp_extract_all(text, F.lit(r"(\\[A-Za-z]+)"), 1)


def has_common_command(text: Column, commands=L.COMMANDS) -> Column:
    """A token match: \\in is not found in \\infty."""
    return F.arrays_overlap(commands_in(text), F.array(*(F.lit("\\" + c) for c in commands)))


def quick_text(html: Column) -> Column:
    """Text without tags, styles and scripts; bodies of math scripts stay."""
    kept = F.regexp_replace(html, r"(?s)<script type=\"math/[^\"]*\">(.*?)</script>", " $1 ")
    kept = F.regexp_replace(kept, r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(kept, "<[^>]*>", " "), r"\s+", " "))


def lexicon_score(text: Column, words=L.MATH_WORDS) -> Column:
    """Share of a small list's words that occur, saturating at five: a score without training."""
    present = reduce(lambda a, b: a + b, (F.lower(text).contains(w).cast("int") for w in words))
    return F.least(present / F.lit(5.0), F.lit(1.0))


def spans(html: Column, encoding: str) -> Column:
    pattern, group = L.ENCODINGS[encoding]
    return F.regexp_extract_all(html, F.lit(pattern), group)


def dollar_spans(html: Column) -> Column:
    """Single-dollar spans after double-dollar ones are taken out."""
    return F.regexp_extract_all(F.regexp_replace(html, L.DISPLAY_STRIP, " "), F.lit(L.INLINE_PATTERN), 1)


def renderer_active(html: Column) -> Column:
    return html.contains("MathJax") | has_common_command(quick_text(html))


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[a-z]+://([^/?#:]+)", 1))


def domain(url: Column, labels: int = 2) -> Column:
    """The last labels of the host; null for an invalid URL."""
    h = host(url)
    parts = F.split(h, r"\.")
    return F.when(h != "", F.array_join(F.slice(parts, F.greatest(F.size(parts) - labels + 1, F.lit(1)), labels), "."))


def canonical(url: Column) -> Column:
    """Without fragment, tracking parameters, and a trailing slash."""
    plain = F.regexp_replace(url, "#.*$", "")
    plain = F.regexp_replace(plain, rf"([?&])(?:{'|'.join(L.TRACKING)})=[^&]*", "$1")
    plain = F.regexp_replace(F.regexp_replace(F.regexp_replace(plain, "[?&]+$", ""), r"\?&+", "?"), "&&+", "&")
    return F.regexp_replace(plain, "/$", "")


def url_rule(url: Column) -> Column:
    """Which rule of inspection a URL falls under, or null."""
    return F.when(url.rlike(r"/(?:user|profile|members?)/"), "profile").when(url.rlike(r"[?&](?:q|query|search|page)="), "listing").when(url.rlike(r"/abs/"), "abstract")


def site_type(url: Column) -> Column:
    return (
        F.when(url.rlike("forum|thread|topic|question"), "Forum").when(url.rlike("arxiv|/pdf/|/abs/|doi"), "Paper").when(host(url).rlike(r"^blog\."), "Blog")
        .when(host(url).rlike(r"^(?:wiki|docs)\.") | url.rlike("dictionary"), "Reference").when(url.rlike(r"course|lecture|lesson|\.edu/"), "Educational").otherwise("Other")
    )


def tokens(text: Column) -> Column:
    """Lower-case words of letters and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def bind(value: Column, f) -> Column:
    """f(value) with value evaluated once a row. Inside f it is a lambda variable, which the optimizer can't replace by
    the expression again (inside another lambda that would repeat it for every element)."""
    return F.element_at(F.transform(F.array(value), f), 1)


def shingles(words: Column, n: int) -> Column:
    """Distinct n-word shingles; fewer words: the whole sequence; none: empty."""

    def of(w: Column) -> Column:
        many = F.transform(F.sequence(F.lit(1), F.size(w) - n + 1), lambda i: F.array_join(F.slice(w, i, n), " "))
        return F.array_distinct(F.when(F.size(w) >= n, many).when(F.size(w) > 0, F.array(F.array_join(w, " "))).otherwise(F.array().cast("array<string>")))

    return bind(words, of)


def hash_order(key: Column, seed: int) -> Column:
    """A reproducible pseudo-random order of keys, the same for any partitioning."""
    from ..fixtures import md5_number

    return md5_number(F.concat(key.cast("string"), F.lit(f"/{seed}")))
