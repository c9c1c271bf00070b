"""Line stage: boilerplate lines, empty headers, stray dollars, and the parameters drawn for each document."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import lexicon as L
from ..functions import columns as C


def parameters(key: Column, seed: int, markdown_share: float = 0.5, lo: int = 1, hi: int = 3) -> list[Column]:
    """output_format and boilerplate_trigger of a document: drawn by hash, so a task that runs again draws alike."""
    form = F.when(F.pmod(C.hash_order(key, seed), F.lit(2)) == 0, "plain").otherwise("markdown") if markdown_share == 0.5 else F.when(F.pmod(C.hash_order(key, seed), F.lit(1000)) >= int(1000 * markdown_share), "plain").otherwise("markdown")
    return [form.alias("output_format"), (F.pmod(C.hash_order(key, seed + 1), F.lit(hi - lo + 1)) + lo).cast("int").alias("boilerplate_trigger")]


def phrase_hits(line: Column, phrases=L.PHRASES) -> Column:
    return reduce(lambda a, b: a + b, (F.lower(line).contains(p).cast("int") for p in phrases))


def drop_boilerplate(text: Column, trigger: Column | int, phrases=L.PHRASES) -> Column:
    """Without the lines that have at least `trigger` different phrases."""
    return F.array_join(F.filter(F.split(text, "\n"), lambda x: phrase_hits(x, phrases) < trigger), "\n")


def is_header(line: Column) -> Column:
    return line.rlike("^#+ ")


def drop_empty_headers(text: Column) -> Column:
    """Without headers that another header or the end follows, blank lines aside."""

    def of(rows: Column) -> Column:
        def stays(x, i):
            rest = F.filter(F.slice(rows, i + 2, F.size(rows)), lambda y: F.trim(y) != "")
            return ~(is_header(x) & F.coalesce(is_header(F.get(rest, F.lit(0))), F.lit(True)))

        return F.array_join(F.filter(rows, stays), "\n")

    return C.bind(F.split(text, "\n"), of)


def escape_dollars(text: Column) -> Column:
    return F.regexp_replace(text, r"\$", r"\\\$")


def repeated(docs: DataFrame, key: str, text_col: str, min_docs: int) -> DataFrame:
    """line, n_docs, n of lines that many documents have: candidates for the phrase list."""
    per = docs.select(key, F.explode(F.split(text_col, "\n")).alias("line")).where(F.trim("line") != "").groupBy(key, "line").agg(F.count("*").alias("k"))
    return per.groupBy("line").agg(F.count("*").alias("n_docs"), F.sum("k").alias("n")).where(F.col("n_docs") >= min_docs)
