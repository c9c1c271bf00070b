import pytest
from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def documents(spark, rows):
    """rows: (doc_id, text) or (doc_id, text, lang)."""
    return spark.createDataFrame([(*r, *[None] * (3 - len(r)), "s", len(r[1] or "")) for r in rows], SCHEMA)


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and long texts, ties, repeated rows, and columns whose names clash with internal ones."""
    rows = [(None, "no id here but words"), (1, None), (2, ""), (3, "one two three four five"), (3, "one two three four five"), (4, "long word " * 30_000), (5, "\n \t"), (6, "one two three four five"), (7, "ünïcödé 文字 😀 <|endoftext|> x"), (8, "1234 5678 !!!")]
    df = documents(spark, rows)
    for name in ("node", "digest", "key", "token", "host", "label", "x"):
        df = df.withColumn(name, F.lit(1))
    return df
