"""Tests for the findings of the second review that were settled last."""

import os

import numpy as np

from formulary.llm import column_bwt
from formulary.llm.common import materialise


def test_pipeline_tables_between_stages_have_no_checksum_files(spark):
    """Each would cost a process that for a moment shares the executor's memory."""
    got = materialise(spark.range(0, 1000, 1, 7), "test-materialise")
    folder = got.inputFiles()[0].removeprefix("file://").rsplit("/", 1)[0]
    names = os.listdir(folder)
    assert sum(n.endswith(".parquet") for n in names) == 7 and not [n for n in names if n.endswith(".crc")]
    assert sorted(r.id for r in got.collect()) == list(range(1000))


def test_op3_byte_symbols_sort_where_they_are(monkeypatch):
    """Only symbols beyond a byte, one for each string, are picked out and sorted by themselves."""
    rng = np.random.default_rng(3)
    symbols = rng.integers(0, 254, 5000).astype(np.uint16)
    symbols[rng.choice(5000, 40, replace=False)] = rng.integers(255, 900, 40)
    want, sort, sizes = np.argsort(symbols, kind="stable"), np.argsort, []
    monkeypatch.setattr(column_bwt.np, "argsort", lambda x, **kw: sizes.append(len(x)) or sort(x, **kw))
    assert (column_bwt._order(symbols) == want).all() and sizes == [5000, 40]
