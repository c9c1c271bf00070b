"""Quality classifier: a generalised additive model with pairwise interactions.

Shallow trees on one binned feature at a time are boosted in a cycle; their sums are one lookup table for each
feature. Then the pairs of features that explain most of what is left get two-dimensional tables the same way.
A text's score is the logistic function of the sum of its table entries.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hash_sample, utf8_view
from .text_shape import NAMES, shape

#: At most this many labelled rows, those with the least id hash, come to the driver (as feature rows, not texts).
SAMPLE = 20_000
CUT = 0.3


@dataclass
class Gam:
    """edges[f]: bin borders; tables[f]: one value for each bin; pairs[(f, g)]: a table over the bins of both."""

    edges: list[np.ndarray]
    base: float = 0.0
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, f], "right") for f, e in enumerate(self.edges)], axis=1)

    def margin(self, x: np.ndarray) -> np.ndarray:
        b = self.bins(x)
        out = np.full(len(x), self.base)
        for f, t in enumerate(self.tables):
            out += t[b[:, f]]
        for (f, g), t in self.pairs.items():
            out += t[b[:, f], b[:, g]]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -40, 40)))


def _leaves(g: np.ndarray, h: np.ndarray, depth: int, ridge: float, least: float) -> np.ndarray:
    """Values of a tree over ordered bins: Newton steps of the leaves left by up to `depth` levels of best cuts."""
    out = np.empty(len(g))

    def grow(a: int, b: int, left: int) -> None:
        gs, hs = np.cumsum(g[a:b]), np.cumsum(h[a:b])
        if left and b - a > 1:
            gain = gs[:-1] ** 2 / (hs[:-1] + ridge) + (gs[-1] - gs[:-1]) ** 2 / (hs[-1] - hs[:-1] + ridge)
            gain[(hs[:-1] < least) | (hs[-1] - hs[:-1] < least)] = -1
            k = int(gain.argmax())
            if gain[k] > gs[-1] ** 2 / (hs[-1] + ridge) + 1e-9:
                grow(a, a + k + 1, left - 1)
                grow(a + k + 1, b, left - 1)
                return
        out[a:b] = gs[-1] / (hs[-1] + ridge)

    grow(0, len(g), depth)
    return out


def _quadrants(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[np.ndarray, float]:
    """Values of the best pair of cuts over a two-dimensional grid, and its gain over none."""
    G, H = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    tot = lambda s: (s[:-1, :-1], s[:-1, -1:] - s[:-1, :-1], s[-1:, :-1] - s[:-1, :-1], s[-1, -1] - s[:-1, -1:] - s[-1:, :-1] + s[:-1, :-1])
    if min(g.shape) < 2:
        return np.zeros_like(g), 0.0
    parts = list(zip(tot(G), tot(H)))
    gain = sum(a * a / (np.maximum(b, 0) + ridge) for a, b in parts)
    i, j = np.unravel_index(int(gain.argmax()), gain.shape)
    v = [a[i, j] / (max(b[i, j], 0) + ridge) for a, b in parts]
    out = np.empty_like(g)
    out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = v
    return out, float(gain[i, j] - G[-1, -1] ** 2 / (H[-1, -1] + ridge))


def fit(x: np.ndarray, y: np.ndarray, bins: int = 32, rounds: int = 120, pair_rounds: int = 40, pairs: int = 6, rate: float = 0.15, depth: int = 2, ridge: float = 2.0) -> Gam:
    """Boost the feature tables in a cycle, then those of the strongest pairs. Without both labels only the base is set."""
    model = Gam([np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) if len(x) else np.empty(0) for f in range(x.shape[1])])
    model.tables = [np.zeros(len(e) + 1) for e in model.edges]
    share = (y.sum() + 0.5) / (len(y) + 1.0)
    model.base = float(np.log(share / (1 - share)))
    if len(y) == 0 or y.min() == y.max():
        return model
    b = model.bins(x)
    m = np.full(len(y), model.base)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-m))
        return y - p, np.maximum(p * (1 - p), 1e-6)

    for _ in range(rounds):
        for f, t in enumerate(model.tables):
            if len(t) > 1:
                g, h = slopes()
                step = rate * _leaves(np.bincount(b[:, f], g, len(t)), np.bincount(b[:, f], h, len(t)), depth, ridge, 1.0)
                t += step
                m += step[b[:, f]]
    coarse = [np.minimum(b[:, f] * 8 // len(t), 7) for f, t in enumerate(model.tables)]
    g, h = slopes()
    gains = []
    for f, k in combinations(range(x.shape[1]), 2):
        code = coarse[f] * 8 + coarse[k]
        gains.append((_quadrants(np.bincount(code, g, 64).reshape(8, 8), np.bincount(code, h, 64).reshape(8, 8), ridge)[1], f, k))
    for _, f, k in sorted(gains, reverse=True)[:pairs]:
        model.pairs[f, k] = np.zeros((len(model.tables[f]), len(model.tables[k])))
    for _ in range(pair_rounds):
        for (f, k), t in model.pairs.items():
            g, h = slopes()
            code = b[:, f] * t.shape[1] + b[:, k]
            step = rate * _quadrants(np.bincount(code, g, t.size).reshape(t.shape), np.bincount(code, h, t.size).reshape(t.shape), ridge)[0]
            t += step
            m += step[b[:, f], b[:, k]]
    for f, t in enumerate(model.tables):  # tables of mean 0, so that the base is the prior
        mean = float(t[b[:, f]].mean())
        t -= mean
        model.base += mean
    return model


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    """Whether crc32 of the id as text is `part` modulo `parts`; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(parts)) == part


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x = shape(*utf8_view(batch.column(1)))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), len(NAMES)).cast(pa.list_(pa.float64()))], ["label", "x"])


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Gam:
    """Learn labels.quality from the rows that aren't held out; a document labelled more than once has its highest label."""
    known = labels.where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), 5, 0))
    known = known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("label"))
    known = hash_sample(known, "doc_id", sample, labels.count())
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(known), "doc_id").select(F.col("label").cast("long").alias("label"), "text")
    got = rows.mapInArrow(_features, "label long, x array<double>").toPandas()
    got = got.iloc[np.lexsort(np.array([list(v) for v in got["x"]]).T)] if len(got) else got  # the order of rows can't matter
    x = np.array(got["x"].tolist(), float).reshape(len(got), len(NAMES))
    return fit(x, (got["label"].to_numpy(float) > 0).astype(float))


def score(docs: DataFrame, model: Gam, cut: float = CUT) -> DataFrame:
    """One row per input row: doc_id, held_out, score, predicted.

    Null and empty texts have the score of all features being 0; repeated rows are scored each; a null id keeps its
    row (held out); other columns are ignored whatever their names; an empty table gives an empty result. Scores
    depend on the text alone.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(model.score(shape(*utf8_view(batch.column(2)))))], ["doc_id", "held_out", "score"])

    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), 5, 0).alias("held_out"), F.col("text").cast("string").alias("text"))
    return narrow.mapInArrow(run, "doc_id long, held_out boolean, score double").withColumn("predicted", (F.col("score") >= cut).cast("int"))


def op6_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels")))
