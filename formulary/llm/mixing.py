"""Mixing domains to target weights with soft memberships.

A classifier fitted on the labelled table predicts each document's domain posteriors. Nonnegative document rates
are then fitted by projected-gradient least squares, so that the expected tokens of every domain meet its target:
minimise the distance between A r and t over r >= 0, where A's column of a document is its tokens times its
posteriors. A step moves the rates by the posteriors times a small vector of multipliers, then clips them at 0. A
document's rate is a function of its posteriors and of the multipliers of the steps so far, so no state is kept
per document: each step is one scan that returns a sum per domain, whatever the number of documents.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_slabs, hash_sample, materialise, mix64, utf8_view
from .shingles import words
from .text_shape import NAMES, shape

DOMAINS = ("clean", "junk", "toxic")
#: Target share of the tokens of each domain in the mixture.
TARGETS = {"clean": 0.955, "junk": 0.04, "toxic": 0.005}
#: At most this many labelled documents, those with the least id hash, are fitted on (as hashed words, not texts).
SAMPLE = 6_000
KEYWORDS = 250
STEPS = 40
TOLERANCE = 1e-4


def domain_of(quality: int | None, toxic: int | None) -> int | None:
    """toxic before junk before clean; None if neither label is there."""
    if quality is None and toxic is None:
        return None
    return 2 if toxic else 1 if quality == 0 else 0


@dataclass
class Classifier:
    """Multinomial logistic regression on the presence of some words and on standardised shape features."""

    vocabulary: np.ndarray  # ascending word hashes
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray

    def inputs(self, present: np.ndarray, shapes: np.ndarray) -> np.ndarray:
        return np.concatenate([present, np.clip((shapes - self.mean) / self.scale, -5, 5), np.ones((len(shapes), 1))], axis=1)

    def posteriors(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(posteriors, number of words) of each text."""
        n, v = len(offsets) - 1, self.vocabulary
        out, count = np.zeros((n, self.weights.shape[1])), np.zeros(n, np.int64)
        for a, b in byte_slabs(offsets, 1 << 20):
            part, at = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            w, wat = words(part, at)
            count[a:b] = np.diff(wat)
            present = np.zeros((b - a, len(v)), np.float32)
            if len(v) and len(w):
                slot = np.minimum(np.searchsorted(v, w), len(v) - 1)
                hit = v[slot] == w
                present[np.repeat(np.arange(b - a), count[a:b])[hit], slot[hit]] = 1
            z = self.inputs(present, shape(part, at)) @ self.weights
            z = np.exp(z - z.max(axis=1, keepdims=True))
            out[a:b] = z / z.sum(axis=1, keepdims=True)
        return out, count


def fit_classifier(word_sets: list[np.ndarray], shapes: np.ndarray, domain: np.ndarray, k: int = len(DOMAINS), keywords: int = KEYWORDS, steps: int = 500, ridge: float = 1e-5) -> Classifier:
    """Pick the words whose presence differs most between a domain and the rest, then fit by Adam on the whole sample."""
    n = len(domain)
    if n == 0:
        return Classifier(np.empty(0, np.uint64), np.zeros(len(NAMES)), np.ones(len(NAMES)), np.zeros((len(NAMES) + 1, k)))
    sizes = [len(s) for s in word_sets]
    value, code = np.unique(np.concatenate(word_sets), return_inverse=True)
    owner = np.repeat(np.arange(n), sizes)
    picked: set[int] = set()
    for d in range(k):
        own = domain == d
        if own.any() and not own.all():
            a = np.bincount(code[own[owner]], minlength=len(value)) / own.sum()
            b = np.bincount(code[~own[owner]], minlength=len(value)) / (~own).sum()
            score = (a - b) ** 2 / (a + b + 20 / n)
            picked.update(np.argsort(-score, kind="stable")[:keywords][: len(value)].tolist())
    chosen = np.array(sorted(picked), np.int64)
    place = np.full(len(value), -1)
    place[chosen] = np.arange(len(chosen))
    present = np.zeros((n, len(chosen)), np.float32)
    hit = place[code] >= 0
    present[owner[hit], place[code[hit]]] = 1
    spread = shapes.std(axis=0)
    model = Classifier(value[chosen], shapes.mean(axis=0), np.where(spread > 1e-9, spread, 1.0), np.zeros((len(chosen) + shapes.shape[1] + 1, k)))
    x, y = model.inputs(present, shapes).astype(np.float64), np.eye(k)[domain]
    first, second, w = np.zeros_like(model.weights), np.zeros_like(model.weights), model.weights
    for t in range(1, steps + 1):
        z = x @ w
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        g = x.T @ (p - y) / n + ridge * w
        first += 0.1 * (g - first)
        second += 0.001 * (g * g - second)
        w -= 0.05 * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return model


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Classifier:
    """Learn the domain from the labelled table; a document labelled more than once has its worst labels."""
    known = labels.where(F.col("doc_id").isNotNull() & (F.col("quality").isNotNull() | F.col("toxic").isNotNull()))
    known = known.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").cast("int").alias("quality"), F.max("toxic").cast("int").alias("toxic"))
    known = hash_sample(known, "doc_id", sample, labels.count())
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(known), "doc_id").select("doc_id", "quality", "toxic", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8_view(batch.column(3))
            w, at = words(data, offsets)
            sets = [np.unique(w[a:b]).tobytes() for a, b in zip(at, at[1:])]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(3)), pa.array(sets, pa.binary()), pa.array([r.tobytes() for r in shape(data, offsets)], pa.binary())], ["doc_id", "quality", "toxic", "words", "shape"])

    got = rows.mapInArrow(run, "doc_id long, quality int, toxic int, words binary, shape binary").collect()
    got.sort(key=lambda r: (r.doc_id, r.words, r.shape))
    domain = np.array([domain_of(r.quality, r.toxic) for r in got], np.int64)
    shapes = np.array([np.frombuffer(r.shape) for r in got]).reshape(len(got), len(NAMES))
    return fit_classifier([np.frombuffer(r.words, np.uint64) for r in got], shapes, domain)


@dataclass
class Steps:
    """Multipliers of the steps so far. After the first `free` ones, rates within `snap` of a whole number of 1 or more
    are set to it; the later steps move the others only."""

    nu: np.ndarray
    free: int
    snap: float = 0.0


def split_rates(p: np.ndarray, steps: Steps) -> tuple[np.ndarray, np.ndarray]:
    """(rates, whether each was set to a whole number) of documents with posteriors p."""
    r, held = np.ones(len(p)), np.zeros(len(p), bool)
    for nu in steps.nu[: steps.free]:
        r = np.maximum(0.0, r - p @ nu)
    if steps.snap > 0:
        whole = np.round(r)
        held = (whole >= 1) & (np.abs(r - whole) <= steps.snap)
        r = np.where(held, whole, r)
    for nu in steps.nu[steps.free :]:
        r = np.where(held, r, np.maximum(0.0, r - p @ nu))
    return r, held


def rates(p: np.ndarray, history: np.ndarray | Steps) -> np.ndarray:
    """Rates of documents with posteriors p after the steps of history (or the steps whose multipliers it has)."""
    return split_rates(p, history if isinstance(history, Steps) else Steps(history, len(history)))[0]


def _memberships(model: Classifier):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p, n = model.posteriors(*utf8_view(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), *(pa.array(p[:, j]) for j in range(p.shape[1]))], ["doc_id", "tokens", *(f"p_{d}" for d in DOMAINS)])

    return run


_MEMBER = "doc_id long, tokens long, " + ", ".join(f"p_{d} double" for d in DOMAINS)


def memberships(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, tokens (words), and a posterior for each domain."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_memberships(model), _MEMBER)


def _matrix(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    return np.stack([batch.column(f"p_{d}").to_numpy() for d in DOMAINS], axis=1), batch.column("tokens").to_numpy().astype(float)


def _sums(table: DataFrame, history: np.ndarray | Steps, gram: bool) -> np.ndarray:
    """Over all documents: tokens times rate by domain, or (of documents not set to a whole number) the token-weighted products of posteriors."""
    k = len(DOMAINS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((k, k) if gram else k)
        for batch in batches:
            p, n = _matrix(batch)
            if gram and isinstance(history, Steps):
                n = n * ~split_rates(p, history)[1]
            total += (p * n[:, None]).T @ p if gram else (n * rates(p, history)) @ p
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size).astype(np.int32)), pa.array(total.ravel())], ["cell", "v"])

    got = table.drop("doc_id").mapInArrow(run, "cell int, v double").groupBy("cell").agg(F.sum("v").alias("v")).collect()
    out = np.zeros(k * k if gram else k)
    for r in got:
        out[r.cell] = r.v
    return out.reshape(k, k) if gram else out


def fit_rates(table: DataFrame, targets: dict[str, float], total: float | None = None, keep: str | None = None, steps: int = STEPS, tolerance: float = TOLERANCE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(multipliers of all steps, expected tokens by domain, target tokens by domain).

    total: tokens of the mixture; by default those of the input, or, with `keep`, as many as leave that domain's
    tokens as they are. The step is 1 in the metric of the token-weighted Gram matrix of the posteriors, in which
    the gradient's Lipschitz constant is 1; fitting stops when the misfit is below tolerance of the total.
    """
    weight = np.array([max(0.0, float(targets.get(d, 0.0))) for d in DOMAINS])
    weight = weight / weight.sum() if weight.sum() else np.full(len(DOMAINS), 1 / len(DOMAINS))
    history = np.zeros((0, len(DOMAINS)))
    now = _sums(table, history, False)
    if total is None:
        k = DOMAINS.index(keep) if keep else 0
        total = now[k] / weight[k] if keep and weight[k] > 0 else now.sum()
    goal = weight * total
    inverse = np.linalg.pinv(_sums(table, history, True), rcond=1e-10)
    for _ in range(steps):
        miss = now - goal
        if np.abs(miss).max() <= tolerance * max(total, 1.0):
            break
        history = np.concatenate([history, [inverse @ miss]])
        later = _sums(table, history, False)
        if np.abs(later - now).max() <= tolerance * max(total, 1.0):
            now = later
            break
        now = later
    return history, now, goal


def fit_whole_rates(table: DataFrame, targets: dict[str, float], snap: float, steps: int = STEPS, tolerance: float = TOLERANCE, **fitting) -> tuple[Steps, np.ndarray, np.ndarray]:
    """fit_rates, then rates near a whole number are set to it and the other documents are fitted again to what is left
    of the targets: (steps, expected tokens by domain, target tokens by domain). Rates below 1 - snap never become 0 by it."""
    nu, now, goal = fit_rates(table, targets, steps=steps, tolerance=tolerance, **fitting)
    history = Steps(nu, len(nu), snap)
    if snap <= 0:
        return history, now, goal
    limit = tolerance * max(goal.sum(), 1.0)
    now = _sums(table, history, False)
    inverse = np.linalg.pinv(_sums(table, history, True), rcond=1e-10)
    for _ in range(steps):
        miss = now - goal
        if np.abs(miss).max() <= limit:
            break
        history = Steps(np.concatenate([history.nu, [inverse @ miss]]), history.free, snap)
        before, now = now, _sums(table, history, False)
        if np.abs(now - before).max() <= limit:
            break
    return history, now, goal


def copies(rate: np.ndarray, draw: np.ndarray, snap: float = 0.0) -> np.ndarray:
    """Whole copies with the rate as mean: draw is uniform in [0, 1). Rates within `snap` of a whole number are taken as it."""
    whole = np.round(rate)
    return np.where(np.abs(rate - whole) <= snap, whole, np.floor(rate + draw)).astype(np.int64)


def _draws(ids: pa.Array, data: np.ndarray | None = None) -> np.ndarray:
    """A number in [0, 1) for each id, the same in every run."""
    x = np.array([0x5BD1E995 if i is None else i & 0xFFFFFFFFFFFFFFFF for i in ids.to_pylist()], np.uint64)
    return (mix64(x + np.uint64(0x632BE59BD9B4E019)) >> np.uint64(11)).astype(float) / 2**53


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] = TARGETS, **fitting) -> DataFrame:
    """One row per input row: doc_id, tokens, p_clean, p_junk, p_toxic, rate, copies.

    Null and empty texts have 0 tokens and the posteriors of an empty text; repeated rows have equal rates and
    copies; a null id keeps its row; other columns are ignored whatever their names; an empty table gives an empty
    result. Without labels all posteriors are equal. Domains without expected tokens can't be raised: their misfit
    stays. copies: the rate rounded up or down by a hash of the id, so that its mean is the rate.
    """
    table = materialise(memberships(docs, train(docs, labels)), "mixing-members")
    history, _, _ = fit_rates(table, targets, **fitting)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            r = rates(_matrix(batch)[0], history)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(r), pa.array(copies(r, _draws(batch.column(0))))], [*batch.schema.names, "rate", "copies"])

    return table.mapInArrow(run, _MEMBER + ", rate double, copies long")


def resample(docs: DataFrame, labels: DataFrame, targets: dict[str, float] = TARGETS, snap: float = 0.1, **fitting) -> DataFrame:
    """The mixture itself: every row of docs as many times as its copies say, with all its columns.

    snap: rates this near to a whole number of 1 or more are taken as it, so that most documents stay as they are;
    the other rates are fitted with these given, so that the expected tokens still meet the targets.
    """
    model = train(docs, labels)
    table = materialise(memberships(docs, model), "mixing-members")
    history, _, _ = fit_whole_rates(table, targets, snap, **fitting)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p, _ = model.posteriors(*utf8_view(batch.column(batch.num_columns - 1)))
            n = copies(rates(p, history), _draws(batch.column(batch.num_columns - 2)))
            own = pa.RecordBatch.from_arrays(batch.columns[:-2], batch.schema.names[:-2])
            yield own.take(pa.array(np.repeat(np.arange(len(n)), n)))

    return docs.withColumn("_id", F.col("doc_id").cast("long")).withColumn("_text", F.col("text").cast("string")).mapInArrow(run, schema)


def op10_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return mix(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
