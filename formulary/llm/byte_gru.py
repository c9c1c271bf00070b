"""Language identification by a bidirectional gated recurrent network over bytes.

The network is trained in numpy by backpropagation through time. It labels every byte position of a text; the
probabilities of a document's positions are pooled to its prediction. Whole texts are read: long ones lie as
stretches side by side, each with some bytes of its neighbours to warm the state up.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hash_sample, utf8_view
from .quality_gam import held_out

#: At most this many labelled documents, those with the least id hash, go to the driver, with their whole texts.
SAMPLE = 4000
HIDDEN = 8
CORE, WARM = 120, 12
UNKNOWN = "und"


@dataclass
class Gru:
    """Weights of both directions. x: byte -> inputs of the three gates; u: state -> gates; o: state -> languages."""

    languages: list[str]
    x: list[np.ndarray]
    u: list[np.ndarray]
    o: list[np.ndarray]
    bias: np.ndarray

    def parameters(self) -> list[np.ndarray]:
        return [*self.x, *self.u, *self.o, self.bias]


def new_model(languages: list[str], hidden: int = HIDDEN, seed: int = 11) -> Gru:
    rng = np.random.default_rng(seed)
    weights = lambda *shape, scale: rng.normal(0, scale, shape).astype(np.float32)
    k = len(languages)
    return Gru(languages, [weights(256, 3 * hidden, scale=0.3) for _ in range(2)], [weights(hidden, 3 * hidden, scale=hidden**-0.5) for _ in range(2)], [weights(hidden, k, scale=hidden**-0.5) for _ in range(2)], np.zeros(k, np.float32))


def _walk(x: np.ndarray, u: np.ndarray, rows: np.ndarray, keep: bool = False, inside: np.ndarray | None = None) -> tuple[np.ndarray, list]:
    """States after each step of (time, batch) bytes; with keep, what the way back needs. Where inside is false the state is 0."""
    t, n = rows.shape
    h_size = u.shape[0]
    h = np.zeros((n, h_size), np.float32)
    states, kept = np.empty((t, n, h_size), np.float32), []
    for i in range(t):
        a, b = x[rows[i]], h @ u
        gates = a[:, : 2 * h_size] + b[:, : 2 * h_size]
        gates *= 0.5
        np.tanh(gates, out=gates)
        gates += 1
        gates *= 0.5
        z, r = gates[:, :h_size], gates[:, h_size:]
        c = b[:, 2 * h_size :] * r
        c += a[:, 2 * h_size :]
        np.tanh(c, out=c)
        if keep:
            kept.append((h, gates, c, b[:, 2 * h_size :]))
        h = c + z * (h - c)
        if inside is not None:
            h *= inside[i][:, None]
        states[i] = h
    return states, kept


def _walk_back(u: np.ndarray, rows: np.ndarray, kept: list, grad: np.ndarray, x_shape: tuple) -> tuple[np.ndarray, np.ndarray]:
    """Gradients of x and u, given those of all states."""
    h_size = u.shape[0]
    gx, gu = np.zeros(x_shape, np.float32), np.zeros_like(u)
    carry = np.zeros((rows.shape[1], h_size), np.float32)
    for i in range(len(kept) - 1, -1, -1):
        h, gates, c, hc = kept[i]
        z, r = gates[:, :h_size], gates[:, h_size:]
        d = grad[i] + carry
        dc = d * (1 - z) * (1 - c * c)
        dz = d * (h - c) * z * (1 - z)
        dr = dc * hc * r * (1 - r)
        da = np.concatenate([dz, dr, dc], axis=1)
        db = np.concatenate([dz, dr, dc * r], axis=1)
        np.add.at(gx, rows[i], da)
        gu += h.T @ db
        carry = d * z + db @ u.T
    return gx, gu


def _softmax(x: np.ndarray) -> np.ndarray:
    x = x - x.max(axis=-1, keepdims=True)
    np.exp(x, out=x)
    x /= x.sum(axis=-1, keepdims=True)
    return x


def position_probabilities(model: Gru, rows: np.ndarray, inside: np.ndarray | None = None) -> np.ndarray:
    """(time, batch) bytes -> (time, batch, languages). inside: which of them are of the text; both directions start at its ends."""
    ahead, _ = _walk(model.x[0], model.u[0], rows, inside=inside)
    behind, _ = _walk(model.x[1], model.u[1], rows[::-1], inside=None if inside is None else inside[::-1])
    return _softmax(ahead @ model.o[0] + behind[::-1] @ model.o[1] + model.bias)


def gradients(model: Gru, rows: np.ndarray, target: np.ndarray, weight: np.ndarray) -> tuple[float, list[np.ndarray]]:
    """Weighted mean cross-entropy of all positions and its gradients; rows and weight: (time, batch), target: (batch)."""
    ahead, kept_a = _walk(model.x[0], model.u[0], rows, True)
    behind, kept_b = _walk(model.x[1], model.u[1], rows[::-1], True)
    p = _softmax(ahead @ model.o[0] + behind[::-1] @ model.o[1] + model.bias)
    total = max(float(weight.sum()), 1e-9)
    picked = np.take_along_axis(p, np.broadcast_to(target[None, :, None], (*p.shape[:2], 1)), axis=2)[..., 0]
    loss = float(-(np.log(np.maximum(picked, 1e-12)) * weight).sum() / total)
    g = p.copy()
    np.put_along_axis(g, np.broadcast_to(target[None, :, None], (*p.shape[:2], 1)), (picked - 1)[..., None], axis=2)
    g *= (weight / total)[..., None].astype(np.float32)
    go = [np.einsum("tnh,tnk->hk", ahead, g), np.einsum("tnh,tnk->hk", behind[::-1], g)]
    gx0, gu0 = _walk_back(model.u[0], rows, kept_a, g @ model.o[0].T, model.x[0].shape)
    gx1, gu1 = _walk_back(model.u[1], rows[::-1], kept_b, (g @ model.o[1].T)[::-1], model.x[1].shape)
    return loss, [gx0, gx1, gu0, gu1, *go, g.sum(axis=(0, 1))]


def fit(texts: list[bytes], languages: list[str], known: list[str], hidden: int = HIDDEN, steps: int = 450, batch: int = 160, span: int = 64, rate: float = 0.02, seed: int = 11) -> Gru:
    """Adam on random batches of `span` bytes from anywhere in the texts, each language drawn alike often; positions past
    a text's end weigh nothing."""
    model = new_model(known, hidden, seed)
    if len(known) < 2:
        return model
    rng = np.random.default_rng(seed)
    size, target = np.array([len(s) for s in texts]), np.array([known.index(x) for x in languages])
    data, begin = np.frombuffer(b"".join(texts), np.uint8), np.cumsum(size) - size
    span = min(span, int(size.max()))
    of = [np.flatnonzero(target == k) for k in range(len(known))]
    first, second = [np.zeros_like(p) for p in model.parameters()], [np.zeros_like(p) for p in model.parameters()]
    for t in range(1, steps + 1):
        pick = np.concatenate([rng.choice(o, -(-batch // len(known))) for o in of])
        start = (rng.random(len(pick)) * np.maximum(size[pick] - span + 1, 1)).astype(int)
        at = start[:, None] + np.arange(span)
        weight = (at < size[pick][:, None]).astype(np.float32)
        chosen = np.where(weight > 0, data[np.minimum(begin[pick][:, None] + at, len(data) - 1)], 0)
        _, grads = gradients(model, np.ascontiguousarray(chosen.T), target[pick], weight.T)
        norm = np.sqrt(sum(float((g * g).sum()) for g in grads))
        step = rate * min(1.0, 2 * (1 - t / (steps + 1)))
        for p, g, a, b in zip(model.parameters(), grads, first, second):
            g = g / max(1.0, norm)
            a += 0.1 * (g - a)
            b += 0.01 * (g * g - b)
            p -= step * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.99**t)) + 1e-7)
    return model


def pooled(model: Gru, data: np.ndarray, offsets: np.ndarray, core: int = CORE, warm: int = WARM, width: int = 2048) -> np.ndarray:
    """Mean of the position probabilities of each text; a text without bytes has equal ones."""
    n, k = len(offsets) - 1, len(model.languages)
    size = np.diff(offsets)
    pieces = -(-size // core)
    owner = np.repeat(np.arange(n), pieces)
    index = np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    begin, end = offsets[owner] + index * core, offsets[1:][owner]
    total = np.zeros((n, k))
    if len(model.languages) == 1:
        return np.ones((n, 1))
    for i in range(0, len(owner), width):
        o, b, e = owner[i : i + width], begin[i : i + width], end[i : i + width]
        at = b[None, :] - warm + np.arange(core + 2 * warm)[:, None]
        inside = (at >= offsets[o][None, :]) & (at < e[None, :])
        rows = np.where(inside, data[np.clip(at, 0, len(data) - 1)], 0).astype(np.uint8)
        p = position_probabilities(model, rows, None if inside.all() else inside)[warm : warm + core]
        p *= (at[warm : warm + core] < np.minimum(b + core, e)[None, :])[..., None]
        np.add.at(total, o, p.sum(axis=0))
    return np.where(size[:, None] > 0, total / np.maximum(size, 1)[:, None], 1 / max(k, 1))


def train(docs: DataFrame, sample: int = SAMPLE) -> Gru | None:
    """Learn from text and non-null lang of documents that aren't held out: whole texts of a sample of them."""
    known = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), 4, 2) & F.col("text").rlike(r"\p{L}"))
    got = hash_sample(known.select("doc_id", "lang", "text"), "doc_id", sample, docs.count()).collect()
    return fit([r.text.encode("utf-8", "surrogatepass") for r in got], [r.lang for r in got], sorted({r.lang for r in got})) if got else None


def with_language(docs: DataFrame, model: Gru | None, text_col: str = "text") -> DataFrame:
    """docs with columns _lang and _lang_score; texts that are null or have no letter are `und` with score 0.

    Without a model (nothing to learn from) every text is `und`. Columns of docs keep their names and values
    (names starting with _ are reserved).
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = pooled(model, *utf8_view(batch.column(batch.num_columns - 2)))
            best, has = p.argmax(axis=1) if len(p) else np.empty(0, int), batch.column(batch.num_columns - 1).to_pylist()
            lang = [model.languages[b] if ok else UNKNOWN for b, ok in zip(best.tolist(), has)]
            score = [float(min(1.0, p[i, b])) if ok else 0.0 for i, (b, ok) in enumerate(zip(best.tolist(), has))]
            keep = [i for i in range(batch.num_columns - 2)]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(lang, pa.string()), pa.array(score, pa.float64())], [*(batch.schema.names[i] for i in keep), "_lang", "_lang_score"])

    if model is None:
        return docs.withColumn("_lang", F.lit(UNKNOWN)).withColumn("_lang_score", F.lit(0.0))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema), "_lang string", "_lang_score double"])
    return docs.withColumn("_text", F.col(text_col).cast("string")).withColumn("_letters", F.coalesce(F.col("_text").rlike(r"\p{L}"), F.lit(False))).mapInArrow(run, schema)


def identify(docs: DataFrame, model: Gru | None) -> DataFrame:
    """One row per input row: doc_id, held_out, lang_pred, score.

    Null texts and those without a letter are `und` with score 0; repeated rows are judged each; a null id keeps its
    row; other columns are ignored whatever their names; an empty table gives an empty result.
    """
    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), 4, 2).alias("held_out"), "text")
    return with_language(narrow, model).select("doc_id", "held_out", F.col("_lang").alias("lang_pred"), F.col("_lang_score").alias("score"))


def op7_query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    docs = table(spark, sf_dir, "documents")
    return identify(docs, train(docs))
