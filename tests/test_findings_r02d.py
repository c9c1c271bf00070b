"""Tests for F4 and F5 of the second review."""

import math
from collections import Counter, defaultdict

import numpy as np
import pytest

from formulary.operators import language_model as lm


def _brute(learn: list[list[str]], asked: dict[int, list[str]], order: int) -> dict[int, tuple[int, float]]:
    """Tokens and perplexity by modified Kneser-Ney on dictionaries of word tuples."""
    starts = ["<s>"] * max(1, order - 1)
    raw = {n: Counter(tuple(w[i - n + 1 : i + 1]) for t in learn for w in [[*starts, *t, "</s>"]] for i in range(len(starts), len(w))) for n in range(1, order + 1)}
    used = {order: raw[order]}
    for n in range(order - 1, 0, -1):
        inner = Counter(g[1:] for g in raw[n + 1])
        used[n] = {g: raw[n][g] if n > 1 and g[0] == "<s>" else c for g, c in inner.items()}
    p, bow, unknown = {}, {}, 1.0
    for n in range(1, order + 1):
        d = [0.0, *lm.ModifiedKneserNey._discounts([sum(c == k for c in used[n].values()) for k in (1, 2, 3, 4)])]
        total, freed = defaultdict(float), defaultdict(float)
        for g, c in used[n].items():
            total[g[:-1]] += c
            freed[g[:-1]] += d[min(c, 3)]
        bow |= {c: freed[c] / total[c] for c in total} if n > 1 else {}
        unknown = freed[()] / total[()] / (len(used[1]) + 1) if n == 1 and used[1] else unknown
        for g, c in used[n].items():
            p[g] = max(c - d[min(c, 3)], 0.0) / total[g[:-1]] + (bow[g[:-1]] * p[g[1:]] if n > 1 else unknown)

    def of(g: tuple[str, ...]) -> float:
        return p[g] if g in p else unknown if len(g) == 1 else bow.get(g[:-1], 1.0) * of(g[1:])

    out = {}
    for i, t in asked.items():
        w = [*starts, *t, "</s>"]
        lp = [math.log(of(tuple(w[k - order + 1 : k + 1]))) for k in range(len(starts), len(w))]
        out[i] = len(lp), math.exp(-sum(lp) / len(lp))
    return out


def _texts(seed: int, n: int) -> list[str]:
    rng = np.random.default_rng(seed)
    return [" ".join(f"w{k}" for k in rng.zipf(1.5, rng.integers(0, 60)) if k < 400) for _ in range(n)]


@pytest.mark.parametrize("order", [1, 2, 3, 5])
def test_f4_kneser_ney_equals_dictionaries(spark, order, monkeypatch):
    """Also in small packets, with texts that are null, empty or unlike what was learned, and with one key twice or null."""
    monkeypatch.setattr(lm, "_CHUNK", 100)
    learn, asked = _texts(1, 60), [*_texts(2, 40), "", "never seen words", *_texts(1, 3)]
    train = spark.createDataFrame([(i, t) for i, t in enumerate(learn)], "doc_id long, text string").repartition(3)
    rows = [*enumerate(asked), (len(asked), None), (None, "w1 w2"), (0, None)]
    model = lm.ModifiedKneserNey(train, order)
    got = {r.doc_id: (r.n_tokens, r.ppl) for r in lm.perplexity(model.log_probabilities(spark.createDataFrame(rows, "doc_id long, text string"))).collect()}
    want = _brute([t.split() for t in learn], {i: t.split() for i, t in enumerate(asked)} | {len(asked): [], None: ["w1", "w2"]}, order)
    both = _brute([t.split() for t in learn], {0: [], 1: asked[0].split()}, order)
    n, m = both[0][0], both[1][0]
    want[0] = n + m, math.exp((n * math.log(both[0][1]) + m * math.log(both[1][1])) / (n + m))
    assert got.keys() == want.keys() and all(got[i][0] == want[i][0] and got[i][1] == pytest.approx(want[i][1], rel=1e-9) for i in want)


def test_f4_tokens_are_shuffled_once_for_all_orders(spark):
    docs = spark.createDataFrame([(1, "a b a c"), (2, "a b b")], "doc_id long, text string")
    plan = lm.ModifiedKneserNey(docs, 5).log_probabilities(docs)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and plan.count("RepartitionByExpression") == 1


def test_f4_every_token_counts(spark):
    """An estimated discount of 0 left contexts nothing for other words; the logarithm of 0 is null and was left out of the mean."""
    assert all(d > 0 for d in lm.ModifiedKneserNey._discounts([10, 10, 10, 90]))
