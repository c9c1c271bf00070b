"""n-gram counts, smoothing and perplexity, as joins of n-gram tables; Kneser-Ney above order two on packed tokens."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import columns as C
from .dedup import _GOLD, _STEP, _mix, _stored

_tokens = lambda text: F.coalesce(C.tokens(text), F.array().cast("array<string>"))  # noqa: E731  (a null text predicts the end mark alone)
START, END, UNKNOWN = "<s>", "</s>", "<unk>"


def marked(docs: DataFrame, order: int, key: str = "doc_id", text_col: str = "text") -> DataFrame:
    """key and its tokens with order - 1 start marks and an end mark."""
    starts = F.array(*([F.lit(START)] * max(1, order - 1)))
    return docs.select(key, F.concat(starts, _tokens(F.col(text_col)), F.array(F.lit(END))).alias("w"))


def ngrams(docs: DataFrame, n: int, order: int | None = None, key: str = "doc_id") -> DataFrame:
    """key, ctx (n - 1 words), w: every n-gram that predicts a word or the end mark."""
    order = order or n
    skip = max(1, order - 1)
    grams = C.bind(F.col("w"), lambda w: F.transform(F.sequence(F.lit(skip + 1), F.size(w)), lambda i: F.struct(F.array_join(F.slice(w, i - (n - 1), n - 1), " ").alias("ctx"), F.element_at(w, i).alias("w"))))
    return marked(docs, order, key).select(key, F.inline(grams))


def counts(docs: DataFrame, n: int, order: int | None = None) -> DataFrame:
    return ngrams(docs, n, order).groupBy("ctx", "w").agg(F.count("*").alias("c"))


def fit_bigram_kn(docs: DataFrame, discount: float = 0.75) -> dict[str, DataFrame]:
    """Interpolated Kneser-Ney of order 2: bigram counts, context totals, continuation counts, their total."""
    bi = counts(docs, 2)
    ctx = bi.groupBy("ctx").agg(F.sum("c").alias("total"), F.count("*").alias("kinds"))
    cont = bi.groupBy("w").agg(F.count("*").alias("cont"))
    return {"bi": bi, "ctx": ctx, "cont": cont, "types": bi.agg(F.count("*").alias("types")), "vocab": cont.agg((F.count("*") + 1).alias("v")), "discount": discount}


def kn_log_probabilities(docs: DataFrame, m: dict, key: str = "doc_id") -> DataFrame:
    """key, lp: natural log-probability of every predicted token. Unknown words share the uniform mass."""
    g = ngrams(docs, 2, key=key).groupBy(key, "ctx", "w").agg(F.count("*").alias("k"))
    x = g.join(m["bi"], ["ctx", "w"], "left").join(m["ctx"], "ctx", "left").join(m["cont"], "w", "left").crossJoin(F.broadcast(m["types"])).crossJoin(F.broadcast(m["vocab"]))
    d, c = m["discount"], F.coalesce(F.col("c"), F.lit(0))
    lower = F.greatest(F.coalesce(F.col("cont"), F.lit(0)) - d, F.lit(0.0)) / F.col("types") + (d * (F.col("v") - 1) / F.col("types")) / F.col("v")
    upper = F.when(F.col("total").isNull(), lower).otherwise((F.greatest(c - d, F.lit(0.0)) + d * F.col("kinds") * lower) / F.col("total"))
    return x.select(key, "k", F.log(upper).alias("lp"))


def perplexity(log_probabilities: DataFrame, key: str = "doc_id") -> DataFrame:
    """key, n_tokens, ppl = exp(-mean log-probability)."""
    return log_probabilities.groupBy(key).agg(F.sum("k").alias("n_tokens"), F.exp(-F.sum(F.col("k") * F.col("lp")) / F.sum("k")).alias("ppl"))


def add_k_perplexity(train: DataFrame, docs: DataFrame, k: float = 0.1, key: str = "doc_id") -> DataFrame:
    """Unigram model with k added to every count, one slot for unknown words."""
    uni = train.select(F.explode(F.concat(_tokens(F.col("text")), F.array(F.lit(END)))).alias("w")).groupBy("w").agg(F.count("*").alias("c"))
    tot = uni.agg(F.sum("c").alias("total"), (F.count("*") + 1).alias("v"))
    g = docs.select(key, F.explode(F.concat(_tokens(F.col("text")), F.array(F.lit(END)))).alias("w")).groupBy(key, "w").agg(F.count("*").alias("k"))
    p = (F.coalesce(F.col("c"), F.lit(0)) + k) / (F.col("total") + k * F.col("v"))
    return perplexity(g.join(uni, "w", "left").crossJoin(F.broadcast(tot)).select(key, "k", F.log(p).alias("lp")), key)


def backoff_perplexity(train: DataFrame, docs: DataFrame, factor: float = 0.4, key: str = "doc_id") -> DataFrame:
    """Back-off without normalisation: the relative frequency of the bigram, else factor times that of the word, with one
    added to each word's count so that an unknown word has a score. exp(-mean log score) ranks texts; it is no probability."""
    bi = counts(train, 2)
    ctx = bi.groupBy("ctx").agg(F.sum("c").alias("total"))
    uni = bi.groupBy("w").agg(F.sum("c").alias("uc"))
    whole = uni.agg((F.sum("uc") + F.count("*") + 1).alias("whole"))
    g = ngrams(docs, 2, key=key).groupBy(key, "ctx", "w").agg(F.count("*").alias("k"))
    x = g.join(bi, ["ctx", "w"], "left").join(ctx, "ctx", "left").join(uni, "w", "left").crossJoin(F.broadcast(whole))
    s = F.when(F.col("c").isNotNull(), F.col("c") / F.col("total")).otherwise(factor * (F.coalesce("uc", F.lit(0)) + 1) / F.col("whole"))
    return perplexity(x.select(key, "k", F.log(s).alias("lp")), key)


#: Word hashes of the marks and of words that a model doesn't know: words are hashed as they are, and no word holds the marks' characters.
_MARKS = tuple(_mix(np.array([k], np.uint64))[0] for k in (1, 2, 3))
#: Predicted tokens of a packet's texts together; a longer text is alone.
_CHUNK = 1 << 21


def _packets(docs: DataFrame, order: int, parts: int, key: str, known=None, text_col: str = "text") -> DataFrame:
    """The tokens of texts, dealt to parts by the word before each: part, kind, keys, counts (tokens of each key), words, and
    for n tokens the places of the order - 1 words before and of the token itself, in width bytes each.

    Kind 0, without known: places are those in words (hashes of the packet's words), tokens are sorted, there are no keys.
    Kind 1: places are those in known (a broadcast of hashes), 0 if a word or one nearer to the token isn't there.
    """
    tokens = docs.select(F.col(key).alias("key"), F.transform(_tokens(F.col(text_col)), lambda t: F.xxhash64(t)).alias("h"))
    starts, kind = max(1, order - 1), int(known is not None)

    def packets(keys: pa.Array, h: np.ndarray, size: np.ndarray, table: tuple | None) -> Iterator[pa.RecordBatch]:
        whole = size + starts + 1
        first = np.cumsum(whole) - whole
        x = np.full(whole.sum(), _MARKS[0], np.uint64)
        x[np.repeat(first + starts - (np.cumsum(size) - size), size) + np.arange(len(h))] = h
        x[first + whole - 1] = _MARKS[1]
        coded = pa.array(x).dictionary_encode()
        words, ids = coded.dictionary.to_numpy(), coded.indices.to_numpy()
        if kind:
            i, there = _find(table[0], words)
            place, words = np.where(there, table[1][i], 0).astype(np.uint32), table[2]
        else:
            rank = np.argsort(-np.bincount(ids), kind="stable")
            place, words = np.empty(len(rank), np.uint32), words[rank]
            place[rank] = np.arange(len(rank), dtype=np.uint32)
        ids = place[ids]
        owner, at = np.repeat(np.arange(len(size), dtype=np.int32), size + 1), np.repeat(first + starts - (np.cumsum(size + 1) - size - 1), size + 1) + np.arange(len(h) + len(size))
        before = ids[at - (order > 1)]
        part = ((_mix(words) >> np.uint64(32)) % np.uint64(parts)).astype(np.int32)[before]  # other bits than those that tell words of a part apart
        if kind:
            part = np.where(before == 0, owner % parts, part)  # nothing is known of them but the token itself
        by = np.argsort(part.astype(np.uint16) if parts < 1 << 16 else part, kind="stable")
        ends = np.searchsorted(part[by], np.arange(parts + 1))
        for p in np.flatnonzero(np.diff(ends)):
            mine = by[ends[p] : ends[p + 1]]
            grams = np.stack([ids[at[mine] - k] for k in range(order - 1, -1, -1)])
            if kind:
                for k in range(order - 3, -1, -1):
                    grams[k][grams[k + 1] == 0] = 0
                own, n = np.unique(owner[mine], return_counts=True)
                keyed, n, mentioned = keys.take(pa.array(own)), pa.array(n.astype(np.int32)), b""
                width = 2 if len(words) <= 1 << 16 else 4
            else:
                there = np.zeros(len(words), bool)
                there[grams.ravel()] = True
                grams = (np.cumsum(there, dtype=np.uint32) - np.uint32(1))[grams]
                grams = grams[:, np.lexsort((grams[-1], *grams[:-1]))]
                keyed, n, mentioned = keys.slice(0, 0), pa.array([], pa.int32()), words[there].tobytes()
                width = 2 if there.sum() <= 1 << 16 else 4
            raw = np.ascontiguousarray(np.ascontiguousarray(grams, f"<u{width}").view(np.uint8).reshape(order, -1, width).transpose(0, 2, 1))
            lists = [pa.ListArray.from_arrays(pa.array([0, len(v)], pa.int32()), v) for v in (keyed, n)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([p], pa.int32()), pa.array([kind], pa.int32()), *lists, pa.array([mentioned], pa.binary()), pa.array([len(mine)], pa.int64()), pa.array([width], pa.int32()), pa.array([pa.compress(raw, "zstd", asbytes=True)], pa.binary())],
                ["part", "kind", "keys", "counts", "words", "n", "width", "ids"],
            )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = None
        if kind:
            by = np.argsort(known.value[0])
            table = known.value[0][by], by, known.value[0]
        for batch in batches:
            size = pc.list_value_length(batch.column(1)).to_numpy(zero_copy_only=False).astype(np.int64)
            h, end = batch.column(1).flatten().to_numpy(zero_copy_only=False).view(np.uint64), np.cumsum(size)
            a = 0
            while a < len(size):
                b = max(a + 1, int(np.searchsorted(end, end[a] - size[a] + _CHUNK, "right")))
                yield from packets(batch.column(0).slice(a, b - a), h[end[a] - size[a] : end[b - 1]], size[a:b], table)
                a = b

    return tokens.mapInArrow(run, f"part int, kind int, keys array<{tokens.schema['key'].dataType.simpleString()}>, counts array<int>, words binary, n long, width int, ids binary")


def _opened(row: dict, order: int) -> np.ndarray:
    """Places of a packet's tokens: order rows, the token's own last."""
    raw = np.frombuffer(pa.decompress(row["ids"], order * row["n"] * row["width"], "zstd"), np.uint8).reshape(order, row["width"], -1)
    return np.ascontiguousarray(raw.transpose(0, 2, 1)).view(f"<u{row['width']}")[:, :, 0]


def _by_part(packets: DataFrame, parts: int, tables, out, schema: str) -> DataFrame:
    """out(model of a part, row) for every packet of kind 1, where tables(training packets of that part) is its model; without
    out, tables' own rows. A task has a part's training packets at once, and then the others one by one."""
    dealt = packets.repartition(parts, "part").sortWithinPartitions("part", "kind")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, learn, model = None, [], None
        for batch in batches:
            for i in range(len(batch)):
                row = {name: batch.column(k)[i].as_py() if name not in ("keys", "counts") else batch.column(k)[i].values for k, name in enumerate(batch.schema.names)}
                if row["part"] != part:
                    if out is None and learn:
                        yield tables(learn)
                    part, learn, model = row["part"], [], None
                if row["kind"] == 0:
                    learn.append(row)
                elif out is not None:
                    model, learn = model if model is not None else tables(learn), []
                    yield out(model, row)
        if out is None and learn:
            yield tables(learn)

    return dealt.mapInArrow(run, schema)


def _chains(x: np.ndarray) -> tuple[dict[int, np.ndarray], dict[int, np.ndarray]]:
    """64-bit names of the contexts of n - 1 words, and of the n-grams, by n from 2."""
    contexts, grams, c = {}, {}, np.array([_GOLD], np.uint64)
    for n in range(2, len(x) + 1):
        c = _mix(c * _STEP + x[-n])
        contexts[n], grams[n] = c, _mix((c ^ np.uint64(_GOLD)) * _STEP + x[-1])
    return contexts, grams


def _find(table: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in a sorted table, and whether what was asked for is there."""
    if not len(table):
        return np.zeros(len(asked), np.int64), np.zeros(len(asked), bool)
    at = np.searchsorted(table, asked)
    at[at == len(table)] = 0
    return at, table[at] == asked


class ModifiedKneserNey:
    """Modified Kneser-Ney of any order.

    The highest order uses counts, lower ones the number of different words before (counts where the context starts the
    text, since nothing stands before it); discounts for counts of 1, 2 and 3 or more come from the counts of counts (0.75
    where those are missing or would give none). Probabilities are interpolated, so that scoring takes the longest n-gram that is there and the
    back-off weights of the contexts that aren't.

    All n-grams and contexts that a token may need, of every order above one, end with the word before it. So tokens of
    training and scored texts are dealt by that word, once and not once for each order, and a task makes the tables of its
    words by itself. What goes through a shuffle are places in lists of words, packed by part; words and n-grams are told
    apart by 64-bit hashes. The words' hashes and own
    probabilities (order one) are broadcast, 16 bytes for each word of the training texts, and scored texts name words by
    their places there.
    """

    def __init__(self, docs: DataFrame, order: int = 3, prune: tuple[int, ...] = ()):
        spark = docs.sparkSession
        self.order, self.parts = order, int(spark.conf.get("spark.sql.shuffle.partitions"))
        least = {n: k for n, k in enumerate(prune, 1) if 1 < n <= order}

        def numbers(learn: list[dict]) -> pa.RecordBatch:
            """n, w, c: for n = 1 each word's count in this part, for others the n-grams with counts of w = 1, 2, 3 and 4."""
            tables = _counted(learn, order, least)
            rows = [(1, *tables[1]), *((n, np.arange(1, 5).astype(np.uint64), np.array([(t["c"] == k).sum() for k in (1, 2, 3, 4)])) for n, t in tables.items() if n > 1)]
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(v)) for v in ([np.full(len(r[1]), r[0], np.int32) for r in rows], [r[1].view(np.int64) for r in rows], [r[2].astype(np.int64) for r in rows])], ["n", "w", "c"])

        self.learn = _stored(_packets(docs.select(F.lit(None).cast("long").alias("key"), "text"), order, self.parts, "key"))
        got = _by_part(self.learn, self.parts, numbers, None, "n int, w long, c long").groupBy("n", "w").agg(F.sum("c").alias("c")).toArrow()
        n, w, c = (got.column(k).to_numpy() for k in range(3))
        found = {k: dict(zip(w[n == k].tolist(), c[n == k].tolist())) for k in range(2, order + 1)}
        w, c = w[n == 1].view(np.uint64), c[n == 1]
        discounts = {k: self._discounts([found[k].get(i, 0) for i in (1, 2, 3, 4)]) for k in found} | {1: self._discounts([int((c == i).sum()) for i in (1, 2, 3, 4)])}
        cut = _cut(c, discounts[1])
        self.unknown = float(cut.sum() / c.sum()) / (len(w) + 1) if len(w) else 1.0
        by = np.argsort(-c, kind="stable")  # frequent words have low places, which pack well
        p = np.maximum(c - cut, 0.0) / max(1, c.sum()) + self.unknown
        self.words = spark.sparkContext.broadcast((np.concatenate([[_MARKS[2], _MARKS[0]], w[by]]).astype(np.uint64), np.concatenate([[self.unknown] * 2, p[by]])))
        self.discounts, self.least = discounts, least

    @staticmethod
    def _discounts(n: list[int]) -> list[float]:
        """Of the numbers of n-grams with counts of 1, 2, 3 and 4."""
        if not all(n[:3]):
            return [0.75] * 3
        y = n[0] / (n[0] + 2 * n[1])
        of = [min(k - (k + 1) * y * n[k] / n[k - 1], k) if n[k] else 0.75 for k in (1, 2, 3)]
        return [d if d > 0 else 0.75 for d in of]  # without a discount a context would leave nothing to words it was not seen with

    def log_probabilities(self, docs: DataFrame, key: str = "doc_id") -> DataFrame:
        """key, k, lp: mean natural log-probability of k predicted tokens of the key; a key has a row for each part that has some."""
        order, words, unknown, discounts, least = self.order, self.words, self.unknown, self.discounts, self.least

        def tables(learn: list[dict]) -> dict:
            model = {}
            for n, t in sorted(_counted(learn, order, least).items()):
                if n > 1:
                    contexts, at = np.unique(t["context"], return_inverse=True)
                    cut = _cut(t["c"], discounts[n])
                    total = np.bincount(at, t["c"], len(contexts))
                    bow = np.bincount(at, cut, len(contexts)) / total
                    if n == 2:
                        by = np.argsort(words.value[0])
                        low = words.value[1][by[_find(words.value[0][by], t["w"])[0]]]
                    else:
                        i, there = _find(model[n - 1][0], t["shorter"])
                        low = np.where(there, model[n - 1][1][i], unknown) if len(model[n - 1][1]) else np.full(len(i), unknown)
                    model[n] = t["name"], np.maximum(t["c"] - cut, 0.0) / total[at] + bow[at] * low, contexts, bow
            return model

        def score(model: dict, row: dict) -> pa.RecordBatch:
            places = _opened(row, order)
            contexts, grams = _chains(words.value[0][places])
            p, at, inside = words.value[1][places[-1]], np.arange(row["n"]), np.arange(row["n"])  # tokens whose shorter n-gram, whose shorter context is known
            for n in range(2, order + 1):
                names, known, before, bow = model[n]
                i, there = _find(names, grams[n][at])
                j, back = _find(before, contexts[n][inside])
                left = inside[back]
                p[left] *= bow[j[back]]
                hit = at[there]
                p[hit] = known[i[there]]
                if not least:  # a longer n-gram or context is only there if the shorter one is
                    at, inside = hit, left
            n = row["counts"].to_numpy(zero_copy_only=False).astype(np.int64)
            lp = np.add.reduceat(np.log(p), np.cumsum(n) - n) / n
            return pa.RecordBatch.from_arrays([row["keys"], pa.array(n), pa.array(lp)], [key, "k", "lp"])

        asked = _packets(docs, order, self.parts, key, words)
        learn = self.learn.withColumn("keys", F.array().cast(asked.schema["keys"].dataType))
        return _by_part(learn.unionByName(asked), self.parts, tables, score, f"{key} {docs.schema[key].dataType.simpleString()}, k long, lp double")


def _cut(c: np.ndarray, d: list[float]) -> np.ndarray:
    return np.array([0.0, *d])[np.minimum(c, 3)]


def _counted(learn: list[dict], order: int, least: dict[int, int]) -> dict:
    """By n: sorted names of the n-grams of a part, their counts, contexts, shorter n-grams and words; for n = 1 words and counts."""
    x = np.concatenate([np.empty((order, 0), np.uint64), *(np.frombuffer(r["words"], np.uint64)[_opened(r, order)] for r in learn)], axis=1)
    contexts, grams = _chains(x)
    out, of, occurs = {}, np.arange(x.shape[1]), np.ones(x.shape[1], np.int64)  # of: a token for each (n + 1)-gram, occurs: how often it is there
    for n in range(order, 1, -1):
        names, first, at = np.unique(grams[n][of], return_index=True, return_inverse=True)
        c, occurs = np.bincount(at, minlength=len(names)), np.bincount(at, occurs, len(names)).astype(np.int64)
        of = of[first]
        if n < order:
            c = np.where(x[-n][of] == _MARKS[0], occurs, c)
        on = c > least.get(n, 0)
        out[n] = {"name": names[on], "c": c[on], "context": contexts[n][of[on]], "shorter": grams[n - 1][of[on]] if n > 2 else None, "w": x[-1][of[on]]}
    w, c = np.unique(x[-1][of], return_counts=True)
    return out | {1: (w, c)}
