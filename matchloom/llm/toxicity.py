"""Toxicity: averaged subword embeddings under a linear softmax, trained jointly in numpy.

A text is toxic where a few words of it are, so the bag is a short window of words: training
starts with whole texts, then keeps, for each text, the window that the model finds worst
(of toxic texts the evidence, of clean texts the hardest counter-example). The score of a
text is the calibrated score of its worst window. Misspellings share most of their n-grams
with known spellings, so they need no entry of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .subwords import WordBatch
from .textkernels import byte_chunks, tidy, utf8_view

ORDERS = (3, 4, 5)
BITS = 18
DIM = 8
WINDOW = 4
THRESHOLD = 0.7
SAMPLE_PER_CLASS = 2500
WHOLE_PER_CLASS = 800
SAMPLE_CHARS = 32_768
CHUNK_BYTES = 1 << 20


class ToxicityModel:
    """Scalar weight of each bucket (its embedding along the softmax's difference): n-grams in
    the first half, whole words in the second."""

    def __init__(self, weights: np.ndarray, bias: float, scale: float, shift: float):
        self.weights, self.bias, self.scale, self.shift = weights, bias, scale, shift

    def window_logits(self, batch: WordBatch) -> np.ndarray:
        """Logit of the window that begins at each word; windows stop at the end of the text."""
        values = np.zeros(len(batch.data), np.float32)
        counts = np.zeros(len(batch.data), np.float32)
        for n in ORDERS:
            h, ok = batch.grams(n, BITS)
            values[: len(h)] += self.weights[h] * ok
            counts[: len(h)] += ok
        value = batch.word_sums(values) + self.weights[(1 << BITS) + batch.word_keys(BITS)]
        count = batch.word_sums(counts) + 1
        run_v, run_c = np.concatenate([[0.0], np.cumsum(value)]), np.concatenate([[0.0], np.cumsum(count)])
        at = np.arange(len(value))
        text = np.repeat(np.arange(len(batch.first) - 1), np.diff(batch.first))
        to = np.minimum(at + WINDOW, batch.first[text + 1]) if len(at) else at
        return (run_v[to] - run_v[at]) / np.maximum(run_c[to] - run_c[at], 1) + self.bias

    def worst(self, batch: WordBatch) -> tuple[np.ndarray, np.ndarray]:
        """Of each text the greatest window logit and its word (the bias and -1 if it has none)."""
        logits = self.window_logits(batch)
        best, where = np.full(len(batch.first) - 1, self.bias), np.full(len(batch.first) - 1, -1)
        full = np.flatnonzero(np.diff(batch.first))
        if len(full):
            best[full] = np.maximum.reduceat(logits, batch.first[full])
            text = np.repeat(np.arange(len(best)), np.diff(batch.first))
            top = np.flatnonzero(logits == best[text])
            where[text[top[::-1]]] = top[::-1]
        return best, where

    def worst_logits(self, batch: WordBatch) -> np.ndarray:
        logits = self.window_logits(batch)
        best, full = np.full(len(batch.first) - 1, self.bias), np.flatnonzero(np.diff(batch.first))
        if len(full):
            best[full] = np.maximum.reduceat(logits, batch.first[full])
        return best

    def scores(self, texts: list[str | None]) -> np.ndarray:
        z = self.scale * self.worst_logits(WordBatch(texts)) + self.shift
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def _bags(batch: WordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all n-grams and whole words, and the text of each, in order of the texts."""
    buckets, word = batch.word_grams(ORDERS, BITS)
    keys = batch.word_keys(BITS).astype(np.int64) + (1 << BITS)
    buckets, word = np.concatenate([buckets, keys]), np.concatenate([word, np.arange(len(keys))])
    owner = (np.searchsorted(batch.first, word, side="right") - 1).astype(np.int32)
    order = np.argsort(owner, kind="stable")
    return buckets[order], owner[order]


def _epoch(rng, table, out, sums, bags, labels, rate):
    """One pass of Adagrad over bags = (buckets, bag of each bucket); labels by bag."""
    buckets, owner = bags
    order = rng.permutation(len(labels))
    starts = np.searchsorted(owner, np.arange(len(labels) + 1))
    for lo in range(0, len(order), 64):
        pick = order[lo : lo + 64]
        spans = [buckets[starts[k] : starts[k + 1]] for k in pick]
        sizes = np.array([len(s) for s in spans])
        if not sizes.sum():
            continue
        idx, seg = np.concatenate(spans), np.repeat(np.arange(len(pick)), sizes)
        mean = np.stack([np.bincount(seg, table[idx, d], len(pick)) for d in range(DIM)], axis=1) / np.maximum(sizes, 1)[:, None]
        logits = mean @ out[:DIM] + out[DIM]
        soft = np.exp(logits - logits.max(axis=1, keepdims=True))
        soft /= soft.sum(axis=1, keepdims=True)
        soft[np.arange(len(pick)), labels[pick]] -= 1
        share = np.where(labels[pick] == 1, 0.5 / max(labels.mean(), 1e-6), 0.5 / max(1 - labels.mean(), 1e-6))[:, None]
        soft *= share / len(pick)
        g_mean = soft @ out[:DIM].T / np.maximum(sizes, 1)[:, None]
        g_out = np.vstack([mean.T @ soft, soft.sum(axis=0)])
        used, at = np.unique(idx, return_inverse=True)
        g_table = np.stack([np.bincount(at, g_mean[seg, d], len(used)) for d in range(DIM)], axis=1)
        sums[0][used] += (g_table**2).mean(axis=1)
        table[used] -= rate * g_table / np.sqrt(sums[0][used] + 1e-10)[:, None]
        sums[1] += g_out**2
        out -= rate * g_out / np.sqrt(sums[1] + 1e-10)


def _fold(table, out) -> tuple[np.ndarray, float]:
    side = out[:, 1] - out[:, 0]
    return (table @ side[:DIM]).astype(np.float32), float(side[DIM])


def fit(texts: list[str], labels: list[int], seed: int = 7, rounds: int = 10) -> ToxicityModel:
    """Train on texts held in memory: WHOLE_PER_CLASS texts of each class as whole bags, then
    ``rounds`` over the windows of all of them. With one class only, the score is that class's share."""
    rng = np.random.default_rng(seed)
    y = np.array(labels, dtype=np.int64)
    if len(y) == 0 or y.min() == y.max():
        share = float(y.mean()) if len(y) else 0.0
        return ToxicityModel(np.zeros(2 << BITS, np.float32), 0.0, 0.0, float(np.log((share + 1e-3) / (1 - share + 1e-3))))
    table = rng.normal(0, 0.05, (2 << BITS, DIM))
    out = np.vstack([rng.normal(0, 0.5, (DIM, 2)), np.zeros((1, 2))])
    sums = [np.full(2 << BITS, 1e-8), np.full((DIM + 1, 2), 1e-8)]
    groups = [range(lo, min(lo + 256, len(texts))) for lo in range(0, len(texts), 256)]
    opening = np.sort(np.concatenate([rng.permutation(np.flatnonzero(y == k))[:WHOLE_PER_CLASS] for k in (0, 1)]))
    for _ in range(2):
        mixed = rng.permutation(opening)
        for lo in range(0, len(mixed), 128):
            batch = WordBatch([texts[k] for k in mixed[lo : lo + 128]])
            _epoch(rng, table, out, sums, _bags(batch), y[mixed[lo : lo + 128]], 0.1)
    for _ in range(rounds):
        weights, bias = _fold(table, out)
        model = ToxicityModel(weights, bias, 1.0, 0.0)
        cut, marks = [], []
        for g in groups:
            batch = WordBatch([texts[k] for k in g])
            _, where = model.worst(batch)
            raw = batch.data.tobytes()
            for k, w in zip(g, where):
                t = k - g.start
                lo, hi = int(batch.first[t]), int(batch.first[t + 1])
                if w >= 0:
                    cut.append(raw[batch.starts[w] : batch.ends[min(w + WINDOW, hi) - 1]].decode())
                    marks.append(y[k])
                    if y[k] == 0:
                        w = int(rng.integers(lo, hi))
                        cut.append(raw[batch.starts[w] : batch.ends[min(w + WINDOW, hi) - 1]].decode())
                        marks.append(0)
        words = WordBatch(cut)
        bags = _bags(words)
        for _ in range(2):
            _epoch(rng, table, out, sums, bags, np.array(marks), 0.1)
    weights, bias = _fold(table, out)
    model = ToxicityModel(weights, bias, 1.0, 0.0)
    worst = np.concatenate([model.worst_logits(WordBatch([texts[k] for k in g])) for g in groups])
    model.scale, model.shift = _calibrate(worst, y)
    return model


def _calibrate(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic fit of the labels to the worst windows' logits, classes weighing the same."""
    middle, spread = float(np.median(z)), float(z.std()) or 1.0
    x = np.stack([(z - middle) / spread, np.ones(len(z))], axis=1)
    weight = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean())) / len(y)
    beta = np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-x @ beta))
        h = (x * (weight * p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        beta -= np.linalg.solve(h, x.T @ (weight * (p - y)) + 1e-3 * beta * [1, 0])
    return float(beta[0] / spread), float(beta[1] - beta[0] * middle / spread)


def training_sample(docs: DataFrame, labels: DataFrame, learn: "F.Column | None", per_class: int) -> tuple[list[str], list[int]]:
    """Up to about ``per_class`` labelled rows of each class, by a hash of the id; rows of more
    than SAMPLE_CHARS characters are not sampled. A document counts as toxic if any of its
    label rows says so."""
    marks = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    if learn is not None:
        marks = marks.where(learn)
    sizes = {r["toxic"]: r["count"] for r in marks.groupBy("toxic").count().collect()}
    share = F.coalesce(*[F.when(F.col("toxic") == k, F.lit(per_class / n)) for k, n in sizes.items()], F.lit(0.0))
    ids = marks.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share * (1 << 30))
    rows = (
        docs.select(F.col("doc_id"), F.col("text").alias("_text")).where(F.length("_text") <= SAMPLE_CHARS)
        .join(F.broadcast(ids), "doc_id").select("doc_id", "toxic", "_text").collect()
    )
    rows.sort(key=lambda r: (r["doc_id"], r["_text"]))
    return [r["_text"] for r in rows], [int(r["toxic"]) for r in rows]


def train(docs: DataFrame, labels: DataFrame, learn=None, per_class: int = SAMPLE_PER_CLASS) -> ToxicityModel:
    return fit(*training_sample(docs, labels, learn, per_class))


def score_documents(docs: DataFrame, model: ToxicityModel, keep: list[str] | None = None, score_col: str = "score") -> DataFrame:
    """The columns ``keep`` (default doc_id) and ``score_col``, one row per input row, whole texts.

    Null, empty and blank texts get the score of an empty bag. Repeated rows repeat, extra
    columns are ignored, an empty table gives an empty result.
    """
    keep = keep or ["doc_id"]
    at = keep.index("text") if "text" in keep else len(keep)
    shared = docs.sparkSession.sparkContext.broadcast((model.weights, model.bias, model.scale, model.shift))
    chosen = docs.select(*[docs[c] for c in keep], *[docs["text"].alias("_scored_text")] * (at == len(keep)))
    kinds = dict(chosen.dtypes)

    def run(batches):
        model = ToxicityModel(*shared.value)
        for batch in batches:
            column = batch.column(at)
            _, offsets = utf8_view(column)
            for lo, hi in byte_chunks(offsets, CHUNK_BYTES):
                scores = model.scores(column.slice(lo, hi - lo).to_pylist())
                cols = [batch.column(i).slice(lo, hi - lo) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(scores)], names=[*keep, score_col])

    return chosen.mapInArrow(tidy(run), ", ".join([*(f"`{c}` {kinds[c]}" for c in keep), f"{score_col} double"]))
