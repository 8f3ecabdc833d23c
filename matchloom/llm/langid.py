"""Language identification: a linear-chain conditional random field over words.

Features of a word: its n-grams, of which those that hold a border mark are its affixes, and
itself as an entry of a hashed lexicon. Transition weights are learned with them, on word
sequences glued from texts of several languages, so a text that switches between languages
is labelled word by word. Forward-backward runs for all texts of a batch at once: long texts
are cut into segments whose transfer matrices are chained, which gives the same marginals as
one pass along the whole text. The language of a text is the label with the largest sum of
word marginals, its score that label's share.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .subwords import WordBatch
from .textkernels import byte_chunks, tidy, utf8_view

ORDERS = (3, 4)
BITS = 16
SEGMENT = 128
RESCALE = 4
CHUNK_BYTES = 1 << 20
UNKNOWN = "und"
DOCS_PER_LANG = 600
SAMPLE_CHARS = 2000
SEQUENCE = 48
LETTERISH = re.compile(r"[^\W\d_]+")


def has_letter(text: str | None) -> bool:
    return text is not None and any(m.group().isalpha() or any(map(str.isalpha, m.group())) for m in LETTERISH.finditer(text))


class ChainModel:
    def __init__(self, labels: list[str], table: np.ndarray, lexicon: np.ndarray, start: np.ndarray, moves: np.ndarray):
        self.labels, self.table, self.lexicon, self.start, self.moves = labels, table, lexicon, start, moves

    def emissions(self, batch: WordBatch) -> np.ndarray:
        """Score of each label for each word: mean over its n-grams plus its lexicon entry."""
        if not len(batch.starts):
            return np.zeros((0, len(self.labels)))
        values = np.zeros((len(batch.data), len(self.labels)), np.float32)
        counts = np.zeros(len(batch.starts))
        for n in ORDERS:
            h, ok = batch.grams(n, BITS)
            h[~ok] = 1 << BITS  # the last row of the table stays zero
            values[: len(h)] += self.table.take(h, axis=0)
            counts += np.maximum(batch.ends - batch.starts + 3 - n, 0)
        sums = np.add.reduceat(values, batch.starts - 1, axis=0).astype(np.float64)
        return sums / np.maximum(counts, 1)[:, None] + self.lexicon[batch.word_keys(BITS)]

    def marginals(self, emissions: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Label probabilities of each word; ``first`` has the offsets of the texts."""
        return chain_marginals(emissions, first, self.start, self.moves)

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        batch = WordBatch(texts)
        sizes = np.diff(batch.first)
        shares = np.zeros((len(texts), max(len(self.labels), 1)))
        if len(self.labels) and len(batch.starts):
            full = np.flatnonzero(sizes)
            p = self.marginals(self.emissions(batch), batch.first)
            shares[full] = np.add.reduceat(p, batch.first[full], axis=0) / sizes[full][:, None]
        best = shares.argmax(axis=1)
        ok = np.array([has_letter(t) for t in texts], bool) & (sizes > 0) & bool(self.labels)
        names = [self.labels[b] if k else UNKNOWN for b, k in zip(best, ok)]
        return names, np.where(ok, np.clip(shares[np.arange(len(texts)), best], 0.0, 1.0), 0.0) if len(texts) else np.zeros(0)


def chain_marginals(emissions: np.ndarray, first: np.ndarray, start: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """Exact forward-backward for all chains at once, in segments of SEGMENT words."""
    n, k = emissions.shape
    potential = np.exp(emissions - emissions.max(axis=1, keepdims=True))
    step = np.exp(moves)
    sizes = np.diff(first)
    pieces = -(-sizes // SEGMENT)
    chain = np.repeat(np.arange(len(sizes)), pieces)
    order_in = np.arange(len(chain)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    begin = first[chain] + order_in * SEGMENT
    length = np.minimum(SEGMENT, first[chain + 1] - begin)
    by_size = np.argsort(-length, kind="stable")
    begin, length = begin[by_size], length[by_size]
    back = np.empty_like(by_size)
    back[by_size] = np.arange(len(by_size))
    active = [int(np.searchsorted(-length, -t, side="left")) for t in range(SEGMENT + 1)]  # segments longer than t

    # label-major blocks of one step of all segments: [step, label, segment]
    place = begin[None, :] + np.minimum(np.arange(SEGMENT)[:, None], length[None, :] - 1)
    block = np.ascontiguousarray(potential[place].transpose(0, 2, 1))
    into = np.ascontiguousarray(step.T)
    span = int(length.max(initial=0))

    def level(x, axes, t):
        if t % RESCALE == RESCALE - 1:  # between rescalings values stay far from underflow
            x /= x.sum(axis=axes, keepdims=True)

    # transfer of each segment that has a successor: label before it, its last label
    chained = np.flatnonzero(length == SEGMENT)
    transfer = np.zeros((k, k, len(chained)))
    transfer[np.arange(k), np.arange(k)] = 1
    if int(pieces.max(initial=0)) > 1:
        for t in range(SEGMENT):
            transfer = np.matmul(into, transfer)
            transfer *= block[t][None, :, : len(chained)]
            level(transfer, (0, 1), t)
    heads = order_in[by_size] == 0
    entry, exit_ = np.ones((k, len(begin))), np.ones((k, len(begin)))
    starts = np.cumsum(pieces) - pieces
    for j in range(1, int(pieces.max(initial=0))):
        own = np.flatnonzero(pieces > j)
        prev, here = back[starts[own] + j - 1], back[starts[own] + j]
        if j == 1:
            x = np.exp(start)[:, None] * block[0][:, prev]
            for t in range(1, SEGMENT):
                x = (into @ x) * block[t][:, prev]
                level(x, 0, t)
        else:
            x = np.einsum("in,ijn->jn", entry[:, prev], transfer[:, :, prev])
        entry[:, here] = x / x.sum(axis=0)
    for j in range(int(pieces.max(initial=0)) - 2, -1, -1):
        own = np.flatnonzero(pieces > j + 1)
        here, nxt = back[starts[own] + j], back[starts[own] + j + 1]
        full = length[nxt] == SEGMENT
        x = np.ones((k, len(own)))
        x[:, full] = np.einsum("ijn,jn->in", transfer[:, :, nxt[full]], exit_[:, nxt[full]])
        x[:, ~full] = _tail(block[:, :, nxt[~full]], length[nxt[~full]], step)
        exit_[:, here] = x / x.sum(axis=0)
    alpha = block.copy()
    state = entry
    for t in range(span):
        a = active[t]
        moved = into @ state[:, :a]
        if t == 0:
            moved[:, heads[:a]] = np.exp(start)[:, None]
        alpha[t, :, :a] *= moved
        state = alpha[t, :, :a]
        level(state, 0, t)
    beta = exit_
    for t in range(span - 1, -1, -1):
        a = active[t]
        alpha[t, :, :a] *= beta[:, :a]
        beta[:, :a] = step @ (block[t, :, :a] * beta[:, :a])
        level(beta, 0, t)
    alpha /= alpha.sum(axis=1, keepdims=True)
    out = np.empty((n, k))
    live = np.arange(SEGMENT)[:, None] < length[None, :]
    out[place[live]] = alpha.transpose(0, 2, 1)[live]
    return out


def _tail(block: np.ndarray, length: np.ndarray, step: np.ndarray) -> np.ndarray:
    """Backward message of last segments, which may be short."""
    x = np.ones(block.shape[1:])
    for t in range(int(length.max(initial=0)) - 1, -1, -1):
        on = length > t
        x[:, on] = step @ (block[t][:, on] * x[:, on])
        if t % RESCALE == 0:
            x /= x.sum(axis=0)
    return x


def fit(texts: list[str], langs: list[str], seed: int = 3, epochs: int = 3) -> ChainModel:
    """Adagrad on the conditional likelihood of sequences of SEQUENCE words, half of them
    glued from pieces of texts in different languages."""
    rng = np.random.default_rng(seed)
    labels = sorted(set(langs))
    k = len(labels)
    table, lexicon = np.zeros(((1 << BITS) + 1, k), np.float32), np.zeros((1 << BITS, k), np.float32)
    start, moves = np.zeros(k), np.zeros((k, k))
    model = ChainModel(labels, table, lexicon, start, moves)
    if k < 2:
        return model
    code = {x: i for i, x in enumerate(labels)}
    words = [(t.split(), code[g]) for t, g in zip(texts, langs) if t and t.split()]
    by_lang = [[w for w, g in words if g == i] for i in range(k)]
    live = [i for i in range(k) if by_lang[i]]
    sums = [np.full(x.shape, 1e-6) for x in (table, lexicon, start, moves)]
    rounds = epochs * max(1, len(words) // 64)
    for _ in range(rounds):
        rows, gold = [], []
        for _ in range(64):
            parts = 1 if rng.random() < 0.5 else int(rng.integers(2, 4))
            row, marks = [], []
            for _ in range(parts):
                g = live[int(rng.integers(len(live)))]
                source = by_lang[g][int(rng.integers(len(by_lang[g])))]
                need = SEQUENCE // parts
                at = int(rng.integers(max(1, len(source) - need + 1)))
                row += source[at : at + need]
                marks += [g] * len(source[at : at + need])
            rows.append(" ".join(row))
            gold += marks
        batch, gold = WordBatch(rows), np.array(gold)
        if len(batch.starts) != len(gold):
            continue
        p = model.marginals(model.emissions(batch), batch.first)
        pair_gold, pair_model = _pair_sums(model, batch, gold)
        slope = p.copy()
        slope[np.arange(len(gold)), gold] -= 1
        slope /= 64
        heads = batch.first[:-1][np.diff(batch.first) > 0]
        buckets, word = batch.word_grams(ORDERS, BITS)
        per = np.bincount(word, minlength=len(gold))
        used, at = np.unique(buckets, return_inverse=True)
        share = slope[word] / np.maximum(per, 1)[word][:, None]
        grads = [(table, sums[0], used, np.stack([np.bincount(at, share[:, j], len(used)) for j in range(k)], axis=1))]
        used, at = np.unique(batch.word_keys(BITS), return_inverse=True)
        grads.append((lexicon, sums[1], used, np.stack([np.bincount(at, slope[:, j], len(used)) for j in range(k)], axis=1)))
        grads.append((start, sums[2], slice(None), slope[heads].sum(axis=0)))
        grads.append((moves, sums[3], slice(None), (pair_model - pair_gold) / 64))
        for weight, total, where, g in grads:
            total[where] += g**2
            weight[where] -= 0.5 * g / np.sqrt(total[where])
    return model


def _pair_sums(model: ChainModel, batch: WordBatch, gold: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Label pairs of neighbouring words: as marked, and as expected by the model."""
    k = len(model.labels)
    inner = np.ones(len(gold), bool)
    inner[batch.first[:-1][np.diff(batch.first) > 0]] = False
    at = np.flatnonzero(inner)
    marked = np.bincount(gold[at - 1] * k + gold[at], minlength=k * k).reshape(k, k).astype(float)
    # expected pairs: forward and backward messages once more, sequences side by side
    emissions = model.emissions(batch)
    potential, step = np.exp(emissions - emissions.max(axis=1, keepdims=True)), np.exp(model.moves)
    sizes, expected = np.diff(batch.first), np.zeros((k, k))
    longest = int(sizes.max(initial=0))
    first = batch.first[:-1]
    alpha = np.zeros((longest, len(sizes), k))
    for t in range(longest):
        on = sizes > t
        x = potential[first[on] + t] * (np.exp(model.start) if t == 0 else alpha[t - 1, on] @ step)
        alpha[t, on] = x / x.sum(axis=1, keepdims=True)
    beta = np.ones((len(sizes), k))
    for t in range(longest - 1, 0, -1):
        on = np.flatnonzero(sizes > t)
        tail = potential[first[on] + t] * beta[on]
        pair = alpha[t - 1, on][:, :, None] * step[None] * tail[:, None, :]
        expected += (pair / pair.sum(axis=(1, 2), keepdims=True)).sum(axis=0)
        x = tail @ step.T
        beta[on] = x / x.sum(axis=1, keepdims=True)
    return marked, expected


def training_sample(docs: DataFrame, learn: Column, per_lang: int) -> tuple[list[str], list[str]]:
    """About ``per_lang`` labelled rows of each language by a hash of the id; of long rows a
    window of SAMPLE_CHARS characters at a place that the hash picks."""
    usable = docs.where(learn & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", "lang", "text")
    sizes = {r["lang"]: r["count"] for r in usable.groupBy("lang").count().collect()}
    if not sizes:
        return [], []
    share = F.element_at(F.create_map(*[F.lit(x) for g, n in sizes.items() for x in (g, per_lang / n)]), F.col("lang"))
    h = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30))
    place = F.pmod(F.xxhash64("doc_id", F.lit(1)), F.greatest(F.length("text") - SAMPLE_CHARS, F.lit(1))).cast("int") + 1
    rows = usable.where(h < share * (1 << 30)).select("doc_id", "lang", F.substring("text", place, F.lit(SAMPLE_CHARS)).alias("text")).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["lang"], r["text"]))
    return [r["text"] for r in rows], [r["lang"] for r in rows]


def train(docs: DataFrame, learn: Column, per_lang: int = DOCS_PER_LANG) -> ChainModel:
    return fit(*training_sample(docs, learn, per_lang))


def predict_documents(docs: DataFrame, model: ChainModel, keep: list[str] | None = None, names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The columns ``keep`` (default doc_id), the predicted language and its score; one row per input row.

    Null texts and texts without a letter are ``und`` with score 0. Repeated rows repeat, extra
    columns are ignored, an empty table gives an empty result. Without any labelled row every
    text is ``und``.
    """
    keep = keep or ["doc_id"]
    at = keep.index("text") if "text" in keep else len(keep)
    shared = docs.sparkSession.sparkContext.broadcast((model.labels, model.table, model.lexicon, model.start, model.moves))
    chosen = docs.select(*[docs[c] for c in keep], *[docs["text"].alias("_read_text")] * (at == len(keep)))
    kinds = dict(chosen.dtypes)

    def run(batches):
        model = ChainModel(*shared.value)
        for batch in batches:
            column = batch.column(at)
            _, offsets = utf8_view(column)
            for lo, hi in byte_chunks(offsets, CHUNK_BYTES):
                labels, scores = model.predict(column.slice(lo, hi - lo).to_pylist())
                cols = [batch.column(i).slice(lo, hi - lo) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(labels, pa.string()), pa.array(scores)], names=[*keep, *names])

    return chosen.mapInArrow(tidy(run), ", ".join([*(f"`{c}` {kinds[c]}" for c in keep), f"{names[0]} string, {names[1]} double"]))
