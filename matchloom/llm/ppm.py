"""Language-model scoring by prediction by partial matching, pretrained on the corpus.

The model is a trie of byte contexts up to ORDER bytes, with method-D escapes and symbol
exclusion. Nothing of it is capped and no task ever holds it whole:

1. the rows of a task form batches by their bytes, where they lie; each batch keeps its texts as
   one blob and lists the distinct grams (history of ORDER bytes, symbol) and words that they
   hold, with their training counts;
2. a gram's key begins with the nearest byte of its history, so the grams of any context are
   neighbours in key order. The keys are cut into ranges of about equal numbers, words into
   ranges of their hashes; their number grows with the texts, so that no range depends on how
   common a context is. A range adds up the counts of all batches;
3. then it walks the contexts from longest to shortest, and answers each batch with the
   probabilities of the grams it asked for (words: with their counts);
4. each batch meets its answers and sums them along its texts.

Contexts that lie across a border of two ranges are known to both: these are the prefixes of the
keys at the border, one for each length, and a small grouped sum over all ranges gives their
counts. Lists travel as one compressed blob for each batch and range, never as one row per gram.
"""

from __future__ import annotations

from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from .storage import Scratch
from .textkernels import LOWER, byte_chunks, give_back, tidy, utf8_view

ORDER = 6
#: Two bytes that no UTF-8 text holds stand for the start and the end of a text.
START, END = 0xFE, 0xFF
BATCH_BYTES = 10 << 20
#: Text whose grams are held at once, and keys that are merged or placed at once.
CHUNK_BYTES = 1 << 19
PIECE = 1 << 17
#: Rows that Spark hands to Python at once.
ARROW_BYTES = 2 << 20
#: Text for each range of keys, and the most ranges (their borders are held in memory).
RANGE_BYTES = 4 << 20
MOST_RANGES = 1 << 20
#: Text and share of the grams that place the borders; they decide on balance, not on results.
BORDER_BYTES = 64 << 20
BORDER_SHARE = 32
END_WORD = np.uint64(0x9E3779B97F4A7C15)
GRAM, WORD, TEXT = 0, 1, 2
#: Batches that one task makes at most.
TASK_BATCHES = 1 << 24


def gram_keys(rows: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The gram at each byte and at the end of each text, its history from the nearest byte to the
    farthest, then the symbol; how many grams each text has."""
    pad = bytes([START]) * ORDER
    data = LOWER[np.frombuffer(b"".join([x for r in rows for x in (pad, r, bytes([END]))]), np.uint8)]
    sizes = np.array([len(r) + 1 for r in rows], dtype=np.int64)
    keys = np.zeros(max(len(data) - ORDER, 0), np.uint64)
    for k in (*range(ORDER - 1, -1, -1), ORDER):
        keys <<= np.uint64(8)
        keys |= data[k : len(data) - ORDER + k]
    # positions that begin in a later text's padding belong to no text
    at = np.cumsum(sizes + ORDER) - (sizes + ORDER)
    own = np.ones(len(keys), bool)
    for k in range(ORDER):
        own[at[1:] - ORDER + k] = False
    return keys[own], sizes


def word_keys(rows: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each word and of the end of each text; how many each text has."""
    import xxhash

    hashed, found, sizes = xxhash.xxh64_intdigest, [], []
    for r in rows:
        words = r.lower().split()
        found.append(np.fromiter(map(hashed, words), np.uint64, len(words)))
        found.append(np.array([END_WORD]))
        sizes.append(len(words) + 1)
    return np.concatenate(found) if found else np.zeros(0, np.uint64), np.array(sizes, np.int64)


def distinct(keys: np.ndarray) -> np.ndarray:
    """Sorted distinct keys, by sorting (np.unique hashes plain integers, which is slower)."""
    keys = np.sort(keys)
    return keys[run_starts(keys)]


def run_starts(keys: np.ndarray) -> np.ndarray:
    """Where each run of equal sorted keys begins."""
    return np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)


def pack(values: np.ndarray) -> bytes:
    return zstandard.compress(values.tobytes(), 3)


def unpack(blob: bytes, kind: type) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(blob), kind)


def pack_sorted(keys: np.ndarray) -> bytes:
    """Ascending keys as differences, byte planes apart (most high planes are zero)."""
    steps = np.diff(keys, prepend=np.uint64(0))
    return pack(np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T))


def unpack_sorted(blob: bytes) -> np.ndarray:
    planes = unpack(blob, np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.uint64).ravel(), dtype=np.uint64)


def gram_range(keys: np.ndarray, borders: np.ndarray) -> np.ndarray:
    """Number of the range of each key; range r begins at border r - 1."""
    return np.searchsorted(borders, keys, side="right")


def word_range(keys: np.ndarray, n: int) -> np.ndarray:
    """The same for hashes of words, in n equal ranges."""
    return (((keys >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)).astype(np.int64)


def context(keys: np.ndarray, length: int) -> np.ndarray:
    """The last ``length`` bytes of the history."""
    return keys >> np.uint64(8 * (ORDER - length + 1)) if length else np.zeros_like(keys)


def shorter(grams: np.ndarray) -> np.ndarray:
    """The same symbols after one byte less of history."""
    return ((grams >> np.uint64(16)) << np.uint64(8)) | (grams & np.uint64(0xFF))


class Tally:
    """Distinct keys of a batch with the count of those in training texts. Parts of like size are
    merged as they come, so that little more is held than the distinct keys."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, keys: np.ndarray, learn: np.ndarray) -> None:
        for chosen, weight in ((keys[learn], 1), (keys[~learn], 0)):
            if not len(chosen):
                continue
            chosen.sort()
            first = run_starts(chosen)
            # a batch holds far less than 2^32 bytes besides one text, and a text less than 2^31
            counts = np.diff(first, append=len(chosen)).astype(np.uint32) * np.uint32(weight)
            self.parts.append((chosen[first], counts))
            del chosen, first, counts
            while len(self.parts) > 1 and 2 * len(self.parts[-1][0]) >= len(self.parts[-2][0]):
                self.merge()

    def merge(self) -> None:
        """Merge the last two parts, PIECE keys of the longer one at a time."""
        (more, n), (keys, counts) = sorted((self.parts.pop(), self.parts.pop()), key=lambda p: len(p[0]))
        merged, sums, size = np.empty(len(keys) + len(more), np.uint64), np.empty(len(keys) + len(more), np.uint32), 0
        ends = [0, *np.searchsorted(more, keys[PIECE::PIECE]).tolist(), len(more)]
        for lo, a, b in zip(range(0, len(keys), PIECE), ends[:-1], ends[1:]):
            some = np.concatenate([keys[lo : lo + PIECE], more[a:b]])
            order = np.argsort(some, kind="stable")
            some = some[order]
            first = run_starts(some)
            to = size + len(first)
            merged[size:to] = some[first]
            sums[size:to] = np.add.reduceat(np.concatenate([counts[lo : lo + PIECE], n[a:b]])[order], first, dtype=np.uint32)
            size = to
        self.parts.append((merged[:size], sums[:size]))

    def total(self) -> tuple[np.ndarray, np.ndarray]:
        while len(self.parts) > 1:
            self.merge()
        return self.parts.pop() if self.parts else (np.zeros(0, np.uint64), np.zeros(0, np.uint32))


def text_rows(column: pa.Array) -> tuple[list[bytes], np.ndarray]:
    data, offsets = utf8_view(column)
    return [data[a:b].tobytes() for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())], offsets


ASKED = "batch long, kind int, grp long, keys binary, counts binary, texts binary"


def cut_batches(batches, batch_bytes: int):
    """Tables of about ``batch_bytes`` of text from the rows ``(doc_id, text, learned)`` of a task; a
    longer text is a table of its own."""
    held, size = [], 0
    for batch in batches:
        _, offsets = utf8_view(batch.column(1))
        for lo, hi in byte_chunks(offsets, max(1, batch_bytes // 4)):
            held.append(batch.slice(lo, hi - lo))
            size += int(offsets[hi] - offsets[lo]) + 16 * (hi - lo)
            if size >= batch_bytes:
                yield pa.Table.from_batches(held)
                held, size = [], 0
    if held:
        yield pa.Table.from_batches(held)


def pack_rows(rows: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, rows.schema) as out:
        out.write_batch(rows)
    return zstandard.compress(sink.getvalue(), 3)


def unpack_rows(blob: bytes) -> pa.Table:
    return pa.ipc.open_stream(zstandard.decompress(blob)).read_all()


def list_batches(batches, borders: np.ndarray, batch_bytes: int, first: int):
    """Of each batch its rows, in numbered blobs of about CHUNK_BYTES, and the blobs for every range.
    Batches are numbered from ``first``. The blobs of the texts, the grams and the words leave one
    after the other."""
    for batch_id, table in enumerate(cut_batches(batches, batch_bytes), first):
        pieces = (b.slice(lo, hi - lo) for b in table.to_batches() for lo, hi in byte_chunks(utf8_view(b.column(1))[1], CHUNK_BYTES))
        for number, piece in enumerate(pieces):
            yield blob_rows(batch_id, [(TEXT, number, None, None, pack_rows(piece))])
        for kind, make, ranged in ((GRAM, gram_keys, lambda k: gram_range(k, borders)), (WORD, word_keys, lambda k: word_range(k, len(borders) + 1))):
            tally = Tally()
            for text, learn in zip(table.column(1).chunks, table.column(2).chunks):
                data, offsets = utf8_view(text)
                flags = learn.to_numpy(zero_copy_only=False)
                for lo, hi in byte_chunks(offsets, CHUNK_BYTES):
                    keys, sizes = make([data[a:b].tobytes() for a, b in zip(offsets[lo:hi].tolist(), offsets[lo + 1 : hi + 1].tolist())])
                    tally.add(keys, np.repeat(flags[lo:hi], sizes))
                    del keys
            keys, counts = tally.total()
            groups = ranged(keys)
            at = np.flatnonzero(np.diff(groups, prepend=-1)).tolist()
            yield blob_rows(batch_id, [(kind, int(groups[a]), pack_sorted(keys[a:b]), pack(counts[a:b]), None) for a, b in zip(at, [*at[1:], len(keys)])])
            del keys, counts, groups
        del table
        give_back()


def blob_rows(batch_id: int, rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
    columns = [pa.array(c, t) for c, t in zip(zip(*rows), kinds)]
    return pa.RecordBatch.from_arrays([pa.array([batch_id] * len(rows), pa.int64()), *columns], names=["batch", "kind", "grp", "keys", "counts", "texts"])


def by_key(batches, key: str):
    """Runs of rows with the same key, from batches sorted by it, as lists of slices."""
    current, parts = None, []
    for batch in batches:
        values = batch.column(batch.schema.get_field_index(key)).to_numpy(zero_copy_only=False)
        if not len(values):
            continue
        turns = [0, *(np.flatnonzero(np.diff(values)) + 1).tolist(), len(values)]
        for a, b in zip(turns[:-1], turns[1:]):
            if parts and values[a] != current:
                yield current, parts
                parts = []
            current = values[a]
            parts.append(batch.slice(a, b - a))
    if parts:
        yield current, parts


class Context:
    """Totals and kinds of the symbols of each context of one length, from its grams."""

    def __init__(self, grams: np.ndarray, counts: np.ndarray):
        live = counts > 0
        self.grams, self.counts = grams[live], counts[live]
        self.names, self.of = np.unique(self.grams >> np.uint64(8), return_inverse=True)
        size = max(len(self.names), 1)  # a context that was never seen reads the last place
        self.total = np.bincount(self.of, self.counts, size)
        self.kinds = np.bincount(self.of, minlength=size).astype(float)

    def find(self, names: np.ndarray) -> np.ndarray:
        """Index of each context, -1 where it was never seen."""
        if not len(self.names):
            return np.full(len(names), -1)
        at = np.minimum(np.searchsorted(self.names, names), len(self.names) - 1)
        return np.where(self.names[at] == names, at, -1)

    def count(self, grams: np.ndarray) -> np.ndarray:
        if not len(self.grams):
            return np.zeros(len(grams))
        at = np.minimum(np.searchsorted(self.grams, grams), len(self.grams) - 1)
        return np.where(self.grams[at] == grams, self.counts[at], 0).astype(float)


def summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    names, of = np.unique(keys, return_inverse=True)
    return names, np.bincount(of, counts, len(names))


def levels_of(keys: np.ndarray, counts: np.ndarray, across: dict[int, tuple[np.ndarray, np.ndarray]]) -> list[Context]:
    """The contexts of each length 0..ORDER; those ``across`` a border with their counts everywhere."""
    out = []
    for k in range(ORDER + 1):
        grams, n = summed((context(keys, k) << np.uint64(8)) | (keys & np.uint64(0xFF)), counts)
        if k in across:
            whole, total = across[k]
            inside = ~np.isin(grams >> np.uint64(8), np.unique(whole >> np.uint64(8)))
            grams, n = np.concatenate([grams[inside], whole]), np.concatenate([n[inside], total])
            order = np.argsort(grams, kind="stable")
            grams, n = grams[order], n[order]
        out.append(Context(grams, n))
    return out


def log_probabilities(keys: np.ndarray, counts: np.ndarray, across: dict[int, tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """log10 of the probability of each gram. keys: all grams asked for of one range (sorted,
    distinct), counts: in training; across: per length, the grams of the contexts that reach
    beyond the range, with their counts in all training texts."""
    levels = levels_of(keys, counts, across)
    out, open_ = np.zeros(len(keys)), np.ones(len(keys), bool)
    barred, barred_kinds = np.zeros(len(keys)), np.zeros(len(keys))
    for k in range(ORDER, -1, -1):
        level, names = levels[k], context(keys, k)
        gram = (names << np.uint64(8)) | (keys & np.uint64(0xFF))
        at = level.find(names)
        known = open_ & (at >= 0)
        n, total, kinds = level.count(gram), level.total[at], level.kinds[at]
        left = total - barred
        hit = known & (n > 0)
        out[hit] += np.log10((n[hit] - 0.5) / left[hit])
        novel = 0.5 * (kinds - barred_kinds)
        miss = known & (n == 0) & (novel > 0)
        out[miss] += np.log10(novel[miss] / left[miss])
        open_ &= ~hit
        if k:  # what this context has seen can't be what a shorter one predicts
            lower = levels[k - 1].count(shorter(level.grams))
            barred = np.where(known, np.bincount(level.of, lower, len(level.total))[at], barred)
            barred_kinds = np.where(known, kinds, barred_kinds)
    rest = 256 - len(levels[0].grams)
    out[open_] -= np.log10(max(rest, 1))
    return out


def border_ends(borders: np.ndarray, r: int) -> np.ndarray:
    """The keys at both ends of a range."""
    return borders[max(r - 1, 0) : r + 1]


TOTALS = "slot long, keys binary, counts binary, tokens long, types long, lengths array<int>, names array<long>, symbols array<int>, sums array<long>"


def merge_ranges(batches, borders: np.ndarray):
    """From blobs sorted by slot (kind and range) to one row for each slot: its keys with their
    counts over all batches, training tokens and distinct training words, and, of the contexts
    across its borders, the training counts of their symbols inside."""
    for slot, parts in by_key(batches, "slot"):
        table = pa.Table.from_batches(parts)
        lists = [unpack_sorted(b) for b in table.column("keys").to_pylist()]
        counts = np.concatenate([unpack(b, np.uint32) for b in table.column("counts").to_pylist()])
        keys, of = np.unique(np.concatenate(lists), return_inverse=True)
        total = np.bincount(of, counts, len(keys)).astype(np.int64)
        words = int(slot) >> 32 == WORD
        found = [] if words else list(inside_contexts(keys, total, border_ends(borders, int(slot) & 0xFFFFFFFF)))
        lengths, names, symbols, sums = (list(x) for x in (zip(*found) if found else ([], [], [], [])))
        row = {"slot": int(slot), "keys": pack_sorted(keys), "counts": pack(total), "tokens": int(total.sum()) * words, "types": int((total > 0).sum()) * words, "lengths": lengths, "names": names, "symbols": symbols, "sums": sums}
        kinds = [pa.int64(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int64())]
        yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row.values(), kinds)], names=list(row))


def inside_contexts(keys: np.ndarray, counts: np.ndarray, ends: np.ndarray):
    """Length, context, symbol and training count inside a range, for contexts across its ends."""
    for k in range(ORDER + 1):
        width = 8 * (ORDER - k + 1)
        for name in np.unique(context(ends, k)).tolist():
            least = name << width
            a, b = np.searchsorted(keys, np.uint64(least)), np.searchsorted(keys, np.uint64(least + (1 << width) - 1), side="right")
            sums = np.bincount((keys[a:b] & np.uint64(0xFF)).astype(np.int64), counts[a:b], 256).astype(np.int64)
            for s in np.flatnonzero(sums).tolist():
                yield k, name, s, int(sums[s])


def answer_ranges(batches):
    """From rows sorted by slot to answers: batch, kind, grp, values. Of a slot there is the row with
    its totals (batch -1), rows with the grams of contexts across its borders (batch -2 - length),
    and the blobs of the batches."""
    for slot, parts in by_key(batches, "slot"):
        table = pa.Table.from_batches(parts)
        batch = table.column("batch").to_numpy()
        across = {-2 - r["batch"]: (np.array(r["grams"], np.uint64), np.array(r["sums"], np.int64)) for r in table.filter(pa.array(batch < -1)).to_pylist()}
        across = {k: (g[np.argsort(g)], n[np.argsort(g)]) for k, (g, n) in across.items()}
        whole = table.filter(pa.array(batch == -1))
        keys, total = unpack_sorted(whole.column("keys")[0].as_py()), unpack(whole.column("counts")[0].as_py(), np.int64)
        kind = int(slot) >> 32
        values = log_probabilities(keys, total, across).astype(np.float32) if kind == GRAM else total
        asked = table.filter(pa.array(batch >= 0))
        blobs = [pack(values[np.searchsorted(keys, unpack_sorted(b))]) for b in asked.column("keys").to_pylist()]
        n = len(blobs)
        yield pa.RecordBatch.from_arrays([asked.column("batch").combine_chunks(), pa.array([kind] * n, pa.int32()), pa.array([int(slot) & 0xFFFFFFFF] * n, pa.int64()), pa.array(blobs, pa.binary())], names=["batch", "kind", "grp", "vals"])


class Lookup:
    """Open addressing over distinct 64-bit keys, filled and read by whole arrays."""

    def __init__(self, keys: np.ndarray):
        self.bits = max(4, int(np.ceil(np.log2(max(len(keys), 1) * 2.5))))
        self.slot = np.full(1 << self.bits, -1, np.int32)
        self.keys = keys
        for lo in range(0, len(keys), PIECE):
            at = self.home(keys[lo : lo + PIECE])
            todo = np.arange(lo, lo + len(at), dtype=np.int32)
            while len(todo):
                free = self.slot[at] < 0
                self.slot[at[free]] = todo[free]
                lost = self.slot[at] != todo
                todo, at = todo[lost], (at[lost] + 1) & ((1 << self.bits) - 1)

    def home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Index of each key; every key must be present."""
        at = self.home(keys)
        out = self.slot[at]
        todo = np.flatnonzero(self.keys[out] != keys)
        while len(todo):
            at[todo] = (at[todo] + 1) & ((1 << self.bits) - 1)
            out[todo] = self.slot[at[todo]]
            todo = todo[self.keys[out[todo]] != keys[todo]]
        return out


def score_batch(texts: list[pa.Array], answers: list[tuple[int, int, bytes]], tokens: int, types: int):
    """Per text of a batch: n_tokens, n_known, base_score, score."""
    rows = [r for t in texts for r in text_rows(t)[0]]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in rows])])
    result = [np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64), np.zeros(len(rows)), np.zeros(len(rows))]
    for kind, make in ((GRAM, gram_keys), (WORD, word_keys)):
        chunks = list(byte_chunks(offsets, CHUNK_BYTES))
        made = [make(rows[lo:hi]) for lo, hi in chunks] if kind == WORD else None  # grams take too much room
        tally = Tally()
        for c, (lo, hi) in enumerate(chunks):
            keys, _ = made[c] if made else make(rows[lo:hi])
            tally.add(keys, np.zeros(len(keys), bool))
        asked = tally.total()[0]
        blobs = sorted((g, v) for k, g, v in answers if k == kind)
        values = np.concatenate([unpack(v, np.float32 if kind == GRAM else np.int64) for _, v in blobs])
        if len(values) != len(asked):
            raise RuntimeError("a batch and its answers differ")
        lookup = Lookup(asked)
        for c, (lo, hi) in enumerate(chunks):
            keys, sizes = made[c] if made else make(rows[lo:hi])
            found = values[lookup.find(keys)].astype(np.float64)
            at = np.cumsum(sizes) - sizes
            if kind == GRAM:
                result[3][lo:hi] = np.add.reduceat(found, at)
            else:
                result[0][lo:hi] = sizes
                result[1][lo:hi] = np.add.reduceat((found > 0).astype(np.int64), at)
                result[2][lo:hi] = np.add.reduceat(np.log10((found + 1) / (tokens + types + 1)), at)
    return result


def score_documents(docs: DataFrame, learn: Column, scratch: Scratch | None = None, batch_bytes: int = BATCH_BYTES, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """``(doc_id, learned, n_tokens, n_known, train_tokens, base_score, score)``, one row per
    input row, over whole texts; ``learn`` marks the rows whose texts train both models.

    Null text counts as empty: one end symbol, one end token. Repeated rows count and score
    each for itself, a null doc_id is kept and learns only if ``learn`` says true, extra
    columns are ignored, an empty table gives an empty result. Without training texts every
    byte costs log10(256) and every token log10(1).
    """
    scratch = scratch or Scratch(docs.sparkSession, "ppm")
    size = docs.agg(F.sum(F.octet_length("text") + 16)).first()[0]
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce(learn, F.lit(False)).alias("learned"))
    borders = gram_borders(rows, int(size or 0), range_bytes)

    def list_all(batches):
        yield from list_batches(batches, borders, batch_bytes, TaskContext.get().partitionId() * TASK_BATCHES)

    # texts and lists lie apart, so that the lists can go as soon as they are answered; the blobs are
    # compressed, and pages of a few of them need no large buffers
    made = rows.mapInArrow(tidy(list_all), ASKED)
    path = f"{scratch.root}/asked"
    with small_batches(docs.sparkSession):
        made.withColumn("part", (F.col("kind") == TEXT).cast("int")).write.partitionBy("part").option("parquet.page.size.row.check.min", 8).parquet(path, compression="uncompressed")
    whole = docs.sparkSession.read.schema(f"{ASKED}, part int").parquet(path)
    asked, texts = whole.where("part = 0"), whole.where("part = 1").select("batch", "grp", "texts")
    asked._scratch_path = f"{path}/part=0"
    slot = (F.col("kind").cast("long") * (1 << 32) + F.col("grp")).alias("slot")

    def merge_all(rows):
        yield from merge_ranges(rows, borders)

    # as many tasks as ranges, so that no task grows with the input
    tasks = 2 * (len(borders) + 1)
    lists = asked.select(slot, "batch", "keys", "counts")
    totals = scratch.save(lists.select("slot", "keys", "counts").repartition(tasks, "slot").sortWithinPartitions("slot").mapInArrow(tidy(merge_all), TOTALS), "totals", "uncompressed")
    known = totals.agg(F.sum("tokens"), F.sum("types")).first()
    tokens, types = int(known[0] or 0), int(known[1] or 0)
    across = border_contexts(totals, borders, scratch).withColumn("batch", F.lit(-2).cast("long") - F.col("length"))
    both = lists.unionByName(totals.select("slot", F.lit(-1).cast("long").alias("batch"), "keys", "counts"))
    both = both.unionByName(across.select("slot", "batch", "grams", "sums"), allowMissingColumns=True)
    answers = both.repartition(tasks, "slot").sortWithinPartitions("slot")
    answers = scratch.save(answers.mapInArrow(tidy(answer_ranges), "batch long, kind int, grp long, vals binary"), "answers", "uncompressed")
    scratch.drop(asked, totals)

    def join_batch(left: pa.Table, right: pa.Table) -> pa.Table:
        blobs = sorted(zip(left.column("grp").to_pylist(), left.column("texts").to_pylist()))
        held = pa.concat_tables([unpack_rows(blob) for _, blob in blobs])
        del blobs
        values = score_batch(held.column("text").chunks, list(zip(*(right.column(c).to_pylist() for c in ("kind", "grp", "vals")))), tokens, types)
        give_back()
        return pa.table({
            "doc_id": held.column("doc_id"), "learned": held.column("learned"), "n_tokens": pa.array(values[0], pa.int64()), "n_known": pa.array(values[1], pa.int64()),
            "train_tokens": pa.array(np.full(len(held), tokens), pa.int64()), "base_score": pa.array(values[2], pa.float64()), "score": pa.array(values[3], pa.float64()),
        })

    ddl = "doc_id long, learned boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    batches = max(1, texts.where("grp = 0").count())
    left, right = (t.repartition(batches, "batch").groupBy("batch") for t in (texts, answers))
    return left.cogroup(right).applyInArrow(join_batch, ddl)


@contextmanager
def small_batches(spark: SparkSession):
    """Meanwhile Python gets rows by ARROW_BYTES. Spark's own bound is 64 MB and its buffers double as they fill."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name, None)
    spark.conf.set(name, str(ARROW_BYTES))
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def gram_borders(rows: DataFrame, size: int, range_bytes: int) -> np.ndarray:
    """Keys that cut the grams into ranges, from a share of the grams of a sample of the rows."""
    ranges = min(MOST_RANGES, -(-size // range_bytes))
    if ranges < 2:
        return np.zeros(0, np.uint64)
    sample = rows.where(F.pmod(F.xxhash64("doc_id", F.octet_length("text")), F.lit(max(1, size // BORDER_BYTES))) == 0)

    def some(batches):
        for batch in batches:
            held, offsets = text_rows(batch.column(0))
            for lo, hi in byte_chunks(offsets, CHUNK_BYTES):
                keys = distinct(gram_keys(held[lo:hi])[0])
                mixed = (keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)
                keys = keys[mixed % np.uint64(BORDER_SHARE) == 0]
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64))], names=["key"])

    shares = [F.lit(k / ranges) for k in range(1, ranges)]
    with small_batches(rows.sparkSession):
        found = sample.select("text").mapInArrow(tidy(some), "key long").agg(F.percentile_approx("key", F.array(*shares), F.lit(max(10_000, 4 * ranges)))).first()[0]
    return np.unique(np.array(found or [], np.int64)).astype(np.uint64)


def border_contexts(totals: DataFrame, borders: np.ndarray, scratch: Scratch) -> DataFrame:
    """``(slot, length, grams, sums)``: of each range the grams of the contexts across its borders,
    at most two of each length, with their training counts everywhere."""

    def wanted(rows):
        for batch in rows:
            out = [(r, k, c) for r in batch.column(0).to_pylist() for k in range(ORDER + 1) for c in np.unique(context(border_ends(borders, r), k)).tolist()]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*out) if out else ([], [], []))], names=["slot", "length", "name"])

    cells = totals.select(F.explode(F.arrays_zip("lengths", "names", "symbols", "sums")).alias("c")).select(F.col("c.lengths").cast("long").alias("length"), F.col("c.names").alias("name"), F.col("c.symbols").alias("symbol"), F.col("c.sums").alias("n"))
    sums = scratch.save(cells.groupBy("length", "name", "symbol").agg(F.sum("n").alias("n")), "across")
    ranges = totals.sparkSession.range(len(borders) + 1 if len(borders) else 0).mapInArrow(wanted, "slot long, length long, name long")
    gram = F.shiftleft("name", 8).bitwiseOR(F.col("symbol"))
    return ranges.join(sums, ["length", "name"]).groupBy("slot", "length").agg(F.collect_list(gram).alias("grams"), F.collect_list("n").alias("sums"))
