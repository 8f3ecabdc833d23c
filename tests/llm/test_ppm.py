"""Scores against a plain dictionary version of prediction by partial matching."""

import math
import random
import tracemalloc
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from matchloom.llm import ppm

ORDER = ppm.ORDER


def plain(texts, learn):
    counts = [defaultdict(Counter) for _ in range(ORDER + 1)]

    def symbols(text):
        return bytes([0xFE]) * ORDER + text.encode().lower() + bytes([0xFF])

    for text, use in zip(texts, learn):
        if use:
            s = symbols(text or "")
            for i in range(ORDER, len(s)):
                for k in range(ORDER + 1):
                    counts[k][s[i - k : i]][s[i]] += 1

    def cost(history, c):
        total, barred = 0.0, set()
        for k in range(ORDER, -1, -1):
            seen = counts[k].get(history[len(history) - k :])
            if not seen:
                continue
            left = sum(n for x, n in seen.items() if x not in barred)
            if c in seen:
                return total + math.log10((seen[c] - 0.5) / left)
            if novel := 0.5 * len(set(seen) - barred):
                total += math.log10(novel / left)
            barred |= set(seen)
        return total - math.log10(256 - len(counts[0].get(b"", ())))

    words = Counter()
    for text, use in zip(texts, learn):
        if use:
            words.update([*(text or "").encode().lower().split(), None])
    n, v = sum(words.values()), len(words)
    out = []
    for text in texts:
        s, tokens = symbols(text or ""), [*(text or "").encode().lower().split(), None]
        out.append((
            len(tokens), sum(words[t] > 0 for t in tokens), n,
            sum(math.log10((words[t] + 1) / (n + v + 1)) for t in tokens),
            sum(cost(s[i - ORDER : i], s[i]) for i in range(ORDER, len(s))),
        ))
    return out


def test_scores_match_plain_version(spark):
    rng = random.Random(5)
    texts = ["".join(rng.choice("ab cD\n") for _ in range(rng.randint(0, 60))) for _ in range(60)] + [None, "", " \t", "é\x00ü", "abcabc" * 300, "aB c", "aB c"]
    rows = [(i, t, "x") for i, t in enumerate(texts)]
    learn = [zlib.crc32(str(i).encode()) % 7 != 2 for i, _, _ in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string, score string")
    flag = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(7)) != 2
    got = {r["doc_id"]: r for r in ppm.score_documents(df, flag, batch_bytes=700).collect()}
    assert len(got) == len(rows)
    for (i, _, _), want, use in zip(rows, plain(texts, learn), learn):
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"], r["learned"]) == (*want[:3], use)
        assert r["base_score"] == pytest.approx(want[3], rel=1e-9)
        assert r["score"] == pytest.approx(want[4], rel=1e-5)


@pytest.mark.parametrize("range_bytes", [40, 300])
def test_borders_of_key_ranges_change_nothing(spark, range_bytes):
    rng = random.Random(7)
    # one pair of bytes nearly everywhere, a row repeated often, and contexts that borders cut
    texts = ["th" * rng.randint(0, 40) + "".join(rng.choice("the ") for _ in range(rng.randint(0, 50))) for _ in range(80)] + ["the same row"] * 400
    learn = [i % 5 != 2 for i in range(len(texts))]
    df = spark.createDataFrame([(i if i < 80 else 80, t, u) for i, (t, u) in enumerate(zip(texts, learn))], "doc_id long, text string, u boolean")
    got = sorted((r["doc_id"], r["n_tokens"], r["score"]) for r in ppm.score_documents(df, F.col("u"), batch_bytes=900, range_bytes=range_bytes).collect())
    want = sorted((min(i, 80), p[0], p[4]) for i, p in enumerate(plain(texts, learn)))
    assert len(got) == len(want) and all(a[:2] == b[:2] and a[2] == pytest.approx(b[2], rel=1e-5) for a, b in zip(got, want))


def test_empty_table_and_no_training(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert ppm.score_documents(df, F.lit(True)).count() == 0
    one = spark.createDataFrame([(None, "ab"), (3, None)], "doc_id long, text string")
    rows = {r["doc_id"]: r for r in ppm.score_documents(one, F.lit(False)).collect()}
    assert rows[None]["score"] == pytest.approx(3 * -math.log10(256)) and rows[3]["n_tokens"] == 1 and rows[3]["base_score"] == 0


def test_lists_of_a_batch_need_room_for_distinct_grams_only(monkeypatch):
    rng = random.Random(3)
    texts = ["".join(rng.choice("abcdefgh ") for _ in range(4000)) for _ in range(32)] * 16
    learn = [i % 3 > 0 for i in range(len(texts))]
    rows = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts), pa.array(learn)], names=["doc_id", "text", "learned"])
    monkeypatch.setattr(ppm, "CHUNK_BYTES", 1 << 17)
    tracemalloc.start()
    out = [r for b in ppm.list_batches(iter([rows]), np.zeros(0, np.uint64), 4 << 20, 0) for r in b.to_pylist()]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 12 * sum(map(len, texts))
    (grams,) = [r for r in out if r["kind"] == ppm.GRAM]
    want = Counter()
    for text, use in zip(texts, learn):
        keys, counts = np.unique(ppm.gram_keys([text.encode()])[0], return_counts=True)
        want.update(dict(zip(keys.tolist(), (counts * use).tolist())))
    got = dict(zip(ppm.unpack_sorted(grams["keys"]).tolist(), ppm.unpack(grams["counts"], np.uint32).tolist()))
    assert got == want


def test_scoring_a_batch_needs_little_room_beside_its_texts():
    rng = np.random.default_rng(11)
    letters = np.frombuffer(b"abcdefghijklmnopqrstuvwxyz     ", np.uint8)
    some = [letters[rng.integers(0, len(letters), 4096)].tobytes().decode() for _ in range(256)]
    texts = pa.array(some * 4)
    size = sum(map(len, some)) * 4
    answers = []
    for kind, make, dtype in ((ppm.GRAM, ppm.gram_keys, np.float32), (ppm.WORD, ppm.word_keys, np.int64)):
        n = len(np.unique(make([t.encode() for t in some])[0]))
        answers.append((kind, 0, ppm.pack(np.ones(n, dtype))))
    tracemalloc.start()
    known, total, _, score = (ppm.score_batch([texts], answers, 1, 1)[k] for k in (1, 0, 2, 3))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 20 * size
    assert (known == total).all() and (score == 4097).all() and total.tolist() == [len(t.split()) + 1 for t in some * 4]


def test_texts_of_a_batch_leave_in_small_blobs(spark):
    texts = [f"{i} " + "ab c" * 8000 for i in range(60)]
    learn = [i % 3 > 0 for i in range(len(texts))]
    rows = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts), pa.array(learn)], names=["doc_id", "text", "learned"])
    out = [r for b in ppm.list_batches(iter([rows]), np.zeros(0, np.uint64), 4 << 20, 0) for r in b.to_pylist()]
    held = [ppm.unpack_rows(r["texts"]) for r in out if r["kind"] == ppm.TEXT]
    assert max(t.nbytes for t in held) < 1 << 20
    assert pa.concat_tables(held).to_pylist() == rows.to_pylist()

    df = spark.createDataFrame([(i, t, u) for i, (t, u) in enumerate(zip(texts, learn))], "doc_id long, text string, u boolean").coalesce(1)
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name, None)
    wide, narrow = (sorted(tuple(r) for r in ppm.score_documents(df, F.col("u"), batch_bytes=n).collect()) for n in (4 << 20, 40_000))
    assert spark.conf.get(name, None) == before
    assert len(wide) == len(narrow) == len(texts)
    assert all(a[:-1] == b[:-1] and a[-1] == pytest.approx(b[-1], rel=1e-9) for a, b in zip(wide, narrow))


def test_parts_of_a_tally_merge_by_pieces(monkeypatch):
    monkeypatch.setattr(ppm, "PIECE", 5)
    rng = np.random.default_rng(2)
    tally, want = ppm.Tally(), Counter()
    for size in (40, 3, 0, 25, 11, 1):
        keys, learn = rng.integers(0, 60, size).astype(np.uint64), rng.random(size) < 0.5
        tally.add(keys, learn)
        for k, u in zip(keys.tolist(), learn.tolist()):
            want[k] += u
    keys, counts = tally.total()
    assert keys.tolist() == sorted(want) and counts.tolist() == [want[k] for k in sorted(want)]
    lookup = ppm.Lookup(keys)
    assert lookup.find(keys[::-1].copy()).tolist() == list(range(len(keys)))[::-1]
