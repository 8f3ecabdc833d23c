"""Hashed character n-grams of words, computed for whole batches of texts at once.

Words are runs of non-space bytes of the lower-cased text; the spaces around a word count as
its border marks, so n-grams that hold one are prefixes and suffixes. An n-gram never reaches
into the next word.
"""

from __future__ import annotations

import numpy as np

from .textkernels import IS_SPACE

MIX = np.uint32(2654435761)
STEP = np.uint32(16777619)
POWER = np.uint64(0x100000001B3)
BACK = np.uint64(pow(0x100000001B3, -1, 1 << 64))


class WordBatch:
    """Bytes of some texts joined by spaces, the spans of their words, words of each text."""

    def __init__(self, texts: list[str | None]):
        raw = [(t or "").lower().encode() for t in texts]
        self.data = np.frombuffer(b" ".join([b"", *raw, b"", b""]), dtype=np.uint8)
        self.space = IS_SPACE[self.data]
        turns = np.diff((~self.space).astype(np.int8))
        self.starts = np.flatnonzero(turns == 1) + 1
        self.ends = np.flatnonzero(turns == -1) + 1
        text_at = np.cumsum([1, *[len(r) + 1 for r in raw]])
        self.first = np.searchsorted(self.starts, text_at)
        self.seen = np.cumsum(self.space, dtype=np.int32)

    def grams(self, n: int, bits: int):
        """Bucket and validity of the n-gram (n >= 3) at each byte; it belongs to the word at
        the byte after."""
        data, m = self.data, len(self.data) - n + 1
        if m <= 0:
            return np.zeros(0, np.uint32), np.zeros(0, bool)
        h = np.full(m, n, dtype=np.uint32)
        for k in range(n):
            byte = data[k : k + m]
            h *= STEP
            h ^= np.where(self.space[k : k + m], np.uint8(32), byte) if k in (0, n - 1) else byte
        h *= MIX
        h >>= np.uint32(32 - bits)
        return h, self.seen[n - 2 : n - 2 + m] == self.seen[:m]

    def word_sums(self, values: np.ndarray) -> np.ndarray:
        """Sum per word of values that stand at the byte before the one they belong to."""
        run = np.zeros((len(values) + 1, *values.shape[1:]))
        np.cumsum(values, axis=0, dtype=np.float64, out=run[1:])
        return run[self.ends - 1] - run[self.starts - 1]

    def word_keys(self, bits: int) -> np.ndarray:
        """A bucket for each whole word."""
        with np.errstate(over="ignore"):
            power = np.cumprod(np.full(len(self.data), POWER, np.uint64))
            run = np.zeros(len(self.data) + 1, np.uint64)
            np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * power, out=run[1:])
            back = np.cumprod(np.full(len(self.data), BACK, np.uint64))
            h = (run[self.ends] - run[self.starts]) * back[self.starts]
            h ^= h >> np.uint64(29)
            h *= np.uint64(0x9E3779B97F4A7C15)
        return (h >> np.uint64(64 - bits)).astype(np.uint32)

    def word_grams(self, orders: tuple[int, ...], bits: int) -> tuple[np.ndarray, np.ndarray]:
        """Buckets of all n-grams and the word of each, for training."""
        word_at = np.cumsum(np.bincount(self.starts, minlength=len(self.data) + 1)) - 1
        found, owner = [], []
        for n in orders:
            h, ok = self.grams(n, bits)
            at = np.flatnonzero(ok)
            found.append(h[at] | np.uint32(0))
            owner.append(word_at[at + 1])
        return np.concatenate(found), np.concatenate(owner)
