"""Exact byte-level BPE by dynamic programming over prefixes.

For every prefix of a pre-token there is just one token that can end its encoding, so the
table of last tokens is filled from left to right: an automaton over the vocabulary gives
the tokens that are suffixes of the prefix, and the one that may follow the last token of
what is left is kept. Following the back-pointers from the end gives the ids.

Words recur over all tasks of a worker process, so the cache of pre-tokens stays with it; it holds
ids joined by commas only, and its bound keeps it and the pairs at about 160 MB, by calculation.

Two neighbouring tokens are compatible when no merge across their border would run before
both are complete; that is read off the two merge trees, without encoding anything.
"""

from __future__ import annotations

import hashlib
import json
from functools import lru_cache

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, functions as F

from .textkernels import byte_chunks, tidy, utf8_view

#: Fixed value: the split pattern of byte-level BPE vocabularies of this family.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

#: Pre-tokens of one of two generations, and pairs of tokens: about 250 and 130 bytes each.
CACHE_ENTRIES = 250_000
PAIR_ENTRIES = 300_000
LONGEST_CACHED = 64


def printable_bytes() -> dict[str, int]:
    """The stand-in character of each byte in vocabulary files, by rule: printable Latin-1
    bytes stand for themselves, the others follow from U+0100 in order."""
    own = [b for b in range(256) if 0x21 <= b <= 0x7E or 0xA1 <= b <= 0xAC or 0xAE <= b <= 0xFF]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(0x100 + k): b for k, b in enumerate(rest)}


class PairRules:
    """Which token may directly follow which, from the merge list."""

    def __init__(self, merges: list[tuple[int, int]], product: list[int], n_tokens: int):
        self.rank = {a << 20 | b: k for k, (a, b) in enumerate(merges)}
        self.parts: list[tuple[int, int] | None] = [None] * n_tokens
        self.born = [-1] * n_tokens
        for k, (pair, made) in enumerate(zip(merges, product)):
            if self.parts[made] is None:
                self.parts[made], self.born[made] = pair, k
        self.known: dict[int, bool] = {}
        self.edges: tuple[dict[int, list], dict[int, list]] = {}, {}

    def edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """Nodes along one side of a token's merge tree, each with the rank that ends its life."""
        if (out := self.edges[side].get(token)) is None:
            out = self.edges[side][token] = self._edge(token, side)
        return out

    def _edge(self, token: int, side: int) -> list[tuple[int, int]]:
        out, until = [], len(self.rank) + 1
        while True:
            out.append((token, until))
            if self.parts[token] is None:
                return out
            until = self.born[token]
            token = self.parts[token][side]

    def fits(self, left: int, right: int) -> bool:
        key = left << 20 | right
        if (ok := self.known.get(key)) is None:
            ok = self._fits(left, right)
            if len(self.known) > PAIR_ENTRIES:
                self.known.clear()
            self.known[key] = ok
        return ok

    def _fits(self, left: int, right: int) -> bool:
        rank = self.rank
        facing = self.edge(right, 0)
        for x, x_until in self.edge(left, 1):
            x <<= 20
            for y, y_until in facing:
                # a merge over the border runs if both sides still stand at its rank; at equal
                # rank the leftmost goes first: the left tree's own merge, then the border
                if (at := rank.get(x | y)) is not None and at < x_until and at <= y_until:
                    return False
        return True


class PrefixEncoder:
    """One vocabulary, ready to encode pre-tokens and texts."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        to_byte = printable_bytes()
        vocab = spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        size = max([*vocab.values(), *self.special.values()]) + 1
        self.bytes_of = [b""] * size
        for name, i in vocab.items():
            if name not in self.special:
                self.bytes_of[i] = bytes(to_byte[c] for c in name)
        for name, i in self.special.items():
            self.bytes_of[i] = name.encode()
        pairs = [tuple(m.split(" ") if isinstance(m, str) else m) for m in spec["model"]["merges"]]
        self.rules = PairRules([(vocab[a], vocab[b]) for a, b in pairs], [vocab[a + b] for a, b in pairs], size)
        self.automaton = ahocorasick.Automaton()
        for name, i in vocab.items():
            if name not in self.special and (self.rules.parts[i] is None or self.rules.fits(*self.rules.parts[i]) or self._own(i)):
                raw = self.bytes_of[i]
                self.automaton.add_word(raw.decode("latin-1"), (len(raw), i))
        self.automaton.make_automaton()
        self.split = regex.compile(SPLIT)
        self.around = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.young: dict[str, str] = {}
        self.old: dict[str, str] = {}

    def _own(self, i: int) -> bool:
        """The parts fit except for the merge that makes the token itself."""
        left, right = self.rules.parts[i]
        key = left << 20 | right
        at = self.rules.rank.pop(key)
        ok = self.rules._fits(left, right)
        self.rules.rank[key] = at
        return ok

    def ids(self, raw: bytes) -> list[int]:
        """Token ids of one pre-token."""
        n = len(raw)
        last, sizes = [-1] * (n + 1), [0] * (n + 1)
        known, fits = self.rules.known, self.rules.fits
        for end, (length, token) in self.automaton.iter(raw.decode("latin-1")):
            if last[end + 1] >= 0:
                continue
            start = end + 1 - length
            if start:
                before = last[start]
                ok = known.get(before << 20 | token)
                if not (fits(before, token) if ok is None else ok):
                    continue
            last[end + 1], sizes[end + 1] = token, length
        out = []
        while n > 0:
            out.append(last[n])
            n -= sizes[n]
        return out[::-1]

    def entry(self, piece: str) -> str:
        """The ids of one pre-token joined by commas; they decode to its bytes again."""
        raw = piece.encode()
        ids = self.ids(raw)
        if b"".join([self.bytes_of[i] for i in ids]) != raw:
            raise ValueError("ids do not decode to their pre-token")
        found = ",".join(map(str, ids))
        if len(piece) <= LONGEST_CACHED:
            if len(self.young) >= CACHE_ENTRIES:
                self.old, self.young = self.young, {}
            self.young[piece] = found
        return found

    def again(self, piece: str) -> str:
        """Of a pre-token that the young cache lacks."""
        if (found := self.young.get(piece)) is not None:
            return found
        if (found := self.old.get(piece)) is not None:
            self.young[piece] = found
            return found
        return self.entry(piece)

    def encode(self, text: str) -> tuple[int, str, str]:
        """How many ids, the ids joined by commas, and the text that they decode to."""
        parts = self.around.split(text) if self.around else [text]
        joined, raw = [], []
        for part in parts:
            if part in self.special:
                i = self.special[part]
                joined.append(str(i))
                raw.append(self.bytes_of[i])
                continue
            pieces = self.split.findall(part)
            found = list(map(self.young.get, pieces))
            if None in found:
                found = [self.again(piece) if ids is None else ids for piece, ids in zip(pieces, found)]
            joined += found
            # each piece's ids were decoded when they were made
            raw.append("".join(pieces).encode())
        line = ",".join(joined)
        return line.count(",") + 1 if line else 0, line, b"".join(raw).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def encoder(path: str) -> PrefixEncoder:
    """One per worker process and vocabulary."""
    return PrefixEncoder(path)


def encode_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text", outputs: tuple[str, ...] = ("n_tokens", "ids_sha256", "decoded_sha256")) -> DataFrame:
    """Encode whole texts and decode the ids again; one row per input row.

    ``outputs`` picks from n_tokens, ids (array of int), decoded, ids_sha256, decoded_sha256.
    Null text counts as empty: no ids, hash of the empty string. Strings of special tokens in
    a text become their ids. Extra columns are ignored; repeated rows repeat; an empty table
    gives an empty result. Very long texts are held one at a time.
    """
    kinds = {"n_tokens": (pa.int64(), "long"), "ids": (pa.list_(pa.int32()), "array<int>"), "decoded": (pa.string(), "string"), "ids_sha256": (pa.string(), "string"), "decoded_sha256": (pa.string(), "string")}
    schema = pa.schema([("doc_id", pa.int64()), *((c, kinds[c][0]) for c in outputs)])

    def run(batches):
        bpe = encoder(vocabulary)
        for batch in batches:
            data, offsets = utf8_view(batch.column(1))
            for lo, hi in byte_chunks(offsets, 4 << 20):
                rows: dict[str, list] = {c: [] for c in outputs}
                for a, b in zip(offsets[lo:hi].tolist(), offsets[lo + 1 : hi + 1].tolist()):
                    n, joined, back = bpe.encode(data[a:b].tobytes().decode())
                    made = {
                        "n_tokens": lambda: n,
                        "ids": lambda: [int(x) for x in joined.split(",")] if n else [],
                        "decoded": lambda: back,
                        "ids_sha256": lambda: hashlib.sha256(joined.encode()).hexdigest(),
                        "decoded_sha256": lambda: hashlib.sha256(back.encode()).hexdigest(),
                    }
                    for c in outputs:
                        rows[c].append(made[c]())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), *(pa.array(rows[c], schema.field(c).type) for c in outputs)], schema=schema)

    ddl = ", ".join(["doc_id long", *(f"{c} {kinds[c][1]}" for c in outputs)])
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidy(run), ddl)
