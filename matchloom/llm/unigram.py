"""Token counts under a unigram model, by dynamic programming shared through a trie.

The pieces are those of a public vocabulary file; a piece's score falls with the logarithm of
its rank there (Zipf). The public files hold no unigram model, and tokenizers are never trained,
so the scores are a rule and not an estimate. The distinct pre-tokens that a task meets are
inserted in a trie; a node's forward score is computed once, when the node is made, whatever number
of pre-tokens share the prefix, and the count at each terminal node is stored. Documents then
add up stored counts. The trie is begun anew when it has grown beyond CACHE_NODES.
"""

from __future__ import annotations

import json
import math
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, functions as F

from .bpe import SPLIT, printable_bytes
from .textkernels import byte_chunks, tidy, utf8_view

CACHE_NODES = 1_000_000
NOT_A_TAIL = object()


class PieceModel:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = {t["content"] for t in spec.get("added_tokens", [])}
        to_byte = printable_bytes()
        self.scores = {bytes(to_byte[c] for c in name): -math.log(i + 2.0) for name, i in spec["model"]["vocab"].items() if name not in special}
        # every tail of a piece, with its score if it is one: a search back from a place ends where
        # no piece goes on
        self.tails = {piece[k:]: None for piece in self.scores for k in range(len(piece))}
        self.tails.update(self.scores)
        self.split = regex.compile(SPLIT)
        self.clear()

    def clear(self) -> None:
        """An empty trie: children by node and byte, and each node's best score and its pieces."""
        self.children: dict[int, int] = {}
        self.best, self.pieces = [0.0], [0]
        self.counts: dict[str, int] = {}

    def grow(self, word: bytes, path: list[int]) -> int:
        """The node after ``path``, with the forward score of that prefix of the word: of equal
        scores the one with fewer pieces."""
        end, high, least = len(path), -math.inf, 0
        tails, best, pieces = self.tails, self.best, self.pieces
        for start in range(end - 1, -1, -1):
            score = tails.get(word[start:end], NOT_A_TAIL)
            if score is NOT_A_TAIL:
                break
            if score is not None:
                node = path[start]
                total = best[node] + score
                if total > high or total == high and pieces[node] + 1 < least:
                    high, least = total, pieces[node] + 1
        best.append(high)
        pieces.append(least)
        return len(best) - 1

    def insert(self, word: bytes) -> int:
        """Puts a pre-token in the trie; the count at its terminal node."""
        children, path, node = self.children, [0], 0
        for byte in word:
            key = node << 8 | byte
            node = children.get(key, 0)
            if not node:
                node = children[key] = self.grow(word, path)
            path.append(node)
        return self.pieces[node]

    def count_texts(self, texts: list[str]) -> tuple[list[int], list[int]]:
        split = [self.split.findall(t) for t in texts]
        if len(self.best) > CACHE_NODES:
            self.clear()
        known = self.counts
        for word in set().union(*split) - known.keys():
            known[word] = self.insert(word.encode())
        return [len(s) for s in split], [sum(map(known.__getitem__, s)) for s in split]


@lru_cache(maxsize=2)
def model(path: str) -> PieceModel:
    return PieceModel(path)


def count_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_pretokens, n_tokens)``, one row per input row, over whole texts.

    Null and empty texts have no tokens. Repeated rows repeat, extra columns are ignored, an
    empty table gives an empty result. Every byte is a piece, so every text has a count.
    """

    def run(batches):
        pieces = model(vocabulary)
        for batch in batches:
            data, offsets = utf8_view(batch.column(1))
            for lo, hi in byte_chunks(offsets, 2 << 20):
                texts = [data[a:b].tobytes().decode() for a, b in zip(offsets[lo:hi].tolist(), offsets[lo + 1 : hi + 1].tolist())]
                n, total = pieces.count_texts(texts)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(n, pa.int64()), pa.array(total, pa.int64())], names=["doc_id", "n_pretokens", "n_tokens"])
        pieces.clear()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidy(run), "doc_id long, n_pretokens long, n_tokens long")
