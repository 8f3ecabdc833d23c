"""SimHash near-duplicates: tiled exact comparison of fingerprints in numpy.

Fingerprints are 64 or 128 bits wide. Every pair within the radius is found, whatever the
size of the input:

* a radius below ``blocks`` cuts the 64 bits into ``blocks`` pieces; two fingerprints within
  the radius agree on at least ``blocks - radius`` pieces, so tiles form only inside groups
  that share such a choice of pieces. More rows take more pieces, so that keys stay wide enough;
* a larger radius compares tiles of the whole table, or, where a Jaccard similarity is asked
  for as well, of the rows that share a band of min-hashes.

A group of more than ``tile`` rows is cut by population count, and each pair of tiles whose
counts are within the radius is a task of its own; other pairs are never dealt. Inside a task rows
are sorted by population count, and sub-tiles whose counts differ by more than the radius are
skipped before any exclusive-or. What leaves a task is a forest (each row with the least row
that it reaches there), never all pairs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from .components import components
from .storage import Scratch
from .textkernels import tidy, utf8_view

SEED = 42
SUB_TILE = 256
SPAN = 2048
PIECE = 1 << 16
#: Rows and bytes of shingle sets that one tile of the exact comparison holds.
VERIFY_TILE = 1024
VERIFY_BYTES = 32 << 20
VERIFY_CHUNK = 2048
#: Sets of up to so many shingles are compared whatever their bits: few votes make coarse bits.
SHORT = 64
#: Standard deviations of the distance at the least similarity that larger sets' radius allows.
SPREAD = 5
#: Min-hash bands and hashes of each: at similarity 0.8 all bands differ with a chance of 3e-6.
BANDS, BAND_ROWS = 32, 5
MOST_PIECES = 4


def shingle_hashes(words: list[bytes], size: int, seed: int = SEED) -> Iterator[np.ndarray]:
    """XXH64 of each run of ``size`` words joined by a space, in pieces of bounded length."""
    if not words:
        return
    size = min(size, len(words))
    hashed = xxhash.xxh64_intdigest
    for at in range(0, len(words) - size + 1, PIECE):
        part = words[at : at + PIECE + size - 1]
        line = b" ".join(part)
        lengths = np.fromiter(map(len, part), np.int64, len(part))
        ends = np.cumsum(lengths + 1) - 1
        starts = (ends - lengths).tolist()
        yield np.array([hashed(line[a:b], seed) for a, b in zip(starts, ends[size - 1 :].tolist())], dtype=np.uint64)


def majority_bits(pieces: Iterator[np.ndarray]) -> int:
    """Bit k is 1 where over half of the hashes have it; no hash at all gives 0."""
    votes, total = np.zeros(64, np.int64), 0
    for hashes in pieces:
        bits = np.unpackbits(hashes.view(np.uint8), bitorder="little").reshape(-1, 64)
        votes += bits.sum(axis=0, dtype=np.int64)
        total += len(hashes)
    return int(np.packbits(2 * votes > total, bitorder="little").view(np.uint64)[0]) if total else 0


def word_list(data: np.ndarray, start: int, end: int) -> list[bytes]:
    """Words of one text, A-Z lower-cased (bytes.lower and bytes.split are ASCII only)."""
    return data[start:end].tobytes().lower().split()


def fingerprints(docs: DataFrame, shingle: int = 4, wide: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, w0[, w1, n_shingles])``: fingerprint words as signed longs.

    Null or blank texts get zero; shorter texts than a shingle count as one shingle. ``wide``
    adds a second word over hashes with another seed, the number of distinct shingles, and the
    min-hash bands of their set (none for an empty set).
    """
    kinds = [("doc_id", pa.int64()), ("w0", pa.int64())] + ([("w1", pa.int64()), ("n_shingles", pa.int64())] if wide else [])
    schema = pa.schema(kinds + [("bands", pa.list_(pa.int64()))] * wide)

    def run(batches):
        for batch in batches:
            data, offsets = utf8_view(batch.column(1))
            rows, bands = [[] for _ in kinds[1:]], []
            for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
                words = word_list(data, a, b)
                if wide:
                    pieces = list(shingle_hashes(words, shingle))
                    once = np.unique(np.concatenate(pieces)) if pieces else np.zeros(0, np.uint64)
                    # one strong hash per distinct shingle; the second word mixes it anew
                    rows[0].append(majority_bits(iter([once])))
                    rows[1].append(majority_bits(iter([remix(once)])))
                    rows[2].append(len(once))
                    bands.append(min_hash_bands(once))
                else:
                    rows[0].append(majority_bits(shingle_hashes(words, shingle)))
            cols = [np.array(r, np.uint64).view(np.int64) for r in rows]
            lists = [pa.array(bands, pa.list_(pa.int64()))] if wide else []
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, cols), *lists], schema=schema)

    ddl = "doc_id long, w0 long" + (", w1 long, n_shingles long, bands array<long>" if wide else "")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tidy(run), ddl)


def remix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mix (splitmix constants), so one hash serves two fingerprint words."""
    x = x + np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def min_hash_bands(hashes: np.ndarray) -> np.ndarray:
    """BANDS keys of a set, each over the least of BAND_ROWS hashes of its members."""
    if not len(hashes):
        return np.zeros(0, np.int64)
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint64).max, np.uint64)
    seeds = remix(np.arange(1, 2 * len(least) + 1, dtype=np.uint64))
    flips, odds = seeds[: len(least)], seeds[len(least) :] | np.uint64(1)
    for at in range(0, len(hashes), 2048):
        mixed = hashes[None, at : at + 2048] ^ flips[:, None]
        mixed *= odds[:, None]
        mixed ^= mixed >> np.uint64(32)
        np.minimum(least, mixed.min(axis=1), out=least)
    keys = np.arange(BANDS, dtype=np.uint64)
    for k in range(BAND_ROWS):
        keys = remix(keys ^ least[k::BAND_ROWS])
    return keys.view(np.int64)


def settle(labels: np.ndarray, left: np.ndarray, right: np.ndarray) -> None:
    """Lower the labels of linked rows to the least of both, until nothing moves (in place)."""
    while True:
        low = np.minimum(labels[left], labels[right])
        if (labels[left] == low).all() and (labels[right] == low).all():
            return
        np.minimum.at(labels, left, low)
        np.minimum.at(labels, right, low)
        labels[:] = labels[labels]


def bit_counts(words: np.ndarray) -> np.ndarray:
    return np.bitwise_count(words).sum(axis=1, dtype=np.int64)


def close_rows(a: np.ndarray, b: np.ndarray, radius: int, same: bool, sizes: tuple | None = None, ratio: float = 0.0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of rows within ``radius`` bits. Both inputs (n, words) are sorted by bit count.
    With ``sizes`` of the sets, those whose ratio is below ``ratio`` are left out, and sets of up
    to SHORT members pass whatever their bits (sort them first; they count as zero bits)."""
    ones_a, ones_b = (bit_counts(x) for x in (a, b))
    few_a, few_b = (np.zeros(len(x), bool) for x in (a, b))
    if sizes:
        few_a, few_b = (x <= SHORT / ratio for x in sizes)
    for i in range(0, len(a), SUB_TILE):
        j = min(i + SUB_TILE, len(a))
        for s in range(i if same else 0, len(b), SPAN):
            e = min(s + SPAN, len(b))
            few = few_a[i:j].any() and few_b[s:e].any()
            if not few and (ones_b[s:e].max() < ones_a[i:j].min() - radius or ones_b[s:e].min() > ones_a[i:j].max() + radius):
                continue
            apart = np.bitwise_count(a[i:j, 0][:, None] ^ b[s:e, 0][None, :])
            for w in range(1, a.shape[1]):
                apart += np.bitwise_count(a[i:j, w][:, None] ^ b[s:e, w][None, :])
            hit = apart <= radius
            if sizes:
                x, y = sizes[0][i:j, None], sizes[1][None, s:e]
                hit |= few_a[i:j, None] & few_b[None, s:e]
                hit &= np.minimum(x, y) >= ratio * np.maximum(x, y) - 1e-9
            if hit.any():
                x, y = np.nonzero(hit)
                x, y = x + i, y + s
                keep = x < y if same else slice(None)
                yield x[keep], y[keep]


def ordered_tile(words: np.ndarray, ids: np.ndarray, side: np.ndarray, sizes: np.ndarray | None, ratio: float) -> np.ndarray:
    """Order of a pair of tiles: by side, short sets first, by bit count."""
    ones = bit_counts(words)
    if sizes is not None:
        ones = np.where(sizes <= SHORT / ratio, -1, ones)
    return np.lexsort((ids, ones, side))


def tile_pairs(words: np.ndarray, side: np.ndarray, lone: bool, radius: int, sizes: np.ndarray | None, ratio: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Close pairs of rows of an ordered pair of tiles."""
    if lone:
        yield from close_rows(words, words, radius, True, None if sizes is None else (sizes, sizes), ratio)
    else:
        cut = int(np.searchsorted(side, 1))
        for x, y in close_rows(words[:cut], words[cut:], radius, False, None if sizes is None else (sizes[:cut], sizes[cut:]), ratio):
            yield x, y + cut


def tile_forest(words: np.ndarray, ids: np.ndarray, side: np.ndarray, lone: bool, radius: int, sizes: np.ndarray | None = None, ratio: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """Links found in one pair of tiles, as (row id, least id of its part). side: 0 or 1."""
    order = ordered_tile(words, ids, side, sizes, ratio)
    words, ids, side = words[order], ids[order], side[order]
    sizes = None if sizes is None else sizes[order]
    rank = np.argsort(np.argsort(ids, kind="stable"), kind="stable")
    labels, by_rank = np.arange(len(ids)), np.sort(ids, kind="stable")
    for x, y in tile_pairs(words, side, lone, radius, sizes, ratio):
        settle(labels, rank[x], rank[y])
    moved = np.flatnonzero(labels != np.arange(len(labels)))
    return by_rank[moved], by_rank[labels[moved]]


def pieces_for(n: int, radius: int) -> int:
    """Number of pieces for n rows: more of them cost more copies of each row, but their keys
    are wider, so that groups by chance stay small."""

    def cost(blocks: int) -> float:
        bits = (64 // blocks) * (blocks - radius)
        return math.comb(blocks, radius) * (1 + n / 2**bits / 512)

    return min(range(radius + 1, radius + 1 + MOST_PIECES), key=cost)


def _block_keys(radius: int, blocks: int) -> Column:
    """Every choice of ``blocks - radius`` of the 64-bit word's pieces, as (choice, value)."""
    sizes = [64 // blocks + (i < 64 % blocks) for i in range(blocks)]
    starts = [sum(sizes[:i]) for i in range(blocks)]
    piece = [F.shiftrightunsigned("w0", s).bitwiseAND(F.lit((1 << n) - 1)) for s, n in zip(starts, sizes)]
    keys = []
    for k, chosen in enumerate(combinations(range(blocks), blocks - radius)):
        value = F.lit(0).cast("long")
        for i in chosen:
            value = F.shiftleft(value, sizes[i]).bitwiseOR(piece[i])
        keys.append(F.struct(F.lit(k).alias("choice"), value.alias("value")))
    return F.explode(F.array(*keys))


def deal_tiles(grouped: DataFrame, columns: list[str], tile: int, scratch: Scratch, radius: int | None = None, weight: Column | None = None, most_weight: int = 0) -> DataFrame:
    """Rows of groups (choice, value) to pairs of tiles (i, j): every two rows of a group meet
    in one pair, or, with a radius, every two whose bit counts (column ``ones``) differ by no
    more. ``side`` tells the tiles of a pair apart. Groups of one row are left out; a tile has
    about ``tile`` rows, and ``most_weight`` of the weight, if one is given."""
    tiles = F.ceil(F.count("*") / F.lit(tile))
    if weight is not None:
        tiles = F.greatest(tiles, F.ceil(F.sum(weight) / F.lit(most_weight)))
    sizes = grouped.groupBy("choice", "value").agg(F.count("*").alias("n"), tiles.cast("int").alias("tiles")).where("n > 1").drop("n")
    sizes = scratch.save(sizes, "sizes")
    large = sizes.where("tiles > 1")
    zero = F.lit(0).cast("long")
    whole = grouped.join(sizes.where("tiles = 1"), ["choice", "value"]).select("choice", "value", "id", *columns, zero.alias("i"), zero.alias("j"), F.lit(0).alias("side"))
    if large.isEmpty():
        return whole
    cut = grouped.join(large, ["choice", "value"])
    shift = F.lit(1 << 32).cast("long")
    if radius is None:
        dealt = cut.withColumn("mine", F.pmod(F.xxhash64("id"), F.col("tiles"))).withColumn("other", F.explode(F.sequence(zero, F.col("tiles").cast("long") - 1)))
    else:
        bands = cut.groupBy("choice", "value", "ones").agg(F.ceil(F.count("*") / F.lit(tile)).cast("long").alias("parts"))
        bands = scratch.save(bands.groupBy("choice", "value").agg(F.collect_list(F.struct("ones", "parts")).alias("bands")), "bands")
        own = F.filter("bands", lambda x: x["ones"] == F.col("ones"))[0]["parts"]
        near = F.filter("bands", lambda x: F.abs(x["ones"] - F.col("ones")) <= radius)
        others = F.flatten(F.transform(near, lambda x: F.transform(F.sequence(zero, x["parts"] - 1), lambda part: x["ones"] * shift + part)))
        dealt = cut.join(bands, ["choice", "value"]).withColumn("mine", F.col("ones") * shift + F.pmod(F.xxhash64("id"), own)).withColumn("other", F.explode(others))
    return whole.unionByName(dealt.select(
        "choice", "value", "id", *columns, F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), (F.col("mine") > F.col("other")).cast("int").alias("side"),
    ))


TILE_KEYS = ["choice", "value", "i", "j"]
LINKS = "a long, b long"


def over_tiles(compare):
    """A mapInArrow function that gives each pair of tiles, from rows sorted by TILE_KEYS, to
    ``compare(table, lone)``; it returns arrays (a, b)."""

    def run(batches):
        kept: list[pa.RecordBatch] = []

        def flush(table: pa.Table):
            cols = [table.column(c).to_numpy() for c in TILE_KEYS]
            turn = (np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1).tolist()
            out = []
            for s, e in zip([0, *turn], [*turn, len(table)]):
                if e - s > 1:
                    out.append(compare(table.slice(s, e - s), cols[2][s] == cols[3][s]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out)], names=["a", "b"])

        for batch in batches:
            if not len(batch):
                continue
            kept.append(batch)
            table = pa.Table.from_batches(kept)
            last = [table.column(c)[-1].as_py() for c in TILE_KEYS]
            tail = np.all([table.column(c).to_numpy() == v for c, v in zip(TILE_KEYS, last)], axis=0)
            cut = int(np.argmax(tail))
            if cut:
                yield from flush(table.slice(0, cut))
                kept = table.slice(cut).to_batches()
        if kept:
            yield from flush(pa.Table.from_batches(kept))

    return run


def forest(points: DataFrame, radius: int, tile: int = 16384, blocks: int | None = 5, ratio: float = 0.0, scratch: Scratch | None = None) -> DataFrame:
    """Distinct fingerprints ``(id, w0[, w1])`` to links ``(a, b)`` that connect the same parts as
    all pairs within ``radius`` bits do. ``blocks=None`` compares whole tiles. With a ``ratio``
    points also hold ``n_shingles`` and ``bands``: rows that share a band are compared, sets whose
    sizes rule that Jaccard similarity out are not, and short sets link whatever their bits.
    """
    scratch = scratch or Scratch(points.sparkSession, "forest")
    words = [c for c in ("w0", "w1") if c in points.columns]
    columns = words + ["n_shingles"] * (ratio > 0)
    ones = sum((F.bit_count(c) for c in words[1:]), F.bit_count("w0")).cast("long").alias("ones")
    if ratio > 0:
        grouped = points.select("id", F.posexplode("bands").alias("choice", "value"))
    elif blocks is not None:
        grouped = points.select("id", *columns, ones, _block_keys(radius, blocks).alias("g")).select("id", *columns, "ones", "g.choice", "g.value")
    else:
        grouped = points.select("id", *columns, ones, F.lit(0).alias("choice"), F.lit(0).cast("long").alias("value"))

    def compare(table: pa.Table, lone: bool):
        bits = np.stack([table.column(c).to_numpy().view(np.uint64) for c in words], axis=1)
        sizes = table.column("n_shingles").to_numpy() if ratio > 0 else None
        return tile_forest(bits, table.column("id").to_numpy(), table.column("side").to_numpy(), lone, radius, sizes, ratio)

    if ratio > 0:
        # most bands are no one else's: fingerprints follow only to the rows that meet another
        dealt = deal_tiles(grouped, [], tile, scratch).join(points.select("id", *columns), "id")
    else:
        dealt = deal_tiles(grouped, columns, tile, scratch, radius)
    return dealt.repartition(*TILE_KEYS).sortWithinPartitions(*TILE_KEYS).mapInArrow(tidy(over_tiles(compare)), LINKS).distinct()


def shingle_sets(docs: DataFrame, shingle: int) -> DataFrame:
    """``(id, shingles)``: sorted distinct 64-bit shingle hashes as bytes."""

    def run(batches):
        for batch in batches:
            data, offsets = utf8_view(batch.column(1))
            out = []
            for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
                pieces = list(shingle_hashes(word_list(data, a, b), shingle))
                out.append(np.unique(np.concatenate(pieces)).tobytes() if pieces else b"")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["id", "shingles"])

    return docs.select("id", "text").mapInArrow(tidy(run), "id long, shingles binary")


def verified_links(ids: np.ndarray, sets: list[np.ndarray], pairs: Iterator[tuple[np.ndarray, np.ndarray]], similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Exact Jaccard links among candidate pairs of rows, as a forest. Rows that already hang
    together are not compared again, so a tile of near copies costs about one comparison a row."""
    rank = np.argsort(np.argsort(ids, kind="stable"), kind="stable")
    labels, by_rank = np.arange(len(ids)), np.sort(ids, kind="stable")
    for x, y in pairs:
        while True:
            open_ = labels[rank[x]] != labels[rank[y]]
            x, y = x[open_], y[open_]
            if not len(x):
                break
            good = []
            for k, (i, j) in enumerate(zip(x[:VERIFY_CHUNK].tolist(), y[:VERIFY_CHUNK].tolist())):
                a, b = sets[i], sets[j]
                common = len(np.intersect1d(a, b, assume_unique=True))
                if common >= similarity * (len(a) + len(b) - common):
                    good.append(k)
            settle(labels, rank[x[good]], rank[y[good]])
            x, y = x[VERIFY_CHUNK:], y[VERIFY_CHUNK:]
    moved = np.flatnonzero(labels != np.arange(len(labels)))
    return by_rank[moved], by_rank[labels[moved]]


def similar_documents(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, scratch: Scratch | None = None, tile: int = 2048) -> DataFrame:
    """``(doc_id, component_id)``: documents whose sets of ``shingle``-word shingles have a
    Jaccard similarity of ``similarity`` or more hang together; one row per distinct doc_id.

    Candidates share one of BANDS min-hash bands and lie, if their sets have more than SHORT
    members, within a radius of their 128-bit fingerprints that is SPREAD standard deviations
    beyond the expected distance at that similarity. Candidates form work units, inside which
    links are verified on the shingle sets before they count. A pair at similarity 0.8 is lost
    with a chance of about 4e-6, one above it with less. Texts without words hang together. Rows
    that share a doc_id are one document, whose first text in order of fingerprints counts; null
    ids take no part.
    """
    scratch = scratch or Scratch(docs.sparkSession, "similar")
    angle = math.acos(2 * similarity / (1 + similarity)) / math.pi
    radius = math.ceil(128 * angle + SPREAD * math.sqrt(128 * angle * (1 - angle)))
    same = ["w0", "w1", "n_shingles"]
    rows = fingerprints(docs.where("doc_id is not null"), shingle, wide=True)
    marked = scratch.save(rows.groupBy("doc_id").agg(F.min(F.struct(*same, "bands")).alias("f")).select("doc_id", "f.*"), "fingerprints")
    groups = scratch.save(marked.groupBy(*same).agg(F.min("doc_id").alias("id"), F.first("bands").alias("bands")), "groups")
    near = scratch.save(forest(groups, radius, tile, None, similarity, scratch), "near")
    parts = scratch.save(components(near, scratch), "parts")
    texts = docs.select(F.col("doc_id").alias("id"), "text").join(parts.select(F.col("node").alias("id")), "id", "left_semi")
    members = (F.octet_length("shingles") / 8).cast("long").alias("n_shingles")
    sets = shingle_sets(texts, shingle).select("id", members, "shingles").groupBy("id", "n_shingles").agg(F.min("shingles").alias("shingles"))
    known = groups.select("id", *same).join(parts.select(F.col("node").alias("id"), F.lit(0).alias("choice"), F.col("component").alias("value")), "id")
    grouped = scratch.save(sets.join(known, ["id", "n_shingles"]), "sets")

    def compare(table: pa.Table, lone: bool):
        ids, side = table.column("id").to_numpy(), table.column("side").to_numpy()
        bits = np.stack([table.column(c).to_numpy().view(np.uint64) for c in ("w0", "w1")], axis=1)
        sizes = table.column("n_shingles").to_numpy()
        order = ordered_tile(bits, ids, side, sizes, similarity)
        held = table.column("shingles").to_pylist()
        held = [np.frombuffer(held[k], np.uint64) for k in order.tolist()]
        return verified_links(ids[order], held, tile_pairs(bits[order], side[order], lone, radius, sizes[order], similarity), similarity)

    dealt = deal_tiles(grouped, ["shingles", *same], VERIFY_TILE, scratch, weight=F.octet_length("shingles"), most_weight=VERIFY_BYTES)
    links = dealt.repartition(*TILE_KEYS).sortWithinPartitions(*TILE_KEYS).mapInArrow(tidy(over_tiles(compare)), LINKS)
    named = components(links, scratch)
    final = groups.join(named, groups["id"] == named["node"], "left").select(*same, F.coalesce("component", "id").alias("component_id"))
    return marked.join(final, same).select("doc_id", "component_id")


def near_duplicates(docs: DataFrame, shingle: int = 4, radius: int = 4, scratch: Scratch | None = None, tile: int = 16384) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``, one row per input row.

    Null, empty and blank texts have fingerprint zero and link with one another like any other
    fingerprint. Equal fingerprints are joined before any comparison, so groups of copies cost
    one row each. Repeated rows give repeated result rows; a null doc_id keeps its fingerprint
    and takes its group's component; extra columns are ignored; an empty table gives an empty
    result.
    """
    scratch = scratch or Scratch(docs.sparkSession, "simhash")
    marked = scratch.save(fingerprints(docs, shingle), "fingerprints")
    groups = scratch.save(marked.groupBy("w0").agg(F.min("doc_id").alias("id")), "groups")
    links = forest(groups.where("id is not null"), radius, tile, pieces_for(groups.count(), radius) if radius <= 8 else None, scratch=scratch)
    named = components(links, scratch)
    parts = groups.join(named, groups["id"] == named["node"], "left").select("w0", F.coalesce("component", "id").alias("component_id"))
    return marked.join(parts, "w0").select("doc_id", F.lower(F.lpad(F.hex("w0"), 16, "0")).alias("fingerprint"), "component_id")
