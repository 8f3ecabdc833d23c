"""Embedding near-duplicates: spherical k-means cells, blocked cosine products inside them.

A vector is compared with its whole cell, and the cell also gets every vector of another cell
that could lie within the threshold: if y is nearer to centre b than to a, then no x with
|x - y| <= d (the chord of the threshold) has (x.a - x.b) above d |a - b|. So each vector's links are complete in its own cell and no pair is lost at the borders.

Cells follow the rows: those of more than CELL_ROWS vectors are cut again, each by k-means on a
bounded sample of its own, until they are small or cutting does not pay. It pays where vectors
cluster; without clusters a vector has to visit nearly every cell, the sample shows that, and
cells stay larger. Equal vectors are one row with a multiplicity.

A cell whose rows would be dealt out more than MOST_COPIES times stays whole, and a whole cell of
more than ``tile`` rows is written once, as tiles of rows in order of k-means cells of its own.
Each two tiles meet by a replicated scan of the written tiles, which shuffles nothing; in them two
k-means cells are compared by those of their rows that have to visit the other one. So disk
follows the rows, whatever the number of pairs. Out of a task come counts and a forest, never
all pairs.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .components import components
from .simhash import settle
from .storage import Scratch
from .textkernels import tidy
from .vectors import decode, distinct_vectors, kept_kind, packed

#: Rows of the sample that the centres of one cell are fitted on, and most centres at a time.
FIT_SAMPLE = 8_192
MOST_CENTRES = 128
CELL_ROWS = 256
#: Comparisons that cost as much as dealing out one more copy of a row.
ROW_COST = 400
MOST_LEVELS = 12
PART_ROWS = 8_192
TILE = 4_096
STRIP = 128
#: Rows that a cut may deal out for each row of a cell.
MOST_COPIES = 1.5


def unit(rows: np.ndarray) -> np.ndarray:
    scale = np.abs(rows).max(axis=1, keepdims=True)  # keeps squares in range
    rows = rows / scale
    return rows / np.sqrt((rows**2).sum(axis=1, keepdims=True))


def spherical_centres(sample: np.ndarray, cells: int, seed: int = 11, rounds: int = 8) -> np.ndarray:
    """Spherical k-means on unit rows; an emptied cell restarts at the worst-served row."""
    rng = np.random.default_rng(seed)
    cells = min(cells, len(sample))
    centres = sample[rng.choice(len(sample), cells, replace=False)]
    for _ in range(rounds):
        near = sample @ centres.T
        home = near.argmax(axis=1)
        for c in range(cells):
            own = sample[home == c]
            total = own.sum(axis=0) if len(own) else sample[near.max(axis=1).argmin()]
            size = np.linalg.norm(total)
            if size > 0:
                centres[c] = total / size
    return centres


def visits(rows: np.ndarray, centres: np.ndarray, chord: float) -> tuple[np.ndarray, np.ndarray]:
    """For unit rows the home centre of each, and which centres' cells it has to visit."""
    near = rows @ centres.T
    home = near.argmax(axis=1)
    reach = chord * np.sqrt(np.maximum(2 - 2 * centres @ centres.T, 0)) + 1e-9
    out = near[np.arange(len(rows)), home][:, None] - near <= reach[home]
    out[np.arange(len(rows)), home] = True
    return home, out


def fit_centres(sample: np.ndarray, n: int, chord: float, at_least: int = 1, cell_rows: int = CELL_ROWS, most: int = MOST_CENTRES, row_cost: int = ROW_COST, most_copies: float = math.inf) -> np.ndarray | None:
    """Centres for a cell of n rows, as many as make its comparison cheapest by the sample, or
    None if it should stay whole. ``at_least`` 2 always cuts, but never into more than
    ``most_copies`` of a row."""
    tries, k = [], min(most, len(sample), max(2, -(-n // cell_rows)))
    while k >= 2:
        tries.append(k)
        k = k // 4 if k > 4 else k // 2
    best, cost = None, row_cost + n if at_least < 2 else math.inf
    probe = sample[:: max(1, len(sample) // 512)]
    for k in tries:
        centres = spherical_centres(sample, k)
        home, seen = visits(probe, centres, chord)
        if seen.sum(axis=1).mean() > most_copies:
            continue
        share = np.bincount((sample @ centres.T).argmax(axis=1), minlength=len(centres)) / len(sample)
        # rows that each visited cell holds at home, and a copy of the row for each cell
        price = float((seen * (share * n + row_cost)[None, :]).sum(axis=1).mean()) + row_cost
        if price < cost:
            best, cost = centres, price
    if best is None and at_least > 1 and most_copies == math.inf:
        return sample[:1]
    return best


def cut_cell(part: pa.Table, centres: np.ndarray, chord: float, kind: type = np.float64) -> pa.Table:
    """Rows ``(id, copies, vec, cell, own)`` of one cell, cut by its centres: a row goes to its
    home cell and to those that it has to visit, and a visitor is one in all of them."""
    home, seen = visits(unit(decode(part.column("vec").to_pylist(), kind)), centres, chord)
    row, sub = np.nonzero(seen)
    out = part.select(["id", "copies", "vec"]).take(pa.array(row))
    cell = part.column("cell")[0].as_py()
    names = pa.array([f"{cell}.{c}" for c in range(len(centres))]).take(pa.array(sub))
    own = part.column("own").to_numpy()[row] & (sub == home[row])
    return out.append_column("cell", names).append_column("own", pa.array(own))


PLACED = "id long, copies long, vec binary, cell string, own boolean"


def fitted_centres(placed: DataFrame, sizes: DataFrame, level: int, kind: type, **options) -> DataFrame:
    """``(cell, parts, centres)`` of the cells in ``sizes``, each fitted on a bounded sample of its
    own rows, without those that should stay whole."""
    drawn = F.pmod(F.xxhash64("id", F.lit(level)), F.col("n")) < FIT_SAMPLE
    sample = placed.where("own").join(sizes, "cell").where(drawn).select("cell", "n", "parts", "vec")

    def fit(table: pa.Table) -> pa.Table:
        centres = fit_centres(unit(decode(table.column("vec").to_pylist(), kind)), table.column("n")[0].as_py(), **options)
        one = table.select(["cell", "parts"]).slice(0, 0 if centres is None else 1)
        return one.append_column("centres", pa.array([] if centres is None else [centres.tobytes()], pa.binary()))

    return sample.groupBy("cell").applyInArrow(fit, "cell string, parts int, centres binary")


def by_parts(placed: DataFrame, fitted: DataFrame, run, schema: str, tasks: int | None = None) -> DataFrame:
    """``run(rows, centres)`` for the parts of each fitted cell."""
    dealt = placed.join(fitted.select("cell", "parts"), "cell").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")))
    shapes = fitted.select("cell", "centres", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts").cast("long") - 1)).alias("part"))
    if tasks is not None:
        dealt, shapes = (x.repartition(tasks, "cell", "part") for x in (dealt, shapes))

    def both(rows: pa.Table, centres: pa.Table) -> pa.Table:
        at = np.frombuffer(centres.column("centres")[0].as_py(), np.float64)
        return run(rows, at)

    empty = pa.schema([(c.split()[0], pa.type_for_alias({"long": "int64", "boolean": "bool"}.get(c.split()[1], c.split()[1]))) for c in schema.split(", ")]).empty_table()
    return dealt.groupBy("cell", "part").cogroup(shapes.groupBy("cell", "part")).applyInArrow(lambda rows, at: both(rows, at) if len(rows) else empty, schema)


def place_in_cells(
    points: DataFrame, threshold: float, scratch: Scratch, cell_rows: int = CELL_ROWS, most: int = MOST_CENTRES, row_cost: int = ROW_COST, most_copies: float = math.inf, kind: type = np.float64
) -> DataFrame:
    """All points ``(id, copies, vec)`` in cells, level by level."""
    chord = math.sqrt(2 - 2 * threshold) + 1e-9
    placed = points.select("id", "copies", "vec", F.octet_length("vec").cast("string").alias("cell"), F.lit(True).alias("own"))
    done = []
    for level in range(MOST_LEVELS):
        sizes = placed.groupBy("cell").agg(F.sum(F.col("own").cast("long")).alias("n"), F.ceil(F.count("*") / PART_ROWS).cast("int").alias("parts"))
        large = scratch.save(sizes.where(F.col("n") > cell_rows), "large")
        # the first level always cuts, later ones where it pays
        options = dict(chord=chord, at_least=2 if level == 0 else 1, cell_rows=cell_rows, most=most, row_cost=row_cost, most_copies=most_copies)
        fitted = scratch.save(fitted_centres(placed, large, level, kind, **options), "fitted")
        if fitted.isEmpty():
            return reduce(DataFrame.unionByName, [*done, placed])
        done.append(scratch.save(placed.join(fitted, "cell", "left_anti"), "whole"))

        def cut(rows: pa.Table, centres: np.ndarray) -> pa.Table:
            return cut_cell(rows, centres.reshape(-1, len(rows.column("vec")[0].as_py()) // kind().itemsize), chord, kind)

        finer = scratch.save(by_parts(placed, fitted, cut, PLACED), "placed")
        scratch.drop(placed)
        placed = finer
    return reduce(DataFrame.unionByName, [*done, placed])


def exact_cosine(x: np.ndarray, y: np.ndarray) -> float:
    return math.fsum(x * y) / math.sqrt(math.fsum(x * x) * math.fsum(y * y))


def hits(x: np.ndarray, y: np.ndarray, threshold: float):
    """``(rows, columns, hit)`` by strips: which of these rows of x and y have that cosine. Single
    precision finds the candidates, by a bound on its error; doubles decide."""
    if not len(x) or not len(y):
        return
    ux, uy = unit(x), unit(y)
    low = threshold - (x.shape[1] + 8) * 1.2e-7
    x32, y32 = ux.astype(np.float32), uy.astype(np.float32)
    for i in range(0, len(x), STRIP):
        near = x32[i : i + STRIP] @ y32.T >= low
        rows = np.flatnonzero(near.any(axis=1))
        if not len(rows):
            continue
        cols = np.flatnonzero(near[rows].any(axis=0))
        rows += i
        cos = ux[rows] @ uy[cols].T
        hit = cos >= threshold
        for r, c in zip(*np.nonzero(np.abs(cos - threshold) < 1e-12)):
            hit[r, c] = exact_cosine(x[rows[r]], y[cols[c]]) >= threshold
        yield rows, cols, hit


LINKS = "kind int, a long, b long"


def link_table(ids: np.ndarray, counts: np.ndarray, names: np.ndarray, labels: np.ndarray) -> pa.Table:
    """``(kind, a, b)``: kind 0 a forest link of ids, kind 1 id a has b linked rows here."""
    some, moved = np.flatnonzero(counts), np.flatnonzero(labels != np.arange(len(names)))
    kind = np.repeat(np.array([1, 0], np.int32), [len(some), len(moved)])
    a, b = np.concatenate([ids[some], names[moved]]), np.concatenate([counts[some], names[labels[moved]]])
    return pa.table({"kind": pa.array(kind), "a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})


def cell_links(table: pa.Table, threshold: float, kind: type = np.float64) -> pa.Table:
    """Links of the rows that are at home in a cell with all of its rows."""
    ids, own = table.column("id").to_numpy(), table.column("own").to_numpy(zero_copy_only=False)
    x, copies = decode(table.column("vec").to_pylist(), kind), table.column("copies").to_numpy()
    names, place = np.unique(ids, return_inverse=True)
    home = np.flatnonzero(own)
    labels, counts = np.arange(len(names)), np.zeros(len(home), np.int64)
    for rows, cols, hit in hits(x[home], x, threshold):
        hit &= ids[home[rows]][:, None] != ids[cols][None, :]
        counts[rows] += hit @ copies[cols]
        r, c = np.nonzero(hit)
        settle(labels, place[home[rows[r]]], place[cols[c]])
    return link_table(ids[home], counts, names, labels)


TILED = "cell string, part long, id binary, copies binary, own binary, home binary, seen binary, vec binary"


def tile_row(rows: pa.Table, centres: np.ndarray, chord: float, kind: type) -> pa.Table:
    """The rows of a part as one row of blobs, in order of their cells among ``centres``."""
    vec = decode(rows.column("vec").to_pylist(), kind)
    home, seen = visits(unit(vec), centres.reshape(-1, vec.shape[1]), chord)
    order = np.argsort(home, kind="stable")
    whole = {"id": rows.column("id").to_numpy(), "copies": rows.column("copies").to_numpy(), "own": rows.column("own").to_numpy(zero_copy_only=False), "home": home.astype(np.int32), "seen": seen, "vec": vec.astype(kind)}
    blobs = {c: pa.array([v[order].tobytes()], pa.binary()) for c, v in whole.items()}
    return pa.table({"cell": rows.column("cell").slice(0, 1), "part": rows.column("part").slice(0, 1), **blobs})


class Tile:
    def __init__(self, row: dict, side: str, kind: type):
        held = lambda c, of: np.frombuffer(row[side + c], of)
        self.ids, self.copies, self.own, self.home = held("id", np.int64), held("copies", np.int64), held("own", bool), held("home", np.int32)
        self.seen, self.vec = (held(c, of).reshape(len(self.ids), -1) for c, of in (("seen", bool), ("vec", kind)))
        self.cells = np.unique(self.home).tolist()

    def facing(self, cell: int, other: int) -> np.ndarray:
        """Rows of a cell that have to visit the other one."""
        return np.flatnonzero((self.home == cell) & self.seen[:, other])


def tile_links(a: Tile, b: Tile, same: bool, threshold: float) -> pa.Table:
    """Links between two tiles, or inside of one; each pair of rows is compared once."""
    names, place = np.unique(np.concatenate([a.ids, b.ids]), return_inverse=True)
    at = place[: len(a.ids)], place[len(a.ids) :]
    labels, counts = np.arange(len(names)), np.zeros(len(names), np.int64)
    for g in a.cells:
        for h in b.cells:
            if same and h < g:
                continue
            x, y = a.facing(g, h), b.facing(h, g)
            for rows, cols, hit in hits(a.vec[x].astype(np.float64), b.vec[y].astype(np.float64), threshold):
                r, c = x[rows], y[cols]
                hit &= a.own[r][:, None] | b.own[c][None, :]
                if same and g == h:
                    hit &= r[:, None] < c[None, :]
                # rows are told apart here, so plain indexed sums do
                counts[at[0][r]] += np.where(a.own[r], hit @ b.copies[c], 0)
                counts[at[1][c]] += np.where(b.own[c], a.copies[r] @ hit, 0)
                i, j = np.nonzero(hit)
                settle(labels, at[0][r[i]], at[1][c[j]])
    return link_table(names, counts, names, labels)


def compare_cells(placed: DataFrame, threshold: float, scratch: Scratch, tile: int = TILE, kind: type = np.float64) -> DataFrame:
    """``(kind, a, b)`` of all cells, see ``link_table``."""
    sizes = placed.groupBy("cell").agg(F.sum(F.col("own").cast("long")).alias("n"), F.ceil(F.count("*") / tile).cast("int").alias("parts")).where("n > 0")
    sizes = scratch.save(sizes, "sizes")
    small, large = sizes.where("parts = 1").select("cell"), sizes.where("parts > 1")
    found = placed.join(small, "cell").groupBy("cell").applyInArrow(lambda table: cell_links(table, threshold, kind), LINKS)
    tiles = large.agg(F.sum("parts")).first()[0]
    if not tiles:
        return found
    chord = math.sqrt(2 - 2 * threshold) + 1e-9
    fitted = scratch.save(fitted_centres(placed, large, MOST_LEVELS, kind, chord=chord, at_least=2, cell_rows=1, most=max(2, tile // 64), row_cost=0), "tile_centres")
    written = scratch.save(by_parts(placed, fitted, lambda rows, at: tile_row(rows, at, chord, kind), TILED, min(tiles, 4096)), "tiles")
    left, right = (written.toDF(*[side + c for c in written.columns]) for side in ("l_", "r_"))
    met = left.join(right.hint("shuffle_replicate_nl"), (F.col("l_cell") == F.col("r_cell")) & (F.col("l_part") <= F.col("r_part")))

    def run(batches):
        for batch in batches:
            for k in range(len(batch)):
                row = batch.slice(k, 1).to_pylist()[0]
                same = row["l_part"] == row["r_part"]
                out = tile_links(Tile(row, "l_", kind), Tile(row, "r_", kind), same, threshold)
                yield from out.to_batches()

    return found.unionByName(met.mapInArrow(tidy(run), LINKS))


def near_duplicates(vectors: DataFrame, threshold: float = 0.95, scratch: Scratch | None = None, id_col: str = "vec_id", vector_col: str = "embedding", tile: int = TILE) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)``, one row per input row.

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing
    and are kept. Vectors of different length never link. Repeated rows are copies of one
    another; rows with a null vec_id link with nothing. Extra columns are ignored; an empty
    table gives an empty result.
    """
    scratch = scratch or Scratch(vectors.sparkSession, "cosine")
    kind = kept_kind(vectors, vector_col)
    every = packed(vectors, id_col, vector_col, kind)
    # vectors are written once, for the points; rows find theirs by 128 bits of a SHA-256
    mark = F.substring(F.unhex(F.sha2("vec", 256)), 1, 16).alias("mark")
    rows = scratch.save(every.select("vec_id", mark), "rows")
    points = scratch.save(distinct_vectors(every), "points")
    placed = place_in_cells(points, threshold, scratch, most_copies=MOST_COPIES, kind=kind)
    found = scratch.save(compare_cells(placed, threshold, scratch, tile, kind), "found")
    marks = points.select("id", "copies", mark)
    named = components(found.where("kind = 0").select("a", "b"), scratch)
    linked = found.where("kind = 1").groupBy("a").agg(F.sum("b").alias("others"))
    groups = (
        marks.join(linked, F.col("id") == F.col("a"), "left").join(named, F.col("id") == F.col("node"), "left")
        .select("mark", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    )
    usable = F.col("mark").isNotNull() & F.col("vec_id").isNotNull()
    joined = rows.where(usable).join(groups, "mark").select("vec_id", "n_links", "component_id")
    lone = rows.where(~usable).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return joined.unionByName(lone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
