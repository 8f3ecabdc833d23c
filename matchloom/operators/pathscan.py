"""Long paths in bounded tasks: list order by pointer doubling, and the heaviest matching of a
path as a (max, +) product over segments.

A link that is taken rules out the next one. What a segment does to its surroundings is told by
four numbers: the best weight inside it for each state (taken or not) of the link before it and
of its own last link. Those 2 x 2 tables multiply, so segments of SEGMENT links are folded
level by level until one table is left for each path, and choices are read back down the levels.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..edges import arcs
from ..functions.kernels import path_optimum
from ..storage import Scratch

SEGMENT = 4096
MOST_DOUBLINGS = 64
NONE = -math.inf


def rank_links(links: DataFrame, scratch: Scratch) -> DataFrame:
    """Adds ``place``, ``is_cycle`` and ``length`` to ``(eid, u, v, w, comp)``. A path is read from
    its end with the smaller id; a cycle from its least vertex, over its smaller neighbour."""
    both = scratch.save(arcs(links, "eid", "comp").select("eid", "comp", F.col("vertex").alias("tail"), F.col("other").alias("head")), "arcs")
    count = both.groupBy("comp", "tail").agg(F.count("*").alias("d"))
    shape = scratch.save(count.groupBy("comp").agg((F.min("d") == 2).alias("is_cycle"), F.min("tail").alias("least"), (F.sum("d") / 2).cast("long").alias("length")), "shape")
    arc = (F.col("eid") * 2 + (F.col("tail") < F.col("head")).cast("long")).alias("arc")
    named = both.join(shape, "comp").select("comp", "eid", "tail", "head", arc, (F.col("is_cycle") & (F.col("head") == F.col("least"))).alias("stops"))
    ahead = both.select(F.col("tail").alias("head"), F.col("eid").alias("then"), arc.alias("next"))
    met = named.join(ahead, "head", "left").groupBy("arc", "eid", "tail", "head", "stops").agg(F.max(F.when(F.col("then") != F.col("eid"), F.col("next"))).alias("next"))
    # beyond the last arc there is nothing: where it leads, and from where, names the end
    state = scratch.save(met.select("arc", "eid", F.when(~F.col("stops"), F.col("next")).alias("next"), F.lit(1).cast("long").alias("steps"), F.struct("head", "tail").alias("last")), "state")
    for _ in range(MOST_DOUBLINGS):
        if state.where("next is not null").isEmpty():
            break
        further = state.select(F.col("arc").alias("next"), F.col("next").alias("beyond"), F.col("steps").alias("more"), F.col("last").alias("end"))
        moved = state.join(further, "next", "left")
        fresh = scratch.save(moved.select("arc", "eid", F.col("beyond").alias("next"), (F.col("steps") + F.coalesce("more", F.lit(0))).alias("steps"), F.coalesce("end", "last").alias("last")), "state")
        scratch.drop(state)
        state = fresh
    else:
        raise RuntimeError("list order did not settle")
    placed = state.groupBy("eid").agg((F.min_by("steps", "last") - 1).alias("place"))
    return links.join(placed, "eid").join(shape.select("comp", "is_cycle", "length"), "comp")


def sorted_runs(batches, keys: list[str]) -> Iterator[pa.Table]:
    """Tables of the rows that agree in ``keys``, from batches sorted by them."""
    kept: list[pa.Table] = []
    for batch in batches:
        if not len(batch):
            continue
        table = pa.Table.from_batches([batch])
        cols = [table.column(c).to_numpy() for c in keys]
        turn = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        at = [0, *turn.tolist(), len(table)]
        if kept and any(kept[-1].column(c)[-1].as_py() != c0[0] for c, c0 in zip(keys, cols)):
            yield pa.concat_tables(kept)
            kept = []
        for a, b in zip(at[:-2], at[1:-1]):
            yield pa.concat_tables([*kept, table.slice(a, b - a)])
            kept = []
        kept.append(table.slice(at[-2]))
    if kept:
        yield pa.concat_tables(kept)


def link_table(weights: list[int]) -> list[list[float]]:
    """Best weight of a run of links by the state before it and that of its last link."""
    out = []
    for before in (0, 1):
        skip, take = (0.0, NONE) if not before else (NONE, 0.0)
        for w in weights:
            skip, take = max(skip, take), skip + w
        out.append([skip, take])
    return out


def product(tables: list) -> list[list[float]]:
    out = tables[0]
    for t in tables[1:]:
        out = [[max(out[a][0] + t[0][b], out[a][1] + t[1][b]) for b in (0, 1)] for a in (0, 1)]
    return out


def states(tables: list, before: int, last: int) -> list[int]:
    """State after each table on the best way from ``before`` to ``last``; not taken where equal."""
    best = [[NONE, NONE]]
    best[0][before] = 0.0
    for t in tables:
        best.append([max(best[-1][0] + t[0][b], best[-1][1] + t[1][b]) for b in (0, 1)])
    out, at = [], last
    for k in range(len(tables), 0, -1):
        out.append(at)
        at = int(best[k - 1][1] + tables[k - 1][1][at] > best[k - 1][0] + tables[k - 1][0][at])
    return out[::-1]


CELLS = ("m00", "m01", "m10", "m11")
TABLE = "comp long, variant int, part long, " + ", ".join(f"{c} double" for c in CELLS)


def read_tables(run: pa.Table) -> list:
    cols = [run.column(c).to_pylist() for c in CELLS]
    return [[[a, b], [c, d]] for a, b, c, d in zip(*cols)]


def optimum_links(ranked: DataFrame, scratch: Scratch, segment: int = SEGMENT) -> DataFrame:
    """``(eid, u, v, comp)`` of the links that the heaviest matching of their path or cycle takes.
    Paths of up to ``segment`` links are solved where they lie, longer ones by segments; a cycle is
    the better of two paths, one without its first link and one without its last."""
    kept = ["eid", "u", "v", "comp"]

    def whole(batches):
        for run in sorted_runs(batches, ["comp"]):
            taken = sorted(path_optimum(run.column("w").to_pylist(), run.column("is_cycle")[0].as_py()))
            yield from run.select(kept).take(pa.array(taken, pa.int64())).to_batches()

    short = ranked.where(F.col("length") <= segment).repartition("comp").sortWithinPartitions("comp", "place").mapInArrow(whole, "eid long, u long, v long, comp long")
    long = scratch.save(ranked.where(F.col("length") > segment), "long")
    return short if long.isEmpty() else short.unionByName(long_optimum(long, scratch, segment))


def long_optimum(ranked: DataFrame, scratch: Scratch, segment: int) -> DataFrame:
    """``optimum_links`` by segments."""
    variant = F.explode(F.when(F.col("is_cycle"), F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(2)))).alias("variant")
    rows = ranked.select("comp", "place", "w", "eid", "u", "v", "length", variant)
    rows = rows.where("variant = 2 or variant = 0 and place > 0 or variant = 1 and place < length - 1").drop("length")
    rows = scratch.save(rows.withColumn("part", F.floor(F.col("place") / segment)), "rows")
    keys = ["comp", "variant", "part"]

    def dealt(table: DataFrame, order: str) -> DataFrame:
        return table.repartition(*keys).sortWithinPartitions(*keys, order)

    def row(run: pa.Table, t) -> pa.RecordBatch:
        return pa.RecordBatch.from_pylist([{"comp": run.column("comp")[0].as_py(), "variant": run.column("variant")[0].as_py(), "part": run.column("part")[0].as_py(), "m00": t[0][0], "m01": t[0][1], "m10": t[1][0], "m11": t[1][1]}], schema=schema)

    schema = pa.schema([("comp", pa.int64()), ("variant", pa.int32()), ("part", pa.int64()), *((c, pa.float64()) for c in CELLS)])

    def from_links(batches):
        for run in sorted_runs(batches, keys):
            yield row(run, link_table(run.column("w").to_pylist()))

    def from_tables(batches):
        for run in sorted_runs(batches, keys):
            yield row(run, product(read_tables(run)))

    levels = [scratch.save(dealt(rows, "place").mapInArrow(from_links, TABLE), "tables")]
    while not levels[-1].where("part > 0").isEmpty():
        finer = levels[-1].withColumnRenamed("part", "sub").withColumn("part", F.floor(F.col("sub") / segment))
        levels.append(scratch.save(dealt(finer, "sub").mapInArrow(from_tables, TABLE), "tables"))
    # at the top nothing lies before a path, and the better variant of a cycle wins
    value = F.greatest("m00", "m01")
    top = levels[-1].select("comp", "variant", "part", value.alias("value"), (F.col("m01") > F.col("m00")).cast("int").alias("last"))
    best = top.groupBy("comp").agg(F.max_by("variant", F.struct("value", -F.col("variant"))).alias("variant"))
    wanted = top.join(best, ["comp", "variant"]).select(*keys, F.lit(0).alias("before"), "last")
    for level in reversed(levels[:-1]):
        finer = level.withColumnRenamed("part", "sub").withColumn("part", F.floor(F.col("sub") / segment))

        def down(batches):
            for run in sorted_runs(batches, keys):
                after = states(read_tables(run), run.column("before")[0].as_py(), run.column("last")[0].as_py())
                yield pa.RecordBatch.from_pydict({"comp": run.column("comp").to_pylist(), "variant": pa.array(run.column("variant").to_pylist(), pa.int32()), "part": run.column("sub").to_pylist(), "before": pa.array([run.column("before")[0].as_py(), *after[:-1]], pa.int32()), "last": pa.array(after, pa.int32())})

        wanted = scratch.save(dealt(finer.join(wanted, keys), "sub").mapInArrow(down, "comp long, variant int, part long, before int, last int"), "wanted")

    def choose(batches):
        for run in sorted_runs(batches, keys):
            tables = [[[0.0, w], [0.0, NONE]] for w in map(float, run.column("w").to_pylist())]
            after = states(tables, run.column("before")[0].as_py(), run.column("last")[0].as_py())
            yield from run.select(["eid", "u", "v", "comp"]).filter(pa.array([s == 1 for s in after])).to_batches()

    return dealt(rows.join(wanted, keys), "place").mapInArrow(choose, "eid long, u long, v long, comp long")
