"""Local max over resident arcs: windows give each cell its vertex's best edge, edges pass the
flags between the two cells of an edge, and survivors move together. No step writes one place
twice. ``primitive_flags`` is the same phase from scatter and gather."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, Window as W, functions as F

from ..edges import arcs
from ..storage import Scratch
from .scan import gather, prefix_sum, scatter


def phase_flags(cells: DataFrame, key: str = "eid") -> DataFrame:
    """Cells ``(vertex, other, eid)`` with ``matched`` and ``deleted`` after one phase."""
    at_vertex, at_edge = W.partitionBy("vertex"), W.partitionBy("eid")
    best = F.max(key).over(at_vertex)
    mine = cells.withColumn("best", (F.col(key) == best).cast("int"))
    mutual = mine.withColumn("matched", F.sum("best").over(at_edge) == 2)
    spread = mutual.withColumn("hit", F.max("matched").over(at_vertex))
    return spread.withColumn("deleted", F.max("hit").over(at_edge)).drop("best", "hit")


def move_cells(cells: DataFrame, scratch: Scratch) -> DataFrame:
    """Drops the cells of deleted edges, moves the others up by a prefix sum of the flags, and
    points each cell at the new place of its twin."""
    shifted = prefix_sum(cells, ["pos"], F.col("deleted").cast("long"), scratch, "shift").where("not deleted")
    moved = scratch.save(shifted.select(F.col("pos").alias("was"), (F.col("pos") - F.col("shift")).alias("pos"), "vertex", "other", "eid", "twin"), "moved")
    twins = moved.select(F.col("was").alias("twin"), F.col("pos").alias("twin_pos"))
    return gather(moved, "twin", twins, "twin").select("pos", "vertex", "other", "eid", F.col("twin_pos").alias("twin"))


def primitive_flags(cells: DataFrame) -> DataFrame:
    """``phase_flags`` from scatter and gather alone: cells ``(pos, vertex, other, eid, twin)`` write
    their edge to their vertex, read the best back, tell their twin, and mark the vertex."""
    best = scatter(cells, "vertex", "eid", "max").withColumnRenamed("eid", "best")
    mine = gather(cells, "vertex", best).withColumn("mine", F.col("eid") == F.col("best")).drop("best")
    told = gather(mine, "twin", mine.select("pos", F.col("mine").alias("theirs")))
    mutual = told.withColumn("matched", F.col("mine") & F.col("theirs")).drop("mine", "theirs")
    gone = scatter(mutual, "vertex", "matched", "or").withColumnRenamed("matched", "hit")
    marked = gather(mutual, "vertex", gone)
    other = gather(marked, "twin", marked.select("pos", F.col("hit").alias("twin_hit")))
    return other.withColumn("deleted", F.col("hit") | F.col("twin_hit")).drop("hit", "twin_hit")


def run(ordered: DataFrame, scratch: Scratch, max_phases: int, flags=phase_flags) -> tuple[DataFrame, list[dict]]:
    """``(eid, phase)`` of the matched edges and the log of all phases. Cells lie by vertex at
    places 0, 1, 2 ..; after a phase the survivors move together and twins are pointed anew."""
    from .adjacency import build_adjacency, twin_positions
    from .localmax import _line

    _, placed = build_adjacency(ordered, scratch)
    cells = scratch.save(twin_positions(placed).withColumnRenamed("twin_pos", "twin"), "cells")
    count, phase, log, parts = cells.count() // 2, 0, [], []
    while count:
        phase += 1
        if phase > max_phases:
            raise RuntimeError(f"{count} edges are left after {max_phases} phases")
        began = time.time()
        flagged = scratch.save(flags(cells), "flags")
        won = scratch.save(flagged.where("matched and vertex < other").select("eid", F.lit(phase).alias("phase")), "won")
        parts.append(won)
        left = scratch.save(move_cells(flagged, scratch), "cells")
        n_won, n_left = won.count(), left.count() // 2
        log.append(_line(phase, count, n_won, n_left, time.time() - began))
        scratch.drop(cells, flagged)
        cells, count = left, n_left
    if not parts:
        return ordered.select("eid", F.lit(0).alias("phase")).where("false"), log
    return reduce(DataFrame.unionByName, parts), log
