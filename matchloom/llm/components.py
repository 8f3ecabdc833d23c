"""Connected components over an edge table, by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .storage import Scratch


def _largest_hooks(arcs: DataFrame) -> DataFrame:
    """Each vertex hangs its larger neighbours under its least neighbour (or itself)."""
    least = arcs.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return arcs.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))


def _smallest_hooks(pairs: DataFrame) -> DataFrame:
    """Each vertex hangs its smaller neighbours and itself under the least of them."""
    least = pairs.groupBy("a").agg(F.min("b").alias("m"))
    moved = pairs.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(least.select("a", F.col("m").alias("b")))


def components(edges: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """Edges ``(a, b)`` of longs to ``(node, component)``, component = least node reachable.

    Loops, repeated and reversed pairs and an empty table are fine; nodes without an edge to
    another node are not in the result. Each round is written to the shared folder, sums of
    hashes tell the fixed point. ``max_rounds`` is a guard that raises, it drops nothing.
    """
    pairs = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    pairs = scratch.save(pairs, "links")
    state = None
    for _ in range(max_rounds):
        now = pairs.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(now) == state or now[0] == 0:
            return pairs.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(pairs.select(F.col("b").alias("node"), F.col("b").alias("component"))).distinct()
        state = tuple(now)
        arcs = pairs.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(pairs.select(F.col("b").alias("u"), F.col("a").alias("v")))
        wide = _largest_hooks(arcs).where("a <> b").distinct()
        fresh = scratch.save(_smallest_hooks(wide).where("a <> b").distinct(), "stars")
        scratch.drop(pairs)
        pairs = fresh
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
