"""Multilevel contraction: rate the edges, match, merge matched pairs, repeat."""

from __future__ import annotations

from collections.abc import Callable
from itertools import count

from pyspark.sql import DataFrame, functions as F

from ..edges import arcs
from ..storage import Scratch
from .localmax import local_max

SCALE = 1_000_000


def rate_edges(edges: DataFrame, vertex_weight: DataFrame, kind: str | Callable = "weight") -> DataFrame:
    """Adds ``rating``, a long. ``weight``: w; ``expansion2``: w^2 over the product of the vertex
    weights; ``inner_outer``: w over the weight that leaves the pair; or a function of a frame
    with w, cu, cv (vertex weights) and du, dv (weighted degrees) to a column."""
    if kind == "weight":
        return edges.withColumn("rating", F.col("w"))
    outer = arcs(edges, "w").groupBy("vertex").agg(F.sum("w").alias("d"))
    rated = edges
    for c in "uv":
        rated = rated.join(vertex_weight.select(F.col("vertex").alias(c), F.col("c").alias(f"c{c}")), c)
        if kind != "expansion2":  # which asks for no weighted degrees
            rated = rated.join(outer.select(F.col("vertex").alias(c), F.col("d").alias(f"d{c}")), c)
    w = F.col("w").cast("double")
    if kind == "expansion2":
        value = w * w / (F.col("cu") * F.col("cv"))
    elif kind == "inner_outer":
        out = F.col("du") + F.col("dv") - 2 * F.col("w")
        value = F.when(out > 0, w / out).otherwise(w * SCALE)
    else:
        value = kind(rated)
    return rated.withColumn("rating", F.greatest(F.floor(value * SCALE).cast("long"), F.lit(1))).select(*edges.columns, "rating")


def contract(edges: DataFrame, matching: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(coarse_map(vertex, coarse), coarse edges)``: a pair goes by its smaller vertex, loops
    go, parallel edges add up."""
    vertices = arcs(edges).select("vertex").distinct()
    merged = vertices.join(matching.select(F.col("v").alias("vertex"), F.col("u").alias("mate")), "vertex", "left")
    names = merged.select("vertex", F.coalesce("mate", "vertex").alias("coarse"))
    ends = [names.select(F.col("vertex").alias(c), F.col("coarse").alias(f"n{c}")) for c in "uv"]
    moved = edges.join(ends[0], "u").join(ends[1], "v").where("nu <> nv")
    return names, moved.groupBy(F.least("nu", "nv").alias("u"), F.greatest("nu", "nv").alias("v")).agg(F.sum("w").alias("w"))


def coarsen(edges: DataFrame, rating: str | Callable = "weight", min_vertices: int = 32, max_levels: int | None = 20, **options) -> list[dict]:
    """Levels of the hierarchy: each a dict of level, edges, coarse_map, vertex_weight, matching
    and log, until few vertices are left or nothing is matched; ``max_levels`` (None: no bound)
    ends it before."""
    scratch = Scratch(edges.sparkSession, "coarsen")
    live = scratch.save(edges.select("u", "v", "w"), "level")
    weights = scratch.save(arcs(live).select("vertex").distinct().withColumn("c", F.lit(1).cast("long")), "weights")
    levels = []
    for level in count(1) if max_levels is None else range(1, max_levels + 1):
        if live.isEmpty() or weights.count() <= min_vertices:
            break
        # written: the sort by range would rate the edges twice
        rated = scratch.save(rate_edges(live, weights, rating).select("u", "v", F.col("rating").alias("w")), "rated")
        result = local_max(rated, scratch=scratch, **options)
        scratch.drop(rated)
        names, coarse = contract(live, result.matching)
        names = scratch.save(names, "map")
        coarse = scratch.save(coarse, "level")
        fresh = weights.join(names, "vertex", "left").groupBy(F.coalesce("coarse", "vertex").alias("vertex")).agg(F.sum("c").alias("c"))
        fresh = scratch.save(fresh, "weights")
        levels.append({"level": level, "edges": live, "coarse_map": names, "vertex_weight": fresh, "matching": result.matching, "log": result.log, "coarse": coarse})
        live, weights = coarse, fresh
    return levels
