"""Adjacency as a table of cells that point at edge records, and what vertices do with it."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, Window as W, functions as F

from ..edges import arcs, degrees
from ..storage import Scratch
from .scan import OPS, prefix_sum


def build_adjacency(edges: DataFrame, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """``vertices(vertex, degree, offset)`` and ``cells(pos, vertex, other, eid)``: the cells of
    a vertex lie from its offset on, by rising eid."""
    vertices = scratch.save(prefix_sum(degrees(edges), ["vertex"], F.col("degree"), scratch, "offset"), "vertices")
    place = F.row_number().over(W.partitionBy("vertex").orderBy("eid")) - 1
    cells = arcs(edges, "eid").withColumn("k", place).join(vertices.select("vertex", "offset"), "vertex")
    return vertices, scratch.save(cells.select((F.col("offset") + F.col("k")).alias("pos"), "vertex", "other", "eid"), "cells")


def twin_positions(cells: DataFrame) -> DataFrame:
    """Adds ``twin_pos``, the place of the same edge's cell at its other end: the edge record
    holds the place of the lower end, then that of the higher, and each reads the other's."""
    record = cells.groupBy("eid").agg(F.min_by("pos", "vertex").alias("low"), F.max_by("pos", "vertex").alias("high"))
    return cells.join(record, "eid").withColumn("twin_pos", F.when(F.col("vertex") < F.col("other"), F.col("high")).otherwise(F.col("low"))).drop("low", "high")


def vertex_reduce(cells: DataFrame, value: str, op: str | Callable = "max", spread: bool = True) -> DataFrame:
    """Reduce ``value`` over the cells of each vertex; ``spread`` puts the result (``reduced``)
    on every cell. A callable takes a pandas Series and must be associative."""
    if callable(op):
        kind = dict(cells.dtypes)[value]

        def whole(values: pd.Series) -> float:
            return op(values)

        udf = F.pandas_udf(whole, kind)
        small = cells.groupBy("vertex").agg(udf(F.col(value)).alias("reduced"))
    else:
        small = cells.groupBy("vertex").agg(OPS[op](value).alias("reduced"))
    return cells.join(small, "vertex") if spread else small


def relabel(edges: DataFrame, scratch: Scratch, by: str = "degree", points: DataFrame | None = None, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """New vertex numbers 0..n-1 for locality: ``(edges, names(vertex, name))``.

    ``degree``: hubs first; ``random``: hashed; ``morton``: along a space-filling order of
    ``points(id, x, y)``; ``component``: vertices of a part together, by its least vertex.
    """
    from .paths import least_labels

    vertices = degrees(edges)
    if by == "morton":
        spread = F.lit(0).cast("long")
        for bit in range(20):
            for shift, c in ((0, "x"), (1, "y")):
                one = F.shiftright(F.col(c).cast("long"), bit).bitwiseAND(F.lit(1))
                spread = spread.bitwiseOR(F.shiftleft(one, 2 * bit + shift))
        keyed = vertices.join(points.select(F.col("id").alias("vertex"), spread.alias("key")), "vertex")
    elif by == "component":
        keyed = vertices.join(least_labels(edges, scratch).select("vertex", F.col("label").alias("key")), "vertex")
    else:
        keyed = vertices.withColumn("key", -F.col("degree") if by == "degree" else F.xxhash64(F.lit(seed), "vertex"))
    names = scratch.save(prefix_sum(keyed.select("key", "vertex"), ["key", "vertex"], F.lit(1), scratch, "name").select("vertex", "name"), "names")
    ends = [names.select(F.col("vertex").alias(c), F.col("name").alias(f"n{c}")) for c in "uv"]
    named = edges.join(ends[0], "u").join(ends[1], "v")
    rest = [c for c in edges.columns if c not in ("u", "v")]
    return named.select(F.least("nu", "nv").alias("u"), F.greatest("nu", "nv").alias("v"), *rest), names
