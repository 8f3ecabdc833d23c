"""Edge tables: the canonical form, order keys and arcs.

An edge table has ``u < v`` and an integer weight ``w``. ``ordered_edges`` adds ``eid``, a
strict total order of the edges: the larger ``eid`` is the heavier edge. Loops of the methods
compare that one long and carry nothing else.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .storage import Scratch

SEED = 42


def canonical_edges(df: DataFrame, combine: str = "sum", nonpositive: str = "drop", loops: str = "drop") -> DataFrame:
    """Rows ``(u, v, w)`` in any form to a simple graph.

    Null ends and null or NaN weights are dropped, loops are dropped or an error, repeated and
    reversed pairs are combined by sum, max or min, or an error. Weights of zero or less are
    dropped, kept, or replaced by their absolute values before combining.
    """
    if combine not in ("sum", "max", "min", "error") or nonpositive not in ("drop", "keep", "abs") or loops not in ("drop", "error"):
        raise ValueError("unknown option")
    w = F.abs("w") if nonpositive == "abs" else F.col("w")
    usable = F.col("u").isNotNull() & F.col("v").isNotNull() & F.col("w").isNotNull()
    if dict(df.dtypes)["w"] in ("double", "float"):
        usable &= ~F.isnan("w")
        w = F.when(w == 0, F.lit(0.0)).otherwise(w)
    rows = df.where(usable).select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v"), w.alias("w"))
    if loops == "error":
        rows = rows.where(F.when(F.col("u") == F.col("v"), F.raise_error(F.lit("loop"))).otherwise(F.lit(True)))
    rows = rows.where("u <> v")
    reduce = {"sum": F.sum("w"), "max": F.max("w"), "min": F.min("w"), "error": F.max("w")}[combine]
    simple = rows.groupBy("u", "v").agg(reduce.alias("w"), F.count("*").alias("n"))
    if combine == "error":
        simple = simple.where(F.when(F.col("n") > 1, F.raise_error(F.lit("parallel edges"))).otherwise(F.lit(True)))
    simple = simple.select("u", "v", "w")
    return simple.where("w > 0") if nonpositive == "drop" else simple


def unit_weights(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v", F.lit(1).cast("long").alias("w"))


def portable_tie(seed: int = SEED, *more: Column) -> Column:
    """md5 text over seed and ends: the same in every SQL engine."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[m.cast("string") for m in more], F.col("u").cast("string"), F.col("v").cast("string")))


def in_order(edges: DataFrame, tie: Column | None) -> DataFrame:
    """``(u, v, w)`` by rising weight, then by falling noise and ends. The noise is not shuffled: the
    exchange by ranges draws it for its keys, and the sort of a range, as a column, once more."""
    keys = [F.col("w").asc(), *([] if tie is None else [tie.desc()]), F.col("u").desc(), F.col("v").desc()]
    dealt = edges.select("u", "v", "w").repartitionByRange(*keys)
    if tie is None:
        return dealt.sortWithinPartitions(*keys)
    return dealt.withColumn("tie", tie).sortWithinPartitions(F.col("w").asc(), F.col("tie").desc(), F.col("u").desc(), F.col("v").desc()).drop("tie")


def ordered_edges(edges: DataFrame, scratch: Scratch, ties: str = "portable", seed: int = SEED) -> DataFrame:
    """``(u, v, w, eid)``, written once. Ties of the weight go by ``portable`` (md5), ``static``
    (xxhash64) noise, or ``id`` (smaller ends first).

    One range-partitioned sort; ids ascend along it, so no single task sees all edges. The noise is
    a column of its own: as an expression of the sort it would be drawn at each comparison. As
    bytes, md5 sorts as its text does. A written table keeps its order, for methods that follow.
    """
    known = getattr(edges, "_orders", {})
    if (ties, seed) in known:
        return known[ties, seed]
    tie = {"portable": F.unhex(portable_tie(seed)), "static": F.xxhash64(F.lit(seed), "u", "v"), "id": None}[ties]
    ordered = scratch.save(in_order(edges, tie).select("u", "v", "w", F.monotonically_increasing_id().alias("eid")), "edges")
    known[ties, seed] = ordered
    return ordered


def arcs(edges: DataFrame, *keep: str) -> DataFrame:
    """Two rows for each edge: ``vertex, other`` and the columns kept."""
    ends = F.array(F.struct(F.col("u").alias("vertex"), F.col("v").alias("other")), F.struct(F.col("v").alias("vertex"), F.col("u").alias("other")))
    return edges.select(F.explode(ends).alias("end"), *keep).select("end.vertex", "end.other", *keep)


def degrees(edges: DataFrame) -> DataFrame:
    return arcs(edges).groupBy("vertex").agg(F.count("*").alias("degree"))
