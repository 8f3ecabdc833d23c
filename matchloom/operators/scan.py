"""Array primitives over tables: segmented scan, prefix sum, gather, scatter, compaction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..storage import Scratch

OPS = {"max": F.max, "min": F.min, "sum": F.sum, "or": F.bool_or, "count": F.count}


def segmented_scan(df: DataFrame, seg: list[str], order: list[str], value: str, op: str = "sum", out: str = "scan") -> DataFrame:
    """Running reduction of ``value`` inside each segment."""
    run = W.partitionBy(*seg).orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    return df.withColumn(out, OPS[op](value).over(run))


def prefix_sum(df: DataFrame, order: list[str], value: Column, scratch: Scratch, out: str = "before") -> DataFrame:
    """Exclusive sum of ``value`` over all rows that come earlier in ``order``.

    Rows are dealt by range and written; each range is summed by its own task, and only one
    total for each range is added up in one place. ``order`` must tell all rows apart.
    """
    ranged = df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()).withColumn("_value", value)
    kept = scratch.save(ranged, "ranges")
    totals = kept.groupBy("_part").agg(F.sum("_value").alias("_total"))
    ahead = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    bases = totals.select("_part", F.coalesce(F.sum("_total").over(ahead), F.lit(0)).alias("_base"))
    inside = W.partitionBy("_part").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    summed = kept.withColumn("_own", F.coalesce(F.sum("_value").over(inside), F.lit(0)))
    return summed.join(bases, "_part").withColumn(out, F.col("_base") + F.col("_own")).drop("_part", "_value", "_base", "_own")


def gather(df: DataFrame, index: str, source: DataFrame, address: str = "pos") -> DataFrame:
    """Read ``source`` at the addresses in ``df.index``."""
    return df.join(source.withColumnRenamed(address, index), index)


def scatter(df: DataFrame, index: str, value: str, op: str = "max") -> DataFrame:
    """Write ``value`` to addresses; rows that meet are combined."""
    return df.groupBy(F.col(index).alias("pos")).agg(OPS[op](value).alias(value))


def compact(edges: DataFrame, cells: DataFrame, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """Drop flagged edges and their cells and renumber both by prefix sums of the flags.

    ``edges``: ``pos, deleted`` and more; ``cells``: ``pos, edge_pos`` and more. New addresses
    are old ones less what is deleted before them; cells follow their edges.
    """
    gone = F.col("deleted").cast("long")
    moved = prefix_sum(edges, ["pos"], gone, scratch, "shift")
    target = scratch.save(moved.where(~F.col("deleted")).withColumn("new_pos", F.col("pos") - F.col("shift")).drop("shift"), "moved")
    flags = edges.select(F.col("pos").alias("edge_pos"), "deleted")
    shifted = prefix_sum(cells.join(flags, "edge_pos"), ["pos"], gone, scratch, "shift")
    addresses = target.select(F.col("pos").alias("edge_pos"), F.col("new_pos").alias("new_edge_pos"))
    out = shifted.where(~F.col("deleted")).join(addresses, "edge_pos").withColumn("pos", F.col("pos") - F.col("shift"))
    out = out.withColumn("edge_pos", F.col("new_edge_pos")).drop("shift", "deleted", "new_edge_pos")
    return target.withColumn("pos", F.col("new_pos")).drop("new_pos", "deleted"), out
