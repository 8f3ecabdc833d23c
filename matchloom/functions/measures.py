"""Cost and accuracy measures of matchings, runs and graphs."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..edges import arcs, degrees
from ..operators.scan import prefix_sum
from ..storage import Scratch


def matching_weight(matching: DataFrame) -> DataFrame:
    return matching.agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("weight"), F.count("*").alias("size"))


def quality_vs(matching: DataFrame, reference: DataFrame) -> DataFrame:
    """Weight over the reference's weight, and the gap in percent."""
    a, b = matching_weight(matching), matching_weight(reference)
    both = a.select("weight", F.lit(1).alias("k")).join(b.select(F.col("weight").alias("reference"), F.lit(1).alias("k")), "k")  # one row each
    ratio = F.when(F.col("reference") > 0, F.col("weight") / F.col("reference")).otherwise(F.lit(1.0))
    return both.select("weight", "reference", ratio.alias("ratio"), (100 * (1 - ratio)).alias("gap_percent"))


def weight_upper_bound(edges: DataFrame) -> DataFrame:
    """Twice the bound: each vertex gives at most its heaviest edge, each edge has two ends."""
    top = arcs(edges, "w").groupBy("vertex").agg(F.max("w").alias("w"))
    return top.agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("twice_bound"))


def bound_ratio(edges: DataFrame, matching: DataFrame) -> DataFrame:
    """Weight over the bound: the ratio to the optimum is at least that."""
    both = matching_weight(matching).withColumn("k", F.lit(1)).join(weight_upper_bound(edges).withColumn("k", F.lit(1)), "k")
    return both.select((2 * F.col("weight").cast("double") / F.col("twice_bound")).alias("ratio"))


def double_use(matching: DataFrame) -> DataFrame:
    return arcs(matching).groupBy("vertex").count().where("count > 1")


def loose_edges(edges: DataFrame, matching: DataFrame) -> DataFrame:
    """Edges with both ends free; a maximal matching leaves none."""
    used = arcs(matching).select("vertex")
    for c in "uv":
        edges = edges.join(used.withColumnRenamed("vertex", c), c, "left_anti")
    return edges


def phase_summary(log: DataFrame) -> DataFrame:
    """Phases, total work over the edges, mean survival, good phases (a quarter or more gone)."""
    first = F.max_by("live_before", -F.col("phase"))
    return log.agg(
        F.max("phase").alias("phases"), (F.sum("live_before") / first).alias("total_work"), F.avg("shrink").alias("mean_shrink"),
        F.sum((4 * F.col("removed") >= F.col("live_before")).cast("int")).alias("good_phases"),
    )


def doubling_ratio(times: DataFrame) -> DataFrame:
    """``(p, seconds)`` to the ratio time(p/2)/time(p), speedup and efficiency."""
    order = W.orderBy("p")
    first = F.first("seconds").over(order)
    return times.select("p", "seconds", (F.lag("seconds").over(order) / F.col("seconds")).alias("ratio"), (first / F.col("seconds")).alias("speedup"), (first / F.col("seconds") / F.col("p") * F.first("p").over(order)).alias("efficiency"))


def owners(edges: DataFrame, parts: int, kind: str = "range", scratch: Scratch | None = None) -> DataFrame:
    """``(vertex, owner)``: ``range`` gives each owner as many vertices, consecutive by id, as the
    others; ``hash`` deals them by md5."""
    vertices = arcs(edges).select("vertex").distinct()
    if kind == "hash":
        coin = F.conv(F.substring(F.md5(F.col("vertex").cast("string")), 1, 12), 16, 10).cast("long")
        return vertices.select("vertex", F.pmod(coin, F.lit(parts)).cast("int").alias("owner"))
    scratch = scratch or Scratch(edges.sparkSession, "owners")
    vertices = scratch.save(vertices, "vertices")
    n = max(vertices.count(), 1)
    return prefix_sum(vertices, ["vertex"], F.lit(1).cast("long"), scratch, "place").select("vertex", F.floor(F.col("place") * parts / n).cast("int").alias("owner"))


def owned_edges(edges: DataFrame, parts: int, kind: str = "range") -> DataFrame:
    """The edges with the owners ``ou`` and ``ov`` of their ends."""
    at = owners(edges, parts, kind)
    for c in "uv":
        edges = edges.join(at.select(F.col("vertex").alias(c), F.col("owner").alias(f"o{c}")), c)
    return edges


def cut_fraction(edges: DataFrame, parts: int, kind: str = "range") -> DataFrame:
    """Edges whose ends have different owners."""
    return owned_edges(edges, parts, kind).agg(F.sum((F.col("ou") != F.col("ov")).cast("long")).alias("cut"), F.count("*").alias("edges"))


def communication(removed: DataFrame, parts: int, kind: str = "range") -> DataFrame:
    """``(phase, live, cut, messages)`` from edges with the phase that ``removed`` them: live edges of
    a phase, those between owners, and a vote and a flag each way over each of them."""
    per = owned_edges(removed, parts, kind).groupBy("removed").agg(F.count("*").alias("n"), F.sum((F.col("ou") != F.col("ov")).cast("long")).alias("c"))
    later = W.orderBy(F.col("removed").desc()).rowsBetween(W.unboundedPreceding, 0)  # one row a phase
    return per.select(F.col("removed").alias("phase"), F.sum("n").over(later).alias("live"), F.sum("c").over(later).alias("cut"), (4 * F.sum("c").over(later)).alias("messages"))


def levels_above(size: Column, start: int, fan: int, most: int = 20) -> Column:
    """Least k with start * fan^k >= size, in integers."""
    return sum((F.when(size > start * fan**k, 1).otherwise(0) for k in range(most) if start * fan**k < 1 << 62), F.lit(0))


def mapreduce_cost(log: DataFrame, memory: int) -> DataFrame:
    """``(phase, rounds, traffic)`` where a machine holds ``memory`` rows: each aggregation of the
    phase's cells is a tree of that fan, and each level of it moves all cells once."""
    rounds = F.greatest(levels_above(2 * F.col("live_before"), 1, memory), F.lit(1)).cast("int")
    return log.select("phase", rounds.alias("rounds"), (2 * F.col("live_before") * rounds).cast("long").alias("traffic"))


def io_cost(log: DataFrame, memory: int, block: int) -> DataFrame:
    """``(phase, passes, blocks)`` of an external-memory run: the cells of a phase are sorted by a
    merge of fan memory/block, and every pass reads and writes all blocks."""
    cells = 2 * F.col("live_before")
    passes = (1 + levels_above(cells, memory, memory // block)).cast("int")
    return log.select("phase", passes.alias("passes"), (2 * passes * F.ceil(cells / block)).cast("long").alias("blocks"))


def balance_check(edges: DataFrame, parts: int) -> DataFrame:
    """Vertices of a degree above edges/parts, and whether there are none."""
    m = edges.agg(F.count("*").alias("m"))
    d = degrees(edges).agg(F.max("degree").alias("max_degree"))
    both = m.withColumn("k", F.lit(1)).join(d.withColumn("k", F.lit(1)), "k")
    return both.select("m", "max_degree", (F.col("max_degree") * parts <= F.col("m")).alias("balanced"))


def mark_count(edges: DataFrame, matching: DataFrame) -> DataFrame:
    """Ends marked by the edges of one phase: the degrees at the ends of the matched edges."""
    d = degrees(edges)
    joined = matching
    for c in "uv":
        joined = joined.join(d.select(F.col("vertex").alias(c), F.col("degree").alias(f"d{c}")), c)
    return joined.agg(F.coalesce(F.sum(F.col("du") + F.col("dv")), F.lit(0)).alias("marks"))


def match_probability(edges: DataFrame) -> DataFrame:
    """``(u, v, around)``: with unit weights and fresh noise the edge is matched in a phase with
    probability 1/around, around = d(u) + d(v) - 1."""
    d = degrees(edges)
    joined = edges.select("u", "v")
    for c in "uv":
        joined = joined.join(d.select(F.col("vertex").alias(c), F.col("degree").alias(f"d{c}")), c)
    return joined.select("u", "v", (F.col("du") + F.col("dv") - 1).alias("around"))


def weight_diversity(edges: DataFrame) -> DataFrame:
    """Distinct weights against edges: few distinct weights make sorting cheap."""
    return edges.agg(F.countDistinct("w").alias("weights"), F.count("*").alias("edges"))


def percentiles(df: DataFrame, column: str, shares: dict[str, float]) -> DataFrame:
    """One row of exact percentiles of a column of longs, between the two values beside a place in
    proportion. Equal values are counted once, places are prefix sums over ranges of values, and no
    task or machine holds all values."""
    scratch = Scratch(df.sparkSession, "percentiles")
    counts = scratch.save(df.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n")), "counts")
    total = counts.agg(F.sum("n")).first()[0] or 0
    places = {name: (total - 1) * share for name, share in shares.items()}
    ranked = prefix_sum(counts, ["value"], F.col("n"), scratch, "before")

    def value_at(place: int) -> Column:
        return F.max(F.when((F.col("before") <= place) & (F.col("before") + F.col("n") > place), F.col("value")))

    def between(place: float) -> Column:
        low, high = math.floor(place), math.ceil(place)
        if low == high:
            return value_at(low).cast("double")
        a, b = value_at(low), value_at(high)
        return F.when(a == b, a.cast("double")).otherwise(F.lit(high - place) * a + F.lit(place - low) * b)

    return ranked.agg(*[between(place).alias(name) for name, place in places.items()])


def suite_summary(results: DataFrame) -> DataFrame:
    """``(instance, method, weight, reference)`` to the spread of each method's ratio."""
    ratio = F.col("weight") / F.col("reference")
    return results.withColumn("ratio", ratio).groupBy("method").agg(
        F.count("*").alias("instances"), F.min("ratio").alias("least"), F.expr("percentile(ratio, 0.5)").alias("median"), F.max("ratio").alias("most"), F.avg("ratio").alias("mean"))


def pareto(results: DataFrame) -> DataFrame:
    """Rows ``(method, ratio, seconds)`` that no other beats in both."""
    better = results.select(F.col("method").alias("m"), F.col("ratio").alias("r"), F.col("seconds").alias("s"))
    beats = (F.col("r") >= F.col("ratio")) & (F.col("s") <= F.col("seconds")) & ((F.col("r") > F.col("ratio")) | (F.col("s") < F.col("seconds")))
    return results.join(better, beats, "left_anti")
