"""Global paths: greedy growth of a graph of paths and even cycles, then the heaviest matching
of each of them by dynamic programming."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..catalog import make_importable
from ..edges import arcs, ordered_edges
from ..functions.kernels import global_paths_scan, one_task
from ..storage import Scratch
from .localmax import BROADCAST_ROWS, MatchResult, drop_covered, finish
from .pathscan import optimum_links, rank_links

SCAN_ROWS = 5_000_000
LINKS = "eid long, u long, v long, w long, comp long, place long, taken boolean"


def least_labels(edges: DataFrame, scratch: Scratch, most: int = 100) -> DataFrame:
    """``(vertex, label)``: the least vertex of each component, by hooking and doubling."""
    both = arcs(edges).select("vertex", "other").distinct()
    state = scratch.save(both.groupBy("vertex").agg(F.least(F.min("other"), F.col("vertex")).alias("label")), "labels")
    for _ in range(most):
        near = both.join(state.select(F.col("vertex").alias("other"), F.col("label").alias("theirs")), "other").groupBy("vertex").agg(F.min("theirs").alias("theirs"))
        hooked = state.join(near, "vertex").select("vertex", F.least("label", "theirs").alias("label"), F.col("label").alias("was"))
        root = hooked.select(F.col("vertex").alias("label"), F.col("label").alias("root"))
        doubled = hooked.join(root, "label", "left").select("vertex", F.least("label", F.coalesce("root", "label")).alias("label"), "was")
        fresh = scratch.save(doubled, "labels")
        scratch.drop(state)
        state = fresh.select("vertex", "label")
        state._scratch_path = fresh._scratch_path
        if fresh.where("label <> was").isEmpty():
            return state
    raise RuntimeError("labels did not settle")


def grow_paths(ordered: DataFrame, scratch: Scratch, most: int = 1000) -> DataFrame:
    """``(eid, u, v, comp)``: links of the grown graph, by rounds over the paths.

    A path counts as one vertex. An edge that is the heaviest admissible one at the paths of
    both its ends is decided: it joins two paths, closes an even cycle, or would close an odd
    one and goes. That is what the scan in falling order does, because no heavier edge can
    touch either path before.
    """
    live = ordered.select("u", "v", "eid")
    state = scratch.save(arcs(live).select("vertex").distinct().select("vertex", F.col("vertex").alias("comp"), F.lit(0).alias("degree")), "state")
    sizes = scratch.save(state.select("comp", F.lit(0).cast("long").alias("links")), "sizes")
    count, chosen = live.count(), []
    for _ in range(most):
        if not count:
            break
        at = [state.select(F.col("vertex").alias(c), F.col("comp").alias(f"c{c}")) for c in "uv"]
        placed = scratch.save(live.join(at[0], "u").join(at[1], "v").select("u", "v", "eid", "cu", "cv"), "placed")
        best = placed.select("eid", F.explode(F.array_distinct(F.array("cu", "cv"))).alias("comp")).groupBy("comp").agg(F.max("eid").alias("eid"))
        votes = best.groupBy("eid").agg(F.count("*").alias("votes"))
        top = placed.join(votes, "eid").where((F.col("votes") == 2) | (F.col("cu") == F.col("cv")))
        judged = scratch.save(top.join(sizes.withColumnRenamed("comp", "cu"), "cu").withColumn("ok", (F.col("cu") != F.col("cv")) | (F.col("links") % 2 == 1)).select("u", "v", "eid", "cu", "cv", "ok"), "judged")
        taken = scratch.save(judged.where("ok"), "taken")
        chosen.append(taken.select("eid", "u", "v"))
        named = taken.select(F.greatest("cu", "cv").alias("old"), F.least("cu", "cv").alias("new"))
        grown = arcs(taken).groupBy("vertex").agg(F.count("*").alias("more"))
        state2 = state.join(grown, "vertex", "left").join(named.where("old <> new").withColumnRenamed("old", "comp"), "comp", "left")
        state_before, sizes_before, live_before = state, sizes, live
        state = scratch.save(state2.select("vertex", F.coalesce("new", "comp").alias("comp"), (F.col("degree") + F.coalesce("more", F.lit(0))).cast("int").alias("degree")), "state")
        moved = sizes.join(named.where("old <> new").withColumnRenamed("old", "comp"), "comp", "left").select(F.coalesce("new", "comp").alias("comp"), "links")
        added = taken.select(F.least("cu", "cv").alias("comp"), F.lit(1).cast("long").alias("links"))
        sizes = scratch.save(moved.unionByName(added).groupBy("comp").agg(F.sum("links").alias("links")), "sizes")
        full = state.where("degree >= 2").select("vertex")
        rest = placed.select("u", "v", "eid").join(judged.select("eid"), "eid", "left_anti")
        for c in "uv":
            rest = rest.join(full.withColumnRenamed("vertex", c), c, "left_anti")
        live = scratch.save(rest.select("u", "v", "eid"), "live")
        scratch.drop(placed, judged, state_before, sizes_before, *([live_before] if chosen[1:] else []))
        count = live.count()
    else:
        raise RuntimeError("growth did not end")
    if not chosen:
        return ordered.select("eid", "u", "v", F.col("u").alias("comp")).where("false")
    links = chosen[0]
    for p in chosen[1:]:
        links = links.unionByName(p)
    return links.join(state.select(F.col("vertex").alias("u"), "comp"), "u").select("eid", "u", "v", "comp")


def global_paths(edges: DataFrame, rounds: int = 1, engine: str = "auto", maximal: bool = False, ties: str = "portable", seed: int = 42) -> MatchResult:
    """``rounds`` passes over the vertices that are still free; ``maximal`` fills the rest with
    local max. ``engine``: ``rounds``, ``scan`` (one task), or ``auto``: one task, for more edges pieces
    of their order, for more links than one task takes rounds."""
    make_importable(edges.sparkSession)
    scratch = Scratch(edges.sparkSession, "paths")
    ordered = ordered_edges(edges, scratch, ties, seed)
    live, out = ordered, []
    for k in range(1, rounds + 1):
        n = live.count()
        if not n:
            break
        if engine == "scan" or engine == "auto" and n <= SCAN_ROWS:
            won = grown_links_scan(live).where("taken").select("eid", "u", "v")
        elif engine == "auto" and (links := grow_by_pieces(live, scratch)).count() <= SCAN_ROWS:
            # links grow to the same paths without the edges that were turned away
            won = grown_links_scan(links).where("taken").select("eid", "u", "v")
        else:
            links = grow_paths(live, scratch).join(live.select("eid", "w"), "eid")
            ranked = scratch.save(rank_links(scratch.save(links, "links"), scratch), "ranked")
            won = optimum_links(ranked, scratch).select("eid", "u", "v")
        won = scratch.save(won, "won")
        out.append(won.select("eid", F.lit(k).alias("phase")))
        if k < rounds or maximal:
            live = scratch.save(drop_covered(live, won, [], won.count() <= BROADCAST_ROWS).select("u", "v", "w", "eid"), "live")
    if maximal:
        rest = finish(live.select("u", "v", "eid", F.col("eid").alias("key")), [], rounds).where("phase > 0").select("eid", "phase")
        out.append(scratch.save(rest, "rest"))
    if not out:
        return MatchResult(ordered.withColumn("phase", F.lit(0)).where("false").select("u", "v", "w", "eid", "phase"), ordered)
    picked = out[0]
    for p in out[1:]:
        picked = picked.unionByName(p)
    return MatchResult(ordered.join(picked, "eid").select("u", "v", "w", "eid", "phase"), ordered)


def grow_by_pieces(ordered: DataFrame, scratch: Scratch, rows: int | None = None) -> DataFrame:
    """``(eid, u, v, w)``: links of the grown graph, by pieces of the falling order of about ``rows``
    edges. What a piece has to know of heavier ones are their links: edges of vertices with two of
    them leave before one task scans the rest, after the links of before in falling order."""
    rows = rows or SCAN_ROWS
    pieces = max(2, -(-ordered.count() // rows))
    shares = [k / pieces for k in range(pieces - 1, 0, -1)]
    bounds = ordered.approxQuantile("eid", shares, 1e-3)  # where pieces part bears on no result
    edges = [None, *dict.fromkeys(int(x) for x in bounds), None]
    links = None
    for high, low in zip(edges, edges[1:]):
        part = ordered.select("eid", "u", "v", "w")
        part = part if high is None else part.where(F.col("eid") <= high)
        part = part if low is None else part.where(F.col("eid") > low)
        if links is not None:
            full = arcs(links).groupBy("vertex").count().where("count > 1").select("vertex")
            for c in "uv":
                part = part.join(full.withColumnRenamed("vertex", c), c, "left_anti")
            part = part.unionByName(links)
        fresh = scratch.save(grown_links_scan(part).select("eid", "u", "v", "w"), "links")
        if links is not None:
            scratch.drop(links)
        links = fresh
    return links


def grown_links_scan(ordered: DataFrame) -> DataFrame:
    """``(eid, u, v, w, comp, place, taken)`` of all links, by one scan in one task."""

    def compute(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("eid").to_numpy(), kind="stable")[::-1]
        table = table.take(pa.array(order))
        cols = [table.column(c).to_numpy() for c in ("u", "v", "w")]
        part, place, taken = global_paths_scan(*cols)
        at = np.flatnonzero(part >= 0)
        names = np.unique(np.concatenate(cols[:2]))
        rows = table.take(pa.array(at)).select(["eid", "u", "v", "w"])
        # a part goes by its least vertex
        least = np.full(len(names), np.iinfo(np.int64).max)
        np.minimum.at(least, part[at], np.minimum(cols[0][at], cols[1][at]))
        return rows.append_column("comp", pa.array(least[part[at]])).append_column("place", pa.array(place[at])).append_column("taken", pa.array(taken[at]))

    return one_task(ordered.select("eid", "u", "v", "w"), compute, LINKS)
