"""The methods that local max is compared with. All return ``(u, v, w, eid, phase)``."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..catalog import make_importable
from ..edges import arcs, degrees, ordered_edges
from ..functions.kernels import exact_weight, greedy_scan, heavy_edge_sweep, one_task, pointer_scan
from ..storage import Scratch
from .localmax import BROADCAST_ROWS, MatchResult, drop_covered, local_max
from .scan import prefix_sum

SCAN_ROWS = 5_000_000
PICKED = "eid long, phase int"


def _start(edges: DataFrame, label: str, ties: str = "portable", seed: int = 42) -> tuple[Scratch, DataFrame]:
    make_importable(edges.sparkSession)
    scratch = Scratch(edges.sparkSession, label)
    return scratch, ordered_edges(edges, scratch, ties, seed)


def _result(ordered: DataFrame, picked: DataFrame) -> MatchResult:
    return MatchResult(ordered.join(picked, "eid").select("u", "v", "w", "eid", "phase"), ordered)


def scanned(ordered: DataFrame, scan: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """``(eid, phase)`` from a kernel over all edges in falling order, in one task."""
    if (n := ordered.count()) > SCAN_ROWS:
        raise ValueError(f"{n} edges are too many for one task; use engine='rounds'")

    def compute(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("eid").to_numpy(), kind="stable")[::-1]
        table = table.take(pa.array(order))
        taken = scan(table.column("u").to_numpy(), table.column("v").to_numpy())
        eid = table.column("eid").to_numpy()[taken]
        return pa.table({"eid": eid, "phase": np.ones(len(eid), np.int32)})

    return one_task(ordered.select("u", "v", "eid"), compute, PICKED)


def rounds(ordered: DataFrame, scratch: Scratch, pick: Callable[[DataFrame, int], DataFrame], most: int = 500) -> DataFrame:
    """Repeat: ``pick(live, round)`` gives edges of which no two touch; they and what they touch go."""
    live, count, k, out = ordered.select("u", "v", "eid"), ordered.count(), 0, []
    while count:
        k += 1
        if k > most:
            raise RuntimeError(f"{count} edges are left after {most} rounds")
        won = scratch.save(pick(live, k).select("u", "v", "eid"), "won")
        n = won.count()
        if n:
            out.append(won.select("eid", F.lit(k).cast("int").alias("phase")))
            fresh = scratch.save(drop_covered(live, won, [], n <= BROADCAST_ROWS), "live")
            scratch.drop(live)
            live, count = fresh, fresh.count()
    if not out:
        return ordered.select("eid", F.lit(0).alias("phase")).where("false")
    picked = out[0]
    for p in out[1:]:
        picked = picked.unionByName(p)
    return picked


def greedy(edges: DataFrame, engine: str = "rounds", **options) -> MatchResult:
    """Edges by falling weight, taken if both ends are free. Under a strict order that is what
    local max finds, so ``rounds`` is local max; ``scan`` is the sequential reference."""
    if engine == "rounds":
        return local_max(edges, **options)
    _, ordered = _start(edges, "greedy")
    if engine == "auto" and ordered.count() > SCAN_ROWS:
        return local_max(edges, **options)
    return _result(ordered, scanned(ordered, greedy_scan))


def pointer_matching(edges: DataFrame, engine: str = "auto") -> MatchResult:
    """Sorted lists with pointers that move past matched neighbours: ``scan`` in one task, ``rounds``
    over all vertices, or ``auto`` by the number of edges."""
    _, ordered = _start(edges, "pointer")
    if engine == "rounds" or engine == "auto" and ordered.count() > SCAN_ROWS:
        return pointer_rounds(edges)
    return _result(ordered, scanned(ordered, pointer_scan))


def pointer_rounds(edges: DataFrame) -> MatchResult:
    """``pointer_matching`` in rounds over all vertices: each points at its heaviest neighbour that
    is left, mutual pointers match, and only vertices whose neighbour went point anew."""
    scratch, ordered = _start(edges, "pointers")
    aimed: DataFrame | None = None

    def pick(live: DataFrame, k: int) -> DataFrame:
        nonlocal aimed
        cells = arcs(live, "eid")
        if aimed is not None:
            still = aimed.join(live.select("eid"), "eid", "left_semi").select("vertex", "eid")
            again = cells.join(still.select("vertex"), "vertex", "left_anti")
            fresh = still.unionByName(again.groupBy("vertex").agg(F.max("eid").alias("eid")))
        else:
            fresh = cells.groupBy("vertex").agg(F.max("eid").alias("eid"))
        before, aimed = aimed, scratch.save(fresh, "aimed")
        if before is not None:
            scratch.drop(before)
        votes = aimed.groupBy("eid").agg(F.count("*").alias("votes")).where("votes = 2")
        return live.join(votes.select("eid"), "eid", "left_semi")

    return _result(ordered, rounds(ordered, scratch, pick))


def portable_coin(seed: int, k: int | Column, *parts: str) -> Column:
    """48 hashed bits of (seed, round, parts), the same in every SQL engine."""
    k = F.lit(k) if isinstance(k, int) else k
    text = F.concat_ws("|", F.lit(str(seed)), k.cast("string"), *[F.col(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long")


def heavy_edge(edges: DataFrame, order: str = "id", seed: int = 42, engine: str = "rounds") -> MatchResult:
    """Vertices in turn, each free one with its heaviest edge to a free neighbour.

    ``order``: by id, or hashed (``random``). In rounds, a vertex may go when no vertex within
    two steps comes before it: one that is farther cannot change its neighbours. ``engine``:
    ``rounds``, or ``auto``: pieces of the order, each in one task (``scan``: an error if one
    piece would not hold all).
    """
    scratch, ordered = _start(edges, "heavyedge")
    rank = F.struct(F.lit(0).cast("long") if order == "id" else portable_coin(seed, 0, "vertex"), F.col("vertex"))
    if engine == "scan" and (n := ordered.count()) > SCAN_ROWS:
        raise ValueError(f"{n} edges are too many for one task; use engine='auto' or 'rounds'")
    if engine != "rounds":
        return _result(ordered, heavy_edge_pieces(ordered, rank, scratch))

    def pick(live: DataFrame, k: int) -> DataFrame:
        cells = arcs(live, "eid").withColumn("rank", rank)
        one = cells.groupBy("vertex").agg(F.min("rank").alias("rank"), F.max("eid").alias("eid"))
        across = cells.select(F.col("other").alias("vertex"), "rank").groupBy("vertex").agg(F.min("rank").alias("near"))
        first = one.join(across, "vertex").withColumn("least", F.least("rank", "near"))
        reach = cells.select("vertex", "other").join(first.select(F.col("vertex").alias("other"), "least"), "other").groupBy("vertex").agg(F.min("least").alias("far"))
        ready = first.join(reach, "vertex").where("rank <= least and rank <= far").select("eid")
        return live.join(ready, "eid", "left_semi")

    return _result(ordered, rounds(ordered, scratch, pick, most=5000))


def heavy_edge_pieces(ordered: DataFrame, rank: Column, scratch: Scratch, rows: int | None = None) -> DataFrame:
    """``(eid, phase)`` of heavy-edge by pieces of the order of turns, of about ``rows`` edges each.
    An edge goes with the end whose turn comes first. Edges of a piece that touch a vertex matched
    in an earlier piece leave before one task scans the rest."""
    rows = rows or SCAN_ROWS
    names = scratch.save(arcs(ordered).select("vertex").distinct().select(rank.alias("rank")).select("rank.*").toDF("coin", "vertex"), "names")
    turns = scratch.save(prefix_sum(names, ["coin", "vertex"], F.lit(1).cast("long"), scratch, "turn").select("vertex", "turn"), "turns")
    at = [turns.select(F.col("vertex").alias(c), F.col("turn").alias(f"t{c}")) for c in "uv"]
    swap = F.col("tu") < F.col("tv")
    placed = ordered.select("u", "v", "eid").join(at[0], "u").join(at[1], "v")
    placed = scratch.save(placed.select(F.least("tu", "tv").alias("turn"), F.when(swap, F.col("u")).otherwise(F.col("v")).alias("first"), F.when(swap, F.col("v")).otherwise(F.col("u")).alias("other"), "eid"), "placed")
    per = scratch.save(placed.groupBy("turn").agg(F.count("*").alias("n")), "per")
    pieces = prefix_sum(per, ["turn"], F.col("n"), scratch, "before").groupBy(F.floor(F.col("before") / rows).alias("piece")).agg(F.min("turn").alias("low")).orderBy("piece").collect()

    def compute(table: pa.Table) -> pa.Table:
        table = table.take(pa.array(np.lexsort((-table.column("eid").to_numpy(), table.column("turn").to_numpy()))))
        taken = heavy_edge_sweep(table.column("first").to_numpy(), table.column("other").to_numpy())
        return table.filter(pa.array(taken)).select(["first", "other", "eid"])

    won = None
    for k, piece in enumerate(pieces):
        part = placed.where(F.col("turn") >= piece["low"])
        if k + 1 < len(pieces):
            part = part.where(F.col("turn") < pieces[k + 1]["low"])
        if won is not None:
            used = won.select(F.explode(F.array("first", "other")).alias("used"))
            for c in ("first", "other"):
                part = part.join(used.withColumnRenamed("used", c), c, "left_anti")
        fresh = scratch.save(one_task(part.select("turn", "first", "other", "eid"), compute, "first long, other long, eid long"), "won")
        won = fresh if won is None else won.unionByName(fresh)
    if won is None:
        return ordered.select("eid", F.lit(0).alias("phase")).where("false")
    return won.select("eid", F.lit(1).alias("phase"))


def red_blue(edges: DataFrame, p_blue: float = 0.5, seed: int = 42) -> MatchResult:
    """Each round colours vertices by a coin; blue ones propose over their heaviest edge to a
    red neighbour, red ones take the heaviest proposal."""
    scratch, ordered = _start(edges, "redblue")
    limit = int(p_blue * (1 << 48))

    def pick(live: DataFrame, k: int) -> DataFrame:
        # only edges of two colours are proposed, each from its blue end: both coins are drawn once for an edge
        tossed = live.withColumn("bu", portable_coin(seed, k, "u") < limit).withColumn("bv", portable_coin(seed, k, "v") < limit).where("bu <> bv")
        cells = tossed.select(F.when(F.col("bu"), F.col("u")).otherwise(F.col("v")).alias("vertex"), F.when(F.col("bu"), F.col("v")).otherwise(F.col("u")).alias("other"), "eid")
        asked = cells.groupBy("vertex").agg(F.max_by("other", "eid").alias("red"), F.max("eid").alias("eid"))
        return asked.groupBy("red").agg(F.max_by("vertex", "eid").alias("blue"), F.max("eid").alias("eid")).select(F.least("red", "blue").alias("u"), F.greatest("red", "blue").alias("v"), "eid")

    return _result(ordered, rounds(ordered, scratch, pick))


def red_blue_blocks(edges: DataFrame, parts: int | None = None, p_blue: float = 0.5, seed: int = 42) -> MatchResult:
    """``red_blue`` by owners of consecutive vertices: an owner finds the proposals of its blue vertices
    by itself, keeps the best for each red one, and only those go to the owners of the red ones."""
    from ..functions.measures import owners

    scratch, ordered = _start(edges, "redblocks")
    parts = parts or max(2, edges.sparkSession.sparkContext.defaultParallelism, -(-2 * ordered.count() // (1 << 20)))
    at = scratch.save(owners(ordered, parts, "range", scratch), "owners")
    limit = int(p_blue * (1 << 48))

    def propose(table: pa.Table) -> pa.Table:
        vertex, other, eid = (table.column(c).to_numpy() for c in ("vertex", "other", "eid"))
        order = np.lexsort((-eid, vertex))
        first = order[np.concatenate([[True], vertex[order][1:] != vertex[order][:-1]])]
        order = first[np.lexsort((-eid[first], other[first]))]
        best = order[np.concatenate([[True], other[order][1:] != other[order][:-1]])]
        return pa.table({"red": other[best], "eid": eid[best]})

    def pick(live: DataFrame, k: int) -> DataFrame:
        cells = arcs(live, "eid").where((portable_coin(seed, k, "vertex") < limit) & (portable_coin(seed, k, "other") >= limit))
        asked = cells.join(at, "vertex").groupBy("owner").applyInArrow(propose, "red long, eid long")
        return live.join(asked.groupBy("red").agg(F.max("eid").alias("eid")).select("eid"), "eid", "left_semi")

    return _result(ordered, rounds(ordered, scratch, pick))


def random_proposal(edges: DataFrame, seed: int = 42) -> MatchResult:
    """Each vertex picks a random edge, each picked vertex keeps one of its pickers, and of the
    links that are left each vertex picks one; links picked by both ends match."""
    scratch, ordered = _start(edges, "proposal")

    def pick(live: DataFrame, k: int) -> DataFrame:
        named = arcs(live, "eid", "u", "v")
        coin = F.struct(portable_coin(seed, k, "vertex", "u", "v"), F.col("u"), F.col("v"))
        draw = named.groupBy("vertex").agg(F.min_by(F.struct("other", "eid", "u", "v"), coin).alias("p")).select("vertex", "p.*")
        again = F.struct(portable_coin(-seed, k, "other", "u", "v"), F.col("u"), F.col("v"))
        kept = draw.groupBy("other").agg(F.min_by("eid", again).alias("eid")).select("eid").distinct()
        links = arcs(live.join(kept, "eid", "left_semi"), "eid", "u", "v")
        last = F.struct(portable_coin(seed, -k, "vertex", "u", "v"), F.col("u"), F.col("v"))
        votes = links.groupBy("vertex").agg(F.min_by("eid", last).alias("eid")).groupBy("eid").count().where("count = 2")
        return live.join(votes.select("eid"), "eid", "left_semi")

    return _result(ordered, rounds(ordered, scratch, pick))


#: Cells of one vertex that meet as one block.
BLOCK_CELLS = 2048


def touching_pairs(edges: DataFrame, *keep: str) -> DataFrame:
    """Pairs of edges that share an end, once each: the columns ``keep`` of both as structs ``a``
    and ``b``, in no order. Cells of a vertex are dealt into blocks, and each pair of blocks is a
    key of its own, so that a hub is not one task. Edges are simple, so a pair shares one end."""
    cells = arcs(edges, *{"u", "v", *keep}).drop("other")
    parts = cells.groupBy("vertex").agg(F.ceil(F.count("*") / BLOCK_CELLS).cast("int").alias("parts"))
    dealt = cells.join(parts, "vertex").withColumn("mine", F.pmod(F.xxhash64("u", "v"), F.col("parts")).cast("int"))
    one = dealt.select("vertex", F.col("mine").alias("i"), F.explode(F.sequence("mine", F.col("parts") - 1)).alias("j"), F.struct(*keep).alias("a"), F.struct("u", "v").alias("an"))
    two = dealt.select("vertex", F.explode(F.sequence(F.lit(0), "mine")).alias("i"), F.col("mine").alias("j"), F.struct(*keep).alias("b"), F.struct("u", "v").alias("bn"))
    return one.join(two, ["vertex", "i", "j"]).where("i < j or an.u < bn.u or an.u = bn.u and an.v < bn.v").select("a", "b")


def line_graph(ordered: DataFrame, most: int | None = None) -> DataFrame:
    """``(e1, e2)``: pairs of edges that share an end. Their number, the sum of d(d-1)/2, grows
    with the square of the degrees; more than ``most`` are an error where that is given."""
    if most is not None:
        total = degrees(ordered).agg(F.sum(F.col("degree") * (F.col("degree") - 1) / 2)).first()[0] or 0
        if total > most:
            raise ValueError(f"the line graph has {total:.0f} edges")
    pairs = touching_pairs(ordered, "eid")
    return pairs.select(F.least("a.eid", "b.eid").alias("e1"), F.greatest("a.eid", "b.eid").alias("e2"))


def independent_set(nodes: DataFrame, links: DataFrame, scratch: Scratch, priority: Column, most: int = 200) -> DataFrame:
    """Maximal independent set of ``nodes(node)``: each round takes the nodes of a greater
    priority than all live neighbours and removes those neighbours."""
    live = scratch.save(nodes.withColumn("priority", priority), "nodes")
    both = links.select(F.col("e1").alias("node"), F.col("e2").alias("other")).unionByName(links.select(F.col("e2").alias("node"), F.col("e1").alias("other")))
    both, out = scratch.save(both, "pairs"), []
    for k in range(1, most + 1):
        if live.isEmpty():
            break
        rated = both.join(live, "node").join(live.select(F.col("node").alias("other"), F.col("priority").alias("rival")), "other")
        beaten = rated.where("rival > priority").select("node").distinct()
        won = scratch.save(live.join(beaten, "node", "left_anti").select("node"), "won")
        out.append(won.withColumn("phase", F.lit(k)))
        near = both.join(won, "node").select(F.col("other").alias("node"))
        live = scratch.save(live.join(won, "node", "left_anti").join(near, "node", "left_anti"), "nodes")
    if not out:
        return nodes.withColumn("phase", F.lit(0)).where("false")
    chosen = out[0]
    for p in out[1:]:
        chosen = chosen.unionByName(p)
    return chosen


def line_graph_matching(edges: DataFrame, seed: int = 42) -> MatchResult:
    """A maximal matching as an independent set of the line graph, random priorities. The links of
    the line graph are not written out: the neighbours of an edge are the cells of its two ends,
    so an edge beats all of them if it is the greatest at both. Rounds as ``independent_set``."""
    make_importable(edges.sparkSession)
    scratch = Scratch(edges.sparkSession, "linegraph")
    rising = edges.select("u", "v", "w").orderBy(portable_coin(seed, 0, "u", "v"), "u", "v")
    ordered = scratch.save(rising.select("u", "v", "w", F.monotonically_increasing_id().alias("eid")), "edges")
    return local_max(ordered, ties="given", scratch=scratch)


def exact_matching(edges: DataFrame) -> MatchResult:
    """Heaviest matching; each component of up to 22 vertices is solved by its own task."""
    from .paths import least_labels

    scratch, ordered = _start(edges, "exact")
    labels = least_labels(ordered, scratch)
    parts = ordered.join(labels.select(F.col("vertex").alias("u"), "label"), "u")

    def solve(table: pa.Table) -> pa.Table:
        _, chosen = exact_weight(table.column("u").to_numpy(), table.column("v").to_numpy(), table.column("w").to_numpy())
        eid = table.column("eid").to_numpy()[chosen] if chosen else np.zeros(0, np.int64)
        return pa.table({"eid": eid, "phase": np.ones(len(eid), np.int32)})

    return _result(ordered, parts.groupBy("label").applyInArrow(solve, PICKED))


#: Edges of each vertex of the smaller side that a step adds to the core of the assignment.
CORE_EDGES = 12


def exact_bipartite(edges: DataFrame) -> MatchResult:
    """Heaviest matching of a bipartite graph, by assignment on a growing core of its edges.

    The core starts as the heaviest edges of each vertex of the smaller side. Its optimum comes with
    prices of the vertices; edges that weigh more than the prices of their ends join the core, for
    each vertex those of the largest excess first. Where none is left, the prices bound every
    matching of the whole graph by the weight at hand. A core of up to SCAN_ROWS edges is one task,
    a larger one a task for each of its components.
    """
    from ..functions.kernels import priced_assignment
    from .paths import least_labels

    scratch, ordered = _start(edges, "assign")
    useful = ordered.where("w > 0")
    sides = useful.agg(F.approx_count_distinct("u"), F.approx_count_distinct("v")).first()
    side = "u" if sides[0] <= sides[1] else "v"
    best = W.partitionBy(side).orderBy(F.col("excess").desc(), F.col("eid").desc())

    def solve(table: pa.Table) -> pa.Table:
        taken, names, prices = priced_assignment(*(table.column(c).to_numpy() for c in ("u", "v", "w")))
        eid = table.column("eid").to_numpy()[taken]
        kind = np.concatenate([np.zeros(len(eid), np.int32), np.ones(len(names), np.int32)])
        return pa.table({"kind": kind, "name": np.concatenate([eid, names]), "price": np.concatenate([np.zeros(len(eid), np.int64), prices])})

    def heaviest(excess: DataFrame) -> DataFrame:
        return excess.withColumn("place", F.row_number().over(best)).where(F.col("place") <= CORE_EDGES).select("u", "v", "w", "eid")

    core = scratch.save(heaviest(useful.withColumn("excess", F.col("w"))), "core")
    schema = "kind int, name long, price long"
    while True:
        if core.count() <= SCAN_ROWS:
            solved = one_task(core, solve, schema)
        else:
            labels = least_labels(core, scratch)
            solved = core.join(labels.select(F.col("vertex").alias("u"), "label"), "u").groupBy("label").applyInArrow(solve, schema)
        solved = scratch.save(solved, "solved")
        prices = solved.where("kind = 1 and price > 0")
        ends = [prices.select(F.col("name").alias(c), F.col("price").alias(f"p{c}")) for c in "uv"]
        excess = F.col("w") - F.coalesce("pu", F.lit(0)) - F.coalesce("pv", F.lit(0))
        above = useful.join(ends[0], "u", "left").join(ends[1], "v", "left").withColumn("excess", excess).where("excess > 0")
        more = scratch.save(heaviest(above), "more")
        if more.isEmpty():
            picked = solved.where("kind = 0").select(F.col("name").alias("eid"), F.lit(1).alias("phase"))
            return _result(ordered, picked)
        core = scratch.save(core.unionByName(more), "core")
