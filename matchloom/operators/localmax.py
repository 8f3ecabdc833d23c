"""Local max: every edge that outweighs all its neighbours is matched, phase by phase.

Plans for one phase (all give the same matching under the same order):

* ``edges`` - arcs to the best edge of each vertex (hash aggregate of one long), each vertex
  votes for its best edge, an edge with two votes wins. The vote moves as many rows as there
  are vertices.
* ``join`` - the table of best edges is joined back to both ends.
* ``sort`` - the ``edges`` plan with sorts in place of hashing: the best edge is the first of its
  vertex in sorted runs, which spill, and matched vertices leave by merge joins.
* ``arcs`` - window maxima over resident arcs that move together (operators.crew);
  ``primitives`` - the same from scatter, gather and prefix sums alone.
* ``blocks`` - vertex owners work on their own edges first (operators.blocks).
* ``sql`` - the ``join`` plan as one SQL statement.
* ``kernel`` - everything in one task; also the finish of the others.
"""

from __future__ import annotations

import time
from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from ..catalog import make_importable
from ..edges import arcs, ordered_edges, unit_weights
from ..functions.kernels import local_max_phases, one_task
from ..storage import Scratch
from .scan import prefix_sum

BROADCAST_ROWS = 500_000


@dataclass
class MatchResult:
    """A matching, the phases that made it, and the edges it was made from."""

    matching: DataFrame
    edges: DataFrame
    log: Sequence[dict] = field(default_factory=list)

    def weight(self) -> int:
        return self.matching.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]

    def size(self) -> int:
        return self.matching.count()

    def mates(self) -> DataFrame:
        """Each vertex of the graph with its mate, null where it is free."""
        pairs = arcs(self.matching).select("vertex", F.col("other").alias("mate"))
        return arcs(self.edges).select("vertex").distinct().join(pairs, "vertex", "left")

    def free_vertices(self) -> DataFrame:
        return self.mates().where("mate is null").select("vertex")

    def removal_phases(self) -> DataFrame:
        """Edges ``(u, v, eid)`` with the phase that removed them: the first in which an end was
        matched. Null where the matching leaves an edge."""
        at = arcs(self.matching, "phase").select("vertex", "phase")
        ends = [at.select(F.col("vertex").alias(c), F.col("phase").alias(f"p{c}")) for c in "uv"]
        return self.edges.join(ends[0], "u", "left").join(ends[1], "v", "left").select("u", "v", "eid", F.least("pu", "pv").alias("removed"))

    def is_valid(self) -> bool:
        return arcs(self.matching).groupBy("vertex").count().where("count > 1").isEmpty()

    def is_maximal(self) -> bool:
        used = arcs(self.matching).select("vertex")
        loose = self.edges.join(used.withColumnRenamed("vertex", "u"), "u", "left_anti").join(used.withColumnRenamed("vertex", "v"), "v", "left_anti")
        return loose.isEmpty()

    def log_frame(self) -> DataFrame:
        if isinstance(self.log, PhaseLog):
            return self.log.frame()
        rows = [tuple(x.get(c) for c in LOG_COLUMNS) for x in self.log]
        return self.matching.sparkSession.createDataFrame(rows, LOG_SCHEMA)

    def to_table(self, path: str, mode: str = "overwrite", partition_by: tuple[str, ...] = ()) -> None:
        self.matching.write.mode(mode).partitionBy(*partition_by).parquet(path)


class PhaseLog(Sequence):
    """Lines of the phases so far and, of phases that one task finished, a table of their sizes: there
    may be as many as edges, so they come to the driver only where someone reads them."""

    def __init__(self, lines: list[dict], sizes: DataFrame, live: int, seconds: float):
        self.lines, self.sizes, self.live, self.seconds, self.known = lines, sizes, live, seconds, None

    def frame(self) -> DataFrame:
        """``log_frame``, with running sums by ranges of phases."""
        spark = self.sizes.sparkSession
        sizes = prefix_sum(self.sizes, ["removed"], F.col("n"), Scratch(spark, "log"), "gone")
        each = self.seconds / max(self.sizes.count(), 1)
        live = F.lit(self.live) - F.col("gone")
        tail = sizes.select(
            F.col("removed").alias("phase"), live.alias("live_before"), F.col("m").alias("matched"), F.col("n").alias("removed"), (live - F.col("n")).alias("live_after"),
            ((live - F.col("n")) / live).alias("shrink"), F.lit(each).alias("seconds"),
        )
        return spark.createDataFrame([tuple(x.get(c) for c in LOG_COLUMNS) for x in self.lines], LOG_SCHEMA).unionByName(tail)

    def __len__(self) -> int:
        return len(self.lines) + (self.sizes.count() if self.known is None else len(self.known))

    def __getitem__(self, k):
        if self.known is None:
            count, self.known = self.live, []
            rows = self.sizes.orderBy("removed").collect()
            for r in rows:
                self.known.append(_line(r["removed"], count, r["m"], count - r["n"], self.seconds / len(rows)))
                count -= r["n"]
        return (self.lines + self.known)[k]


LOG_COLUMNS = ("phase", "live_before", "matched", "removed", "live_after", "shrink", "seconds")
LOG_SCHEMA = "phase int, live_before long, matched long, removed long, live_after long, shrink double, seconds double"


def candidates(live: DataFrame, by: list[str] = (), levels: int = 1) -> DataFrame:
    """The best live edge of each vertex; ``levels=2`` spreads hubs over salts first."""
    ends = arcs(live, "eid", "key", *by)
    if levels == 2:
        salted = ends.groupBy(*by, "vertex", F.pmod(F.col("eid"), F.lit(64)).alias("salt")).agg(F.max_by("eid", "key").alias("eid"), F.max("key").alias("key"))
        return salted.groupBy(*by, "vertex").agg(F.max_by("eid", "key").alias("eid"))
    return ends.groupBy(*by, "vertex").agg(F.max_by("eid", "key").alias("eid"))


def first_of_runs(live: DataFrame, by: list[str]) -> DataFrame:
    """``candidates`` by sorting: the first cell of each vertex's sorted run."""
    falling = W.partitionBy(*by, "vertex").orderBy(F.col("key").desc())
    return arcs(live, "eid", "key", *by).withColumn("place", F.row_number().over(falling)).where("place = 1").select(*by, "vertex", "eid")


def winners_by_sort(live: DataFrame, by: list[str], levels: int) -> DataFrame:
    votes = first_of_runs(live, by).groupBy(*by, "eid").agg(F.count("*").alias("votes")).where("votes = 2")
    return live.join(votes.select(*by, "eid").hint("merge"), [*by, "eid"], "left_semi")


def winners_by_vote(live: DataFrame, by: list[str], levels: int) -> DataFrame:
    # the two that vote for an edge are its ends, so nothing is looked up among the live edges, which a join would shuffle
    ends = F.min("vertex").alias("u"), F.max("vertex").alias("v")
    return candidates(live, by, levels).groupBy(*by, "eid").agg(F.count("*").alias("votes"), *ends).where("votes = 2").select(*by, "u", "v", "eid")


def winners_by_join(live: DataFrame, by: list[str], levels: int) -> DataFrame:
    best = candidates(live, by, levels)
    left = best.select(*by, F.col("vertex").alias("u"), F.col("eid").alias("best_u"))
    right = best.select(*by, F.col("vertex").alias("v"), F.col("eid").alias("best_v"))
    return live.join(left, [*by, "u"]).join(right, [*by, "v"]).where("eid = best_u and eid = best_v").select(*live.columns)


def winners_by_sql(live: DataFrame, by: list[str], levels: int) -> DataFrame:
    group = "".join(f", {c}" for c in by)
    same = lambda x: "".join(f" and {x}.{c} = e.{c}" for c in by)
    return live.sparkSession.sql(
        f"""
        with best as (
          select vertex{group}, max_by(eid, key) as eid
          from (select u as vertex, eid, key{group} from {{live}} union all select v, eid, key{group} from {{live}})
          group by vertex{group}
        )
        select e.* from {{live}} e
        join best a on a.vertex = e.u and a.eid = e.eid{same("a")}
        join best b on b.vertex = e.v and b.eid = e.eid{same("b")}
        """,
        live=live,
    )


def renewed(seed: int, phase: int):
    """Noise of one phase: 48 bits of md5, so that SQL engines draw the same."""
    text = F.concat_ws("|", F.lit(str(seed)), F.lit(str(phase)), F.col("u").cast("string"), F.col("v").cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long")


WINNERS = {"sort": winners_by_sort, "edges": winners_by_vote, "join": winners_by_join, "sql": winners_by_sql}


def drop_covered(live: DataFrame, won: DataFrame, by: list[str], small: bool, hint: str | None = None) -> DataFrame:
    """Live edges without those that touch a matched vertex. The matched vertices are broadcast
    only where their counted number is small."""
    covered = arcs(won, *by).select(*by, "vertex")
    if small or hint:
        covered = covered.hint(hint or "broadcast")
    for end in ("u", "v"):
        live = live.join(covered.withColumnRenamed("vertex", end), [*by, end], "left_anti")
    return live


def finish(live: DataFrame, by: list[str], after: int) -> DataFrame:
    """The remaining phases in one task (one for each group): ``(by.., u, v, eid, phase)`` of
    matched edges, with the phase in which each other edge went as ``removed``."""
    kinds = dict(live.dtypes)
    schema = ", ".join([*(f"{c} {kinds[c]}" for c in by), "u long, v long, eid long, phase int, removed int"])
    columns = [*by, "u", "v", "eid"]

    def compute(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("key").to_numpy(), kind="stable")[::-1]
        table = table.take(pa.array(order))
        matched, removed = local_max_phases(table.column("u").to_numpy(), table.column("v").to_numpy())
        out = table.select(columns)
        phase = np.where(matched > 0, matched + after, 0)
        return out.append_column("phase", pa.array(phase, pa.int32())).append_column("removed", pa.array(removed + after, pa.int32()))

    rows = live.select(*columns, "key")
    if by:
        return rows.groupBy(*by).applyInArrow(compute, schema)
    return one_task(rows, compute, schema)


def local_max(
    edges: DataFrame, *, weight: str | None = "w", ties: str = "portable", seed: int = 42, plan: str = "edges", levels: int = 1, by: tuple[str, ...] = (),
    max_phases: int = 200, finish_rows: int = 1_000_000, stop_after: int | None = None, scratch: Scratch | None = None, owners: dict | None = None,
) -> MatchResult:
    """Maximal matching of a canonical edge table, with ``phase`` of each matched edge.

    ``ties``: portable, static or id order among equal weights, ``renew``: unit weights and fresh
    noise for each phase, or ``given``: written edges that have their ``eid``. ``weight=None``: unit weights. ``by``: columns that tell apart
    many graphs matched at once. Live edges of ``finish_rows`` or fewer go to one task (0: never);
    ``max_phases`` ends in an error unless edges fit the finish. ``stop_after`` leaves the
    matching as it is after so many phases, not maximal then. ``owners``: options ``parts`` and
    ``owner`` (range or hash) of the plan ``blocks``.
    """
    spark = edges.sparkSession
    make_importable(spark)
    scratch = scratch or Scratch(spark, "localmax")
    by = list(by)
    if weight is None:
        edges = unit_weights(edges) if not by else edges.withColumn("w", F.lit(1).cast("long"))
    elif weight != "w":
        edges = edges.withColumn("w", F.col(weight))
    if ties == "given":
        ordered = edges
    elif by:
        tie = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("u").cast("string"), F.col("v").cast("string")))
        placed = edges.withColumn("tie", F.unhex(tie)).orderBy(F.col("w").asc(), F.col("tie").desc(), F.col("u").desc(), F.col("v").desc())
        ordered = scratch.save(placed.select(*by, "u", "v", "w", F.monotonically_increasing_id().alias("eid")), "edges")
    else:
        ordered = ordered_edges(edges, scratch, "portable" if ties == "renew" else ties, seed)
    if plan in ("arcs", "primitives", "blocks"):
        from . import blocks, crew

        if plan == "blocks":
            picked, log = blocks.run(ordered, scratch, max_phases, **(owners or {}))
        else:
            picked, log = crew.run(ordered, scratch, max_phases, crew.phase_flags if plan == "arcs" else crew.primitive_flags)
        return MatchResult(ordered.join(picked, "eid").select("u", "v", "w", "eid", "phase"), ordered, log)
    live, parts, log, phase = ordered.select(*by, "u", "v", "eid"), [], [], 0
    count = live.count()
    limit = 1 << 62 if plan == "kernel" else finish_rows
    while count:
        if count <= limit and ties != "renew" and stop_after is None:
            began = time.time()
            rest = scratch.save(finish(live.withColumn("key", F.col("eid")), by, phase), "finish")
            parts.append(rest.where("phase > 0").select(*by, "eid", "phase"))
            sizes = rest.groupBy("removed").agg(F.count("*").alias("n"), F.sum((F.col("phase") > 0).cast("int")).alias("m"))
            log = PhaseLog(log, scratch.save(sizes, "sizes"), count, time.time() - began)
            break
        phase += 1
        if phase > max_phases:
            raise RuntimeError(f"{count} edges are left after {max_phases} phases")
        if stop_after is not None and phase > stop_after:
            break
        began = time.time()
        keyed = live.withColumn("key", renewed(seed, phase) if ties == "renew" else F.col("eid"))
        won = scratch.save(WINNERS["edges" if plan == "kernel" else plan](keyed, by, levels).select(*by, "u", "v", "eid"), "won")
        matched = won.count()
        if not matched:
            raise RuntimeError("a phase matched nothing")
        after = scratch.save(drop_covered(live, won, by, matched <= BROADCAST_ROWS, "merge" if plan == "sort" else None), "live")
        left = after.count()
        log.append(_line(phase, count, matched, left, time.time() - began))
        parts.append(won.select(*by, "eid", F.lit(phase).alias("phase")))
        scratch.drop(live)
        live, count = after, left
    columns = [*by, "u", "v", "w", "eid", "phase"]
    if not parts:
        return MatchResult(ordered.withColumn("phase", F.lit(0)).where("false").select(*columns), ordered, log)
    picked = parts[0]
    for p in parts[1:]:
        picked = picked.unionByName(p)
    return MatchResult(ordered.join(picked, [*by, "eid"]).select(*columns), ordered, log)


def _line(phase: int, before: int, matched: int, after: int, seconds: float) -> dict:
    return {"phase": phase, "live_before": before, "matched": matched, "removed": before - after, "live_after": after, "shrink": after / before, "seconds": seconds}


def maximal_matching(edges: DataFrame, *, seed: int = 42, renew: bool = True, **options) -> MatchResult:
    """Unweighted maximal matching; ``renew`` draws new noise for each phase."""
    return local_max(edges, weight=None, ties="renew" if renew else "static", seed=seed, **options)
