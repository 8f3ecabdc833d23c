"""Local max with vertex owners. A task owns some vertices with all their edges; it matches
its inner edges as long as it can, then owners exchange what concerns cut edges only: which
of them are the best of an end, and which vertices are gone."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..edges import arcs
from ..storage import Scratch


def settle_block(vertex: np.ndarray, other: np.ndarray, eid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Inner edges that are matched for good, and cut edges that are the best of their end."""
    own, at = np.unique(vertex, return_inverse=True)
    spot = np.minimum(np.searchsorted(own, other), max(len(own) - 1, 0))
    inner = own[spot] == other
    live, done = np.ones(len(eid), bool), []
    while True:
        idx = np.flatnonzero(live)
        best = np.full(len(own), -1, np.int64)
        np.maximum.at(best, at[idx], eid[idx])
        top = idx[(best[at[idx]] == eid[idx])]
        won = top[inner[top]]
        won = won[best[spot[won]] == eid[won]]
        if not len(won):
            return np.unique(np.concatenate(done)) if done else np.zeros(0, np.int64), eid[top[~inner[top]]]
        done.append(eid[won])
        gone = np.zeros(len(own), bool)
        gone[at[won]] = True
        live &= ~(gone[at] | inner & gone[spot])


#: Cells for each owner, so that what one task holds does not grow with the graph.
OWNER_CELLS = 1 << 20


def run(ordered: DataFrame, scratch: Scratch, max_phases: int, parts: int | None = None, owner: str = "range") -> tuple[DataFrame, list[dict]]:
    """``(eid, phase)``: phase counts exchanges here, which are fewer than phases of a vertex. The log
    tells the rows that crossed owners as ``shuffle_rows``. Owners hold consecutive vertices
    (``range``) or hashed ones."""
    from ..functions.measures import owners
    from .localmax import _line

    parts = parts or max(2, ordered.sparkSession.sparkContext.defaultParallelism, -(-2 * ordered.count() // OWNER_CELLS))
    at = scratch.save(owners(ordered, parts, owner, scratch), "owners")
    cells = arcs(ordered, "eid").join(at, "vertex")
    cells = scratch.save(cells, "owned")
    count, phase, log, out = ordered.count(), 0, [], []

    def settle(table: pa.Table) -> pa.Table:
        won, asked = settle_block(*(table.column(c).to_numpy() for c in ("vertex", "other", "eid")))
        return pa.table({"eid": np.concatenate([won, asked]), "votes": np.concatenate([np.full(len(won), 2), np.ones(len(asked), np.int64)])})

    while count:
        phase += 1
        if phase > max_phases:
            raise RuntimeError(f"{count} edges are left after {max_phases} exchanges")
        began = time.time()
        votes = cells.groupBy("owner").applyInArrow(settle, "eid long, votes long")
        won = scratch.save(votes.groupBy("eid").agg(F.sum("votes").alias("votes")).where("votes >= 2").select("eid"), "won")
        covered = cells.join(won, "eid", "left_semi").select("vertex").distinct()
        left = cells.join(covered, "vertex", "left_anti").join(covered.withColumnRenamed("vertex", "other"), "other", "left_anti").select(*cells.columns)
        left = scratch.save(left, "owned")
        n_won, n_left = won.count(), left.count() // 2
        if not n_won:
            raise RuntimeError("an exchange matched nothing")
        crossed = left.select("eid", "owner").groupBy("eid").agg((F.min("owner") != F.max("owner")).alias("cut")).where("cut").count()
        log.append({**_line(phase, count, n_won, n_left, time.time() - began), "shuffle_rows": crossed})
        out.append(won.select("eid", F.lit(phase).alias("phase")))
        scratch.drop(cells)
        cells, count = left, n_left
    if not out:
        return ordered.select("eid", F.lit(0).alias("phase")).where("false"), log
    picked = out[0]
    for p in out[1:]:
        picked = picked.unionByName(p)
    return picked, log
