"""Further plans of local max, owners, and the costs of a run in other machine models."""

import math

import numpy as np
from conftest import SF
from matchloom import registry
from matchloom.edges import arcs, ordered_edges
from matchloom.functions import measures
from matchloom.operators import adjacency, baselines, coarsen, crew
from matchloom.operators.localmax import local_max
from matchloom.sources import graphs
from matchloom.storage import Scratch
from test_local_max import edges_of, frame, random_graph


def phases_of(result):
    return {(r["u"], r["v"]): r["phase"] for r in result.matching.collect()}


def test_all_plans_give_the_same_phases(spark):
    edges = frame(spark, random_graph(21, n=16, m=40)).cache()
    want = phases_of(local_max(edges, plan="kernel"))
    for plan in ("edges", "sort", "arcs", "primitives"):
        assert phases_of(local_max(edges, plan=plan, finish_rows=0)) == want, plan
    for owner in ("range", "hash"):
        result = local_max(edges, plan="blocks", owners={"owner": owner, "parts": 5})
        assert edges_of(result) == set(want) and all(x["shuffle_rows"] <= x["live_after"] for x in result.log)
    assert edges_of(baselines.pointer_rounds(edges)) == set(want)


def test_cells_move_together(spark):
    scratch = Scratch(spark, "t")
    ordered = ordered_edges(frame(spark, random_graph(22, n=20, m=60)), scratch)
    _, placed = adjacency.build_adjacency(ordered, scratch)
    cells = scratch.save(adjacency.twin_positions(placed).withColumnRenamed("twin_pos", "twin"))
    moved = crew.move_cells(scratch.save(crew.phase_flags(cells)), scratch).collect()
    at = {r["pos"]: r for r in moved}
    assert sorted(at) == list(range(len(moved))) and len(moved) > 0
    assert all(at[r["twin"]]["eid"] == r["eid"] and at[r["twin"]]["vertex"] == r["other"] for r in moved)
    assert [at[k]["vertex"] for k in sorted(at)] == sorted(r["vertex"] for r in moved)


def test_owners_hold_equal_shares(spark):
    # ids of the two sides lie far apart, as in bipartite graphs
    edges = frame(spark, [(i, 10**9 + i % 7, i + 1) for i in range(93)])
    sizes = [r["n"] for r in measures.owners(edges, 4).groupBy("owner").count().withColumnRenamed("count", "n").collect()]
    assert len(sizes) == 4 and max(sizes) - min(sizes) <= 1 and sum(sizes) == 100


def test_removal_phases_and_messages(spark):
    edges = frame(spark, random_graph(23, n=30, m=100)).cache()
    result = local_max(edges)
    removed = {(r["u"], r["v"]): r["removed"] for r in result.removal_phases().collect()}
    rows = {r["phase"]: r for r in measures.communication(result.removal_phases(), 4).collect()}
    for x in result.log:
        assert rows[x["phase"]]["live"] == x["live_before"] == sum(p >= x["phase"] for p in removed.values())
        assert rows[x["phase"]]["messages"] == 4 * rows[x["phase"]]["cut"] <= 4 * x["live_before"]


def test_costs_by_hand(spark):
    log = spark.createDataFrame([(1, 5000), (2, 500), (3, 1)], "phase int, live_before long")
    assert [tuple(r) for r in measures.mapreduce_cost(log, 100).orderBy("phase").collect()] == [(1, 2, 20000), (2, 2, 2000), (3, 1, 2)]
    # 10000 cells, memory 1000, fan 10: two passes; 1000 and 2 cells fit at once
    assert [tuple(r) for r in measures.io_cost(log, 1000, 100).orderBy("phase").collect()] == [(1, 2, 400), (2, 1, 20), (3, 1, 2)]
    for size, start, fan in ((1, 1, 2), (8, 1, 2), (9, 1, 2), (10**9, 10, 10)):
        got = spark.range(1).select(measures.levels_above(measures.F.lit(size), start, fan)).first()[0]
        assert got == max(0, math.ceil(round(math.log(size / start, fan), 9)))


def test_bound_ratio_is_half_or_more(spark):
    edges = frame(spark, random_graph(24, n=30, m=100)).cache()
    assert 0.5 <= measures.bound_ratio(edges, local_max(edges).matching).first()[0] <= 1
    assert arcs(edges).count() == 2 * edges.count()


def test_doubling_ratios_by_hand(spark):
    rows = measures.doubling_ratio(spark.createDataFrame([(1, 8.0), (2, 4.0), (4, 2.5)], "p int, seconds double")).orderBy("p").collect()
    assert [(r["ratio"], r["speedup"], r["efficiency"]) for r in rows] == [(None, 1.0, 1.0), (2.0, 2.0, 1.0), (1.6, 3.2, 0.8)]


def test_noise_is_no_expression_of_the_sort(spark):
    class Kept:
        def save(self, df, name):
            return df

    for ties in ("portable", "static", "id"):
        plan = ordered_edges(frame(spark, random_graph(4, n=9, m=12)), Kept(), ties)._jdf.queryExecution().optimizedPlan().toString()
        (line,) = [x for x in plan.splitlines() if "Sort [" in x]
        assert "md5" not in line and "xxhash64" not in line


def test_pairs_of_few_points_are_many_tasks(spark):
    edges = graphs.rgg_events(spark, SF, True)
    held = Scratch(spark, "held").save(edges.select("u"), "edges")
    assert len(held.inputFiles()) >= spark.sparkContext.defaultParallelism // 2


def test_sweep_runs_each_matching_to_its_end(spark, monkeypatch):
    seen = []

    def kept(edges, **options):
        seen.append(local_max(edges, **options))
        return seen[-1]

    monkeypatch.setattr(registry, "local_max", kept)
    monkeypatch.setattr(registry, "SWEEP_FINISH", 0, raising=False)
    assert [p for p, _ in registry.timed_parts(spark, SF, most=2)] == [1, 2]
    assert len(seen) == 2 and all(r.is_maximal() for r in seen) and edges_of(seen[0]) == edges_of(seen[1])


def test_gram_edges_are_made_once_and_as_if_summed_in_order(spark):
    assert all("/gram-" in f for f in graphs.gram(spark, SF).inputFiles())
    rng = np.random.default_rng(8)
    # products of whole thousandths lie on the border of two weights
    for a, b in ((rng.normal(size=(40, 64)), rng.normal(size=(50, 64))), (rng.integers(-3, 4, (40, 64)) / 1000.0, rng.integers(-3, 4, (50, 64)) / 1000.0)):
        total = np.zeros((40, 50))
        for k in range(64):
            total += a[:, k][:, None] * b[:, k][None, :]
        assert (graphs.floored_products(a, b) == np.floor(np.abs(total) * graphs.STEPS)).all()


def test_rating_joins_only_what_it_asks_for(spark):
    edges = frame(spark, [(1, 2, 6), (2, 3, 4)])
    weights = spark.createDataFrame([(1, 1), (2, 2), (3, 1)], "vertex long, c long")
    rated = coarsen.rate_edges(edges, weights, "expansion2")
    assert {(r["u"], r["v"]): r["rating"] for r in rated.collect()} == {(1, 2): 18_000_000, (2, 3): 8_000_000}
    assert rated._jdf.queryExecution().optimizedPlan().toString().count("Join ") == 2
