"""Local max in all plans, its laws, options and edge cases."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from matchloom.edges import canonical_edges, ordered_edges
from matchloom.functions import measures
from matchloom.functions.kernels import greedy_scan, local_max_phases
from matchloom.operators import blocks
from matchloom.operators.localmax import local_max, maximal_matching
from matchloom.storage import Scratch


def frame(spark, rows, kind="long"):
    return spark.createDataFrame(rows, f"u long, v long, w {kind}")


def edges_of(result):
    return {(r["u"], r["v"]) for r in result.matching.collect()}


def random_graph(seed, n=40, m=150, weights=12):
    rng = random.Random(seed)
    pairs = {tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)}
    return [(u, v, rng.randint(1, weights)) for u, v in sorted(pairs)]


def plain_local_max(rows, key):
    live, out, phase = list(rows), {}, 0
    while live:
        phase += 1
        best = {}
        for e in live:
            for x in e[:2]:
                if x not in best or key(e) > key(best[x]):
                    best[x] = e
        won = {e for e in live if best[e[0]] == e and best[e[1]] == e}
        used = {x for e in won for x in e[:2]}
        out.update({e[:2]: phase for e in won})
        live = [e for e in live if e[0] not in used and e[1] not in used]
    return out


def test_kernel_gives_phases_and_greedy():
    for seed in range(60):
        rows = random_graph(seed, n=random.Random(seed).randint(2, 30))
        order = sorted(rows, key=lambda e: (-e[2], e[0], e[1]))
        u, v = (np.array([e[k] for e in order]) for k in (0, 1))
        matched, removed = local_max_phases(u, v)
        want = plain_local_max(rows, lambda e: (e[2], -e[0], -e[1]))
        assert {e[:2]: p for e, p in zip(order, matched.tolist()) if p} == want
        assert (removed > 0).all() and ((matched > 0) == greedy_scan(u, v)).all()


def test_kernel_long_tail_of_phases():
    n = 101
    u, v = np.arange(n)[::-1].copy(), np.arange(1, n + 1)[::-1].copy()
    matched, _ = local_max_phases(u, v)
    assert matched.max() == 51 and (matched > 0).sum() == 51


def test_all_plans_agree(spark):
    edges = frame(spark, random_graph(3, n=60, m=300)).cache()
    want = {(r["u"], r["v"], r["phase"]) for r in local_max(edges, plan="kernel").matching.collect()}
    for options in ({"finish_rows": 0}, {"plan": "join", "finish_rows": 0}, {"plan": "sql", "finish_rows": 0}, {"plan": "arcs"}, {"finish_rows": 0, "levels": 2}, {"finish_rows": 60}):
        result = local_max(edges, **options)
        assert {(r["u"], r["v"], r["phase"]) for r in result.matching.collect()} == want, options
        assert result.is_valid() and result.is_maximal()
    assert edges_of(local_max(edges, plan="blocks")) == {x[:2] for x in want}
    scratch = Scratch(spark, "t")
    picked, _ = blocks.run(ordered := ordered_edges(edges, scratch), scratch, 100, parts=3, owner="range")
    assert {(r["u"], r["v"]) for r in ordered.join(picked, "eid").collect()} == {x[:2] for x in want}


def test_hand_graphs(spark):
    assert edges_of(local_max(frame(spark, []))) == set()
    assert edges_of(local_max(frame(spark, [(0, 1, 5)]))) == {(0, 1)}
    chain = local_max(frame(spark, [(0, 1, 5), (1, 2, 6), (2, 3, 5), (3, 4, 1)]), finish_rows=0)
    assert edges_of(chain) == {(1, 2), (3, 4)} and chain.weight() == 7 and len(chain.log) == 2
    assert edges_of(local_max(frame(spark, [(0, i, i) for i in range(1, 50)]))) == {(0, 49)}
    clique = local_max(frame(spark, [(i, j, 1) for i in range(20) for j in range(i + 1, 20)]))
    assert clique.size() == 10 and clique.is_valid()
    ids = local_max(frame(spark, [(2**60, 2**60 + 1, 3), (2**60 + 1, 2**60 + 2, 4)]))
    assert edges_of(ids) == {(2**60 + 1, 2**60 + 2)}


def test_canonical_options(spark):
    rows = [(1, 1, 9.0), (2, 1, 3.0), (1, 2, 4.0), (None, 2, 1.0), (3, 4, None), (3, 4, float("nan")), (5, 6, -2.0), (7, 8, 0.0)]
    df = frame(spark, rows, "double")
    got = lambda **o: {(r["u"], r["v"]): r["w"] for r in canonical_edges(df, **o).collect()}
    assert got() == {(1, 2): 7.0}
    assert got(combine="max") == {(1, 2): 4.0} and got(combine="min") == {(1, 2): 3.0}
    assert got(nonpositive="abs")[(5, 6)] == 2.0 and got(nonpositive="keep")[(5, 6)] == -2.0
    with pytest.raises(Exception):
        canonical_edges(df, loops="error").collect()
    with pytest.raises(Exception):
        canonical_edges(df, combine="error").collect()


def test_groups_are_matched_apart(spark):
    rows = [(g, u, v, w) for g in "ab" for u, v, w in random_graph(ord(g))]
    df = spark.createDataFrame(rows, "g string, u long, v long, w long")
    for options in ({}, {"finish_rows": 0}):
        got = {(r["g"], r["u"], r["v"]) for r in local_max(df, by=("g",), **options).matching.collect()}
        want = {(g, *e) for g in "ab" for e in edges_of(local_max(df.where(F.col("g") == g).select("u", "v", "w")))}
        assert got == want


def test_halving_with_unit_weights_and_fresh_noise():
    """Mean share removed in a phase over many draws, on the shapes that are worst."""
    shapes = {"star": [(0, i) for i in range(1, 40)], "cycle": [(i, (i + 1) % 60) for i in range(60)], "path": [(i, i + 1) for i in range(100)], "clique": [(i, j) for i in range(16) for j in range(i + 1, 16)]}
    rng = np.random.default_rng(1)
    for name, pairs in shapes.items():
        shares, marks = [], []
        degree = np.bincount(np.array(pairs).ravel())
        for _ in range(40):
            order = rng.permutation(len(pairs))
            u, v = (np.array([pairs[k][c] for k in order]) for c in (0, 1))
            matched, removed = local_max_phases(u, v)
            shares.append((removed == 1).mean())
            first = matched == 1
            marks.append(degree[u[first]].sum() + degree[v[first]].sum())
        assert np.mean(shares) >= 0.5, name
        assert np.mean(marks) >= len(pairs) * 0.97, name  # expectation is at least the number of edges


def test_maximal_matching_is_deterministic(spark):
    edges = frame(spark, random_graph(9, n=80, m=500))
    first = maximal_matching(edges)
    assert first.is_valid() and first.is_maximal()
    assert edges_of(first) == edges_of(maximal_matching(edges.repartition(7)))
    assert edges_of(first) != edges_of(maximal_matching(edges, seed=5))


def test_measures(spark):
    edges = frame(spark, [(0, 1, 5), (1, 2, 6), (2, 3, 5), (3, 4, 1)])
    result = local_max(edges)
    assert measures.weight_upper_bound(edges).first()[0] == 5 + 6 + 6 + 5 + 1
    assert measures.mark_count(edges, result.matching.where("phase = 1")).first()[0] == 4
    assert measures.loose_edges(edges, result.matching).isEmpty() and measures.double_use(result.matching).isEmpty()
    ratio = measures.quality_vs(result.matching, edges.where("u in (0, 2)")).first()
    assert ratio["ratio"] == pytest.approx(0.7) and ratio["gap_percent"] == pytest.approx(30)
    log = measures.phase_summary(result.log_frame()).first()
    assert log["phases"] == 2 and log["total_work"] == pytest.approx(1.25)
    assert measures.balance_check(edges, 2).first()["balanced"]
    assert measures.cut_fraction(edges, 2).first()["cut"] >= 1
