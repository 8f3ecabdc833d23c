"""Baselines against plain scans, the exact optimum, and path optima against brute force."""

import itertools
import random

import numpy as np
import pytest

from matchloom.edges import ordered_edges
from matchloom.functions.kernels import assignment, exact_weight, path_optimum
from matchloom.operators import baselines, coarsen, paths
from matchloom.operators.localmax import local_max
from matchloom.storage import Scratch
from test_local_max import edges_of, frame, random_graph


def test_path_optimum_is_exact():
    rng = random.Random(1)
    for _ in range(200):
        n, cycle = rng.randint(1, 9), rng.random() < 0.5
        if cycle:
            n += n % 2 or 2
            n = max(4, n - n % 2)
        w = [rng.randint(1, 9) for _ in range(n)]

        def legal(s):
            return all(b - a > 1 for a, b in zip(s, s[1:])) and not (cycle and len(s) > 1 and s[0] == 0 and s[-1] == n - 1)

        best = max(sum(w[i] for i in s) for k in range(n + 1) for s in itertools.combinations(range(n), k) if legal(s))
        got = sorted(path_optimum([float(x) for x in w], cycle))
        assert legal(got) and sum(w[i] for i in got) == best


def test_exact_and_half_guarantee():
    rng = random.Random(2)
    for seed in range(60):
        rows = random_graph(seed, n=rng.randint(4, 9), m=rng.randint(3, 16), weights=9)
        u, v, w = (np.array([e[k] for e in rows]) for k in range(3))
        best, chosen = exact_weight(u, v, w.astype(float))
        brute = max(sum(rows[i][2] for i in s) for k in range(5) for s in itertools.combinations(range(len(rows)), k) if len({x for i in s for x in rows[i][:2]}) == 2 * k)
        assert best == brute == sum(rows[i][2] for i in chosen)
        order = sorted(rows, key=lambda e: -e[2])
        from matchloom.functions.kernels import greedy_scan

        taken = greedy_scan(*(np.array([e[k] for e in order]) for k in (0, 1)))
        assert 2 * sum(e[2] for e, t in zip(order, taken) if t) >= best


def test_assignment_is_exact():
    rng = random.Random(6)
    for _ in range(150):
        a, b = rng.randint(1, 6), rng.randint(1, 6)
        rows = [(x, 100 + y, rng.randint(1, 9)) for x in range(a) for y in range(b) if rng.random() < 0.6]
        if rows:
            u, v, w = (np.array([e[k] for e in rows]) for k in range(3))
            taken = assignment(u, v, w)
            assert len(set(u[taken])) == len(set(v[taken])) == len(taken)
            assert w[taken].sum() == exact_weight(u, v, w.astype(float))[0]


def test_scans_and_rounds_agree(spark):
    edges = frame(spark, random_graph(4, n=30, m=90)).cache()
    assert edges_of(baselines.greedy(edges, engine="scan")) == edges_of(local_max(edges)) == edges_of(baselines.pointer_matching(edges))
    for order in ("id", "random"):
        scan, rounds = (baselines.heavy_edge(edges, order, engine=e) for e in ("scan", "rounds"))
        assert edges_of(scan) == edges_of(rounds) and rounds.is_valid() and rounds.is_maximal()


def test_randomised_methods_are_maximal(spark):
    edges = frame(spark, random_graph(8, n=30, m=90)).cache()
    for method in (baselines.red_blue, baselines.random_proposal, baselines.line_graph_matching):
        result = method(edges)
        assert result.is_valid() and result.is_maximal(), method.__name__


def test_line_graph_guard(spark):
    ordered = ordered_edges(frame(spark, [(0, i, i) for i in range(1, 20)]), Scratch(spark, "t"))
    assert baselines.line_graph(ordered).count() == 19 * 18 // 2
    with pytest.raises(ValueError):
        baselines.line_graph(ordered, most=10)


def test_global_paths(spark):
    chain = frame(spark, [(0, 1, 5), (1, 2, 6), (2, 3, 5), (3, 4, 1)])
    assert edges_of(paths.global_paths(chain)) == {(0, 1), (2, 3)}
    triangle = frame(spark, [(0, 1, 3), (1, 2, 2), (0, 2, 1)])
    assert edges_of(paths.global_paths(triangle)) == {(0, 1)}
    edges = frame(spark, random_graph(11, n=24, m=60)).cache()
    scan, rounds = (edges_of(paths.global_paths(edges, engine=e)) for e in ("scan", "rounds"))
    weight = {(u, v): w for u, v, w in random_graph(11, n=24, m=60)}
    assert sum(weight[e] for e in scan) == sum(weight[e] for e in rounds)
    scratch = Scratch(spark, "t")
    ordered = ordered_edges(edges, scratch)
    one = {(r["u"], r["v"]) for r in paths.grown_links_scan(ordered).collect()}
    assert one == {(r["u"], r["v"]) for r in paths.grow_paths(ordered, scratch).collect()}
    full = paths.global_paths(edges, rounds=3, maximal=True)
    assert full.is_valid() and full.is_maximal()


def test_coarsening_keeps_weight(spark):
    edges = frame(spark, random_graph(5, n=40, m=150)).cache()
    for rating in ("weight", "expansion2", "inner_outer"):
        levels = coarsen.coarsen(edges, rating=rating, min_vertices=4, max_levels=3)
        total = sum(w for _, _, w in random_graph(5, n=40, m=150))
        for x in levels:
            joined = x["matching"].select("u", "v").join(x["edges"], ["u", "v"]).agg({"w": "sum"}).first()[0]
            left = x["coarse"].agg({"w": "sum"}).first()[0] or 0
            assert left + joined == total
            assert x["vertex_weight"].agg({"c": "sum"}).first()[0] == 40
            total = left


def test_exact_by_component(spark):
    edges = frame(spark, [(0, 1, 5), (1, 2, 6), (2, 3, 5), (10, 11, 1), (11, 12, 3)])
    assert edges_of(baselines.exact_matching(edges)) == {(0, 1), (2, 3), (11, 12)}
