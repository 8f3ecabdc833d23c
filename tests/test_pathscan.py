"""Long paths by doubling and segments, against the sequential kernels."""

import random

from matchloom.functions.kernels import path_optimum
from matchloom.operators import pathscan
from matchloom.storage import Scratch


def links_of(seed):
    """Paths and even cycles with shuffled vertex names; comp is the least vertex."""
    rng = random.Random(seed)
    names, at, links, parts = rng.sample(range(10_000), 400), 0, [], {}
    for cycle, n in [(False, 1), (False, 2), (False, 13), (True, 4), (True, 10)]:
        own = names[at : at + n + (not cycle)]
        at += len(own)
        pairs = list(zip(own, own[1:])) + ([(own[-1], own[0])] if cycle else [])
        w = [rng.randint(1, 30) for _ in pairs]
        parts[min(own)] = (cycle, own, w)
        links += [(0, min(p), max(p), x, min(own)) for p, x in zip(pairs, w)]
    rng.shuffle(links)
    return [(k, *e[1:]) for k, e in enumerate(links)], parts


def test_places_follow_the_links(spark):
    for seed in (1,):
        links, parts = links_of(seed)
        df = spark.createDataFrame(links, "eid long, u long, v long, w long, comp long")
        rows = {}
        for r in pathscan.rank_links(df, Scratch(spark, "t")).collect():
            rows.setdefault(r["comp"], []).append(r)
        assert rows.keys() == parts.keys()
        for comp, (cycle, own, w) in parts.items():
            got = sorted(rows[comp], key=lambda r: r["place"])
            assert [r["place"] for r in got] == list(range(len(w))) and all(r["is_cycle"] == cycle and r["length"] == len(w) for r in got)
            if cycle:
                k = own.index(comp)
                turned = own[k:] + own[:k]
                walk = turned + [comp] if turned[1] < turned[-1] else [comp, *turned[:0:-1], comp]
            else:
                walk = own if own[0] < own[-1] else own[::-1]
            assert [(r["u"], r["v"]) for r in got] == [tuple(sorted(p)) for p in zip(walk, walk[1:])]


def test_segments_find_the_optimum(spark):
    links, parts = links_of(3)
    scratch = Scratch(spark, "t")
    ranked = scratch.save(pathscan.rank_links(spark.createDataFrame(links, "eid long, u long, v long, w long, comp long"), scratch))
    weight = {e[0]: e[3] for e in links}
    for segment in (3, 4096):
        taken = {}
        for r in pathscan.optimum_links(ranked, scratch, segment).collect():
            taken.setdefault(r["comp"], []).append(r)
        for comp, (cycle, own, w) in parts.items():
            got = taken.get(comp, [])
            ends = [x for r in got for x in (r["u"], r["v"])]
            assert len(ends) == len(set(ends)), (segment, comp)
            assert sum(weight[r["eid"]] for r in got) == sum(w[k] for k in path_optimum([float(x) for x in w], cycle)), (segment, comp)


def test_tables_multiply():
    rng = random.Random(4)
    w = [rng.randint(0, 9) for _ in range(12)]
    whole = pathscan.link_table(w)
    for cut in range(1, 12):
        assert pathscan.product([pathscan.link_table(w[:cut]), pathscan.link_table(w[cut:])]) == whole
