"""Findings on larger inputs: whole jobs where a guard, one task or the driver was in the way."""

import random
from itertools import combinations

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from matchloom import registry
from matchloom.edges import ordered_edges
from matchloom.storage import Scratch

from test_local_max import edges_of, frame, random_graph

SMALL = "/root/testdata/sf0.001"


def by_sql(name, d=SMALL):
    con = duckdb.connect()
    for t in ("part", "orders", "lineitem", "customer", "supplier", "nation", "region", "events", "embeddings"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    return con.execute(__spark_entry__.oracle_sql()[name]).fetchall()


@pytest.mark.parametrize("name", ["graph_random_alpha", "graph_random_alpha_16", "graph_random_alpha_64"])
def test_random_graphs_read_their_vertices(spark, name):
    df = registry.QUERIES[name](spark, SMALL)
    assert [f for f in df.inputFiles() if f.endswith("part.parquet")]
    assert sorted(map(tuple, df.collect())) == sorted(by_sql(name))


def test_line_graph_of_hubs_in_blocks(spark, monkeypatch):
    from matchloom.operators import baselines

    monkeypatch.setattr(baselines, "BLOCK_CELLS", 4)
    rows = random_graph(31, n=20, m=90) + [(100, k, 1) for k in range(101, 140)]
    got = [tuple(r) for r in registry.named_line_graph(frame(spark, rows)).collect()]
    named = sorted((u, v) for u, v, _ in rows)
    want = {(*a, *b) for a, b in combinations(named, 2) if set(a) & set(b)}
    assert len(got) == len(want) and set(got) == want


def test_line_graph_has_no_bound_unless_asked(spark):
    """The star of customers at 6 x sf0.1 has 162 million pairs; the bound stopped at 50."""
    star = spark.range(1, 11_001).selectExpr("0L as u", "id as v", "1L as w")
    from matchloom.operators import baselines

    ordered = ordered_edges(star, Scratch(spark, "star"))
    assert baselines.line_graph(ordered).count() == 11_000 * 10_999 // 2
    result = baselines.line_graph_matching(star)
    assert result.size() == 1


def test_assignment_proves_itself():
    import numpy as np

    from matchloom.functions.kernels import exact_weight, priced_assignment

    rng = random.Random(3)
    for _ in range(200):
        ends = [(i, 100 + j) for i in range(rng.randint(1, 7)) for j in range(rng.randint(1, 7)) if rng.random() < 0.6] or [(0, 100)]
        (u, v), w = map(np.array, zip(*ends)), np.array([rng.randint(-2, 9) for _ in ends])
        taken, names, prices = priced_assignment(u, v, w)
        price = dict(zip(names.tolist(), prices.tolist()))
        assert prices.min() >= 0 and all(price[a] + price[b] >= c for a, b, c in zip(u.tolist(), v.tolist(), w.tolist()))
        assert len(set(u[taken])) == len(taken) == len(set(v[taken]))
        assert w[taken].sum() == prices.sum() == exact_weight(u, v, w)[0]


def test_bipartite_optimum_of_a_large_table(spark, monkeypatch):
    """8,000 x 8,000 vertices, a table beyond the bound of before, and a core that has to grow."""
    from matchloom.operators import baselines

    n = 8_000
    far = spark.range(n).selectExpr("id as u", "id + 1000000 as v", "10L as w").unionByName(spark.range(n - 1).selectExpr("id as u", "id + 1000001 as v", "11L as w"))
    assert baselines.exact_bipartite(far).weight() == 11 * (n - 1)
    monkeypatch.setattr(baselines, "CORE_EDGES", 1)
    rows = [(u, 100 + v, w) for u, v, w in ((r.randrange(9), r.randrange(12), r.randrange(1, 20)) for r in [random.Random(5)] for _ in range(60))]
    rows = list({(u, v): (u, v, w) for u, v, w in rows}.values())
    from matchloom.functions.kernels import exact_weight
    import numpy as np

    want = exact_weight(*(np.array(c) for c in zip(*rows)))[0]
    assert baselines.exact_bipartite(frame(spark, rows)).weight() == want
    monkeypatch.setattr(baselines, "SCAN_ROWS", 0)
    assert baselines.exact_bipartite(frame(spark, rows)).weight() == want


def test_heavy_edge_by_pieces(spark):
    from matchloom.functions.kernels import heavy_edge_scan
    from matchloom.operators import baselines
    import numpy as np

    rows = random_graph(41, n=40, m=200)
    ordered = ordered_edges(frame(spark, rows), scratch := Scratch(spark, "pieces"))
    falling = sorted(map(tuple, ordered.select("eid", "u", "v").collect()), reverse=True)
    eid, u, v = map(np.array, zip(*falling))
    names = sorted({*u.tolist(), *v.tolist()})
    want = set(eid[heavy_edge_scan(u, v, {x: i for i, x in enumerate(names)})].tolist())
    rank = F.struct(F.lit(0).cast("long"), F.col("vertex"))
    got = baselines.heavy_edge_pieces(ordered, rank, scratch, rows=30)
    assert {r["eid"] for r in got.collect()} == want


def test_percentiles_hold_no_values_in_one_place(spark):
    from matchloom.functions import measures

    for n in (0, 1, 2, 7, 1000):
        df = spark.range(n).selectExpr("pmod(id * 37, 251) - 60 as w")
        shares = {"p25": 0.25, "p50": 0.5, "p90": 0.9}
        got = measures.percentiles(df, "w", shares)
        want = df.agg(*[F.expr(f"percentile(w, {p})").alias(c) for c, p in shares.items()])
        assert got.collect() == want.collect() and got.schema.simpleString() == want.schema.simpleString()
        assert "percentile(" not in got._jdf.queryExecution().toString()


def test_growth_by_pieces_is_growth(spark):
    from matchloom.operators import paths

    scratch = Scratch(spark, "growth")
    ordered = ordered_edges(frame(spark, random_graph(51, n=60, m=400)), scratch)
    want = {tuple(r) for r in paths.grown_links_scan(ordered).select("eid", "comp", "taken").collect()}
    links = paths.grow_by_pieces(ordered, scratch, rows=60)
    assert {tuple(r) for r in paths.grown_links_scan(links).select("eid", "comp", "taken").collect()} == want


def test_log_of_a_long_finish_stays_in_tables(spark):
    """A path of rising weights has as many phases as half its edges."""
    from matchloom.operators.localmax import PhaseLog, local_max

    path = spark.range(400).selectExpr("id as u", "id + 1 as v", "id + 1 as w")
    result = local_max(path, plan="kernel")
    assert isinstance(result.log, PhaseLog) and result.log.known is None and len(result.log) == 200
    frame_ = [tuple(r)[:6] for r in result.log_frame().orderBy("phase").collect()]
    assert result.log.known is None and frame_ == [tuple(x.values())[:6] for x in result.log] and frame_[0][:5] == (1, 400, 1, 2, 398)


def test_delaunay_around_points():
    """The points around one settle it as all points do, in time that does not grow with them."""
    import time

    import numpy as np

    from matchloom.sources.delaunay import Grid, delaunay_partners, partners

    rng = np.random.default_rng(2)
    lattice = np.stack(np.meshgrid(np.arange(14), np.arange(14)), -1).reshape(-1, 2) * 7
    for xy in (rng.integers(0, 1000, (300, 2)), (rng.normal(size=(300, 2)) * 1e5).astype(np.int64), lattice, np.array([[0, 0], [5, 0], [9, 0]])):
        xy = np.unique(xy, axis=0)
        grid = Grid(xy)
        for k in range(len(xy)):
            assert set(partners(xy, grid, k)) == set(delaunay_partners(xy, k))
    xy = np.unique(rng.integers(0, 1_000_000, (100_000, 2)), axis=0)
    grid, began = Grid(xy), time.time()
    for k in range(0, len(xy), 1000):
        partners(xy, grid, k)
    assert time.time() - began < 5  # about 15 s by all points


def test_written_edges_are_ordered_once(spark):
    scratch = Scratch(spark, "once")
    edges = scratch.save(frame(spark, random_graph(5, n=20, m=60)), "edges")
    first = ordered_edges(edges, scratch)
    assert ordered_edges(edges, Scratch(spark, "twice")) is first
    assert ordered_edges(edges, scratch, "static") is not first and ordered_edges(edges, scratch, seed=7) is not first
    weights = [f(edges).weight() for f in registry.METHODS.values()]
    assert weights == [f(frame(spark, random_graph(5, n=20, m=60))).weight() for f in registry.METHODS.values()]


def test_votes_name_the_winners_without_a_join(spark):
    from matchloom.operators import localmax

    live = ordered_edges(frame(spark, random_graph(6, n=30, m=90)), Scratch(spark, "votes")).withColumn("key", F.col("eid"))
    for levels in (1, 2):
        got, want = (f(live, [], levels).select("u", "v", "eid") for f in (localmax.winners_by_vote, localmax.winners_by_join))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
        assert "Join" not in got._jdf.queryExecution().executedPlan().toString()


def test_noise_of_the_order_is_not_shuffled(spark):
    from matchloom import edges as module

    df = frame(spark, [(u, v, w % 3) for u, v, w in random_graph(7, n=40, m=200)]).repartition(5)
    tie = F.unhex(module.portable_tie(3))
    placed = module.in_order(df, tie)
    got = placed.select("u", "v", "w").collect()
    want = df.withColumn("tie", tie).orderBy("w", F.col("tie").desc(), F.col("u").desc(), F.col("v").desc()).select("u", "v", "w").collect()
    assert got == want
    below = placed._jdf.queryExecution().optimizedPlan().toString().split("RepartitionByExpression")[1]
    assert "AS tie" not in below
