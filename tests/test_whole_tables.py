"""Registered queries run on whole tables: none keeps to the first rows of one."""

import duckdb
import pytest

from matchloom import registry
from matchloom.edges import arcs
from matchloom.operators import baselines, paths
from matchloom.operators.localmax import local_max
from matchloom.sources import graphs
from test_local_max import edges_of

SMALL, SF = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def pairs(df):
    return {(r["u"], r["v"]) for r in df.select("u", "v").collect()}


def assert_maximal(rows, edges):
    used = {x for e in rows for x in e}
    assert len(used) == 2 * len(rows) and rows <= edges and all(u in used or v in used for u, v in edges)


@pytest.mark.parametrize("name", ["hem_id_whole", "hem_random_whole", "red_blue_whole", "random_proposal"])
def test_baselines_are_maximal_on_all_parts(spark, name):
    rows = registry.QUERIES[name](spark, SF)
    assert_maximal(pairs(rows), pairs(graphs.part_supp(spark, SF)))


def test_line_graph_matching_covers_all_customers(spark):
    assert_maximal(pairs(registry.QUERIES["line_graph_matching"](spark, SMALL)), pairs(graphs.customer_nation(spark, SMALL)))


@pytest.mark.parametrize("name", ["hem_rounds_whole", "red_blue_whole", "line_graph_whole"])
def test_whole_tables_match_sql(spark, name):
    con = duckdb.connect()
    for t in ("lineitem", "customer"):
        con.execute(f"create view {t} as select * from '{SF if name == 'line_graph_whole' else SMALL}/{t}.parquet'")
    got = registry.QUERIES[name](spark, SF if name == "line_graph_whole" else SMALL)
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(f"select {', '.join(got.columns)} from ({registry.SQL[name]})").fetchall())


def test_growth_spans_all_parts(spark):
    rows = registry.QUERIES["gpa_growth"](spark, SF).collect()
    degree = {}
    for r in rows:
        for x in (r["u"], r["v"]):
            degree[x] = degree.get(x, 0) + 1
    assert max(degree.values()) == 2 and {(r["u"], r["v"]) for r in rows} <= pairs(graphs.part_supp(spark, SF))
    # all suppliers are on paths: each has more parts than it can hold
    suppliers = arcs(graphs.part_supp(spark, SF)).where(f"vertex >= {graphs.RIGHT}").select("vertex").distinct()
    assert all(degree[r["vertex"]] == 2 for r in suppliers.collect())


def test_exact_on_all_nations(spark):
    assert {v for _, v in pairs(registry.QUERIES["exact_small"](spark, SMALL))} == {v for _, v in pairs(graphs.nation_region(spark, SMALL))}


def test_heavy_edge_leaves_the_scan_above_its_bound(spark, monkeypatch):
    edges = graphs.customer_nation(spark, SMALL)
    want = edges_of(baselines.heavy_edge(edges, "random", engine="scan"))
    monkeypatch.setattr(baselines, "SCAN_ROWS", 10)
    assert edges_of(baselines.heavy_edge(edges, "random", engine="auto")) == want


def test_rising_path_is_matched_to_its_end(spark):
    rows = registry.QUERIES["lm_rising_path_whole"](spark, SF).collect()
    edges = graphs.rising_path(spark, SF).count()
    assert {r["w"] for r in rows} == set(range(edges, 0, -2)) and {r["phase"] for r in rows} == set(range(1, (edges + 1) // 2 + 1))


def test_coarsening_goes_on_until_few_vertices_are_left(spark):
    rows = registry.QUERIES["coarsen_levels"](spark, SF).orderBy("level").collect()
    print(rows)
    assert all(a["coarse_edges"] == b["edges"] for a, b in zip(rows, rows[1:]))
    assert len(rows) > 4 and rows[-1]["coarse_edges"] <= 32 * 31 // 2
