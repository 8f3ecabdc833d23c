"""Graph builders, array operators, streams, files and SQL names against plain versions."""

import itertools
import math
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from conftest import SF
from matchloom import registry
from matchloom.edges import arcs, canonical_edges, ordered_edges
from matchloom.functions.register import register_functions, register_views
from matchloom.operators import adjacency, scan
from matchloom.operators.localmax import local_max
from matchloom.plans import report
from matchloom.sources import files, graphs
from matchloom.sources.delaunay import delaunay_edges
from matchloom.storage import Scratch
from matchloom.streaming import windows
from test_local_max import edges_of, frame, random_graph

SMALL = "/root/testdata/sf0.001"


def test_registry_is_consistent():
    assert set(registry.SQL) <= set(registry.QUERIES) and len(registry.QUERIES) > 90


@pytest.mark.parametrize("name", ["lm_part_supp", "lm_order_part", "red_blue_portable", "hem_rounds", "mm_unit_portable", "compact", "twin_positions", "join_asof_events", "stream_tumbling"])
def test_queries_match_sql(spark, name):
    con = duckdb.connect()
    con.execute("set TimeZone = 'UTC'")
    for t in ("part", "lineitem", "orders", "customer", "nation", "region", "events"):
        con.execute(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    got = registry.QUERIES[name](spark, SMALL).toPandas()
    want = con.execute(registry.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and len(got) == len(want)
    cols = sorted(got.columns)
    key = lambda df: sorted(map(str, df[cols].astype(object).where(df[cols].notna(), None).astype(str).itertuples(index=False, name=None)))
    strip = lambda rows: [r.replace(".0'", "'") for r in rows]
    assert strip(key(got)) == strip(key(want))


def test_known_sizes_at_one_hundredth(spark):
    result = local_max(graphs.copurchase(spark, SF))
    assert (result.size(), len(result.log), result.weight()) == (989, 10, 1792)
    assert local_max(graphs.part_supp(spark, SF)).size() == 100


def test_radius_edges_against_all_pairs(spark):
    rng = random.Random(1)
    points = [(i, rng.randrange(1000), rng.randrange(1000)) for i in range(200)]
    df = spark.createDataFrame(points, "id long, x long, y long")
    got = {(r["u"], r["v"]): r["w"] for r in graphs.radius_edges(df, 90).collect()}
    want = {(a[0], b[0]): max(d, 1) for a, b in itertools.combinations(points, 2) if (d := (a[1] - b[1]) ** 2 + (a[2] - b[2]) ** 2) < 8100}
    assert got == want


def test_delaunay_against_empty_circles(spark):
    rng = random.Random(2)
    points = sorted({(rng.randrange(500), rng.randrange(500)) for _ in range(40)})
    df = spark.createDataFrame([(i, *p) for i, p in enumerate(points)], "id long, x long, y long")
    got = {(r["u"], r["v"]) for r in delaunay_edges(df).collect()}
    want = set()
    for tri in itertools.combinations(range(len(points)), 3):
        (ax, ay), (bx, by), (cx, cy) = (points[k] for k in tri)
        d = 2 * (ax * (by - cy) + bx * (cy - ay) + cx * (ay - by))
        if d == 0:
            continue
        ux = ((ax**2 + ay**2) * (by - cy) + (bx**2 + by**2) * (cy - ay) + (cx**2 + cy**2) * (ay - by)) / d
        uy = ((ax**2 + ay**2) * (cx - bx) + (bx**2 + by**2) * (ax - cx) + (cx**2 + cy**2) * (bx - ax)) / d
        r = math.hypot(ax - ux, ay - uy)
        if all(math.hypot(x - ux, y - uy) >= r - 1e-7 for x, y in points):
            want |= {tuple(sorted(e)) for e in itertools.combinations(tri, 2)}
    assert got == want


def test_cells_and_twins(spark):
    scratch = Scratch(spark, "t")
    ordered = ordered_edges(frame(spark, random_graph(2)), scratch)
    vertices, cells = adjacency.build_adjacency(ordered, scratch)
    rows = sorted(cells.collect(), key=lambda r: r["pos"])
    assert [r["pos"] for r in rows] == list(range(len(rows)))
    for v in vertices.collect():
        own = [r for r in rows if r["vertex"] == v["vertex"]]
        assert len(own) == v["degree"] and own[0]["pos"] == v["offset"]
    twins = {r["pos"]: r for r in adjacency.twin_positions(cells).collect()}
    for r in twins.values():
        t = twins[r["twin_pos"]]
        assert t["twin_pos"] == r["pos"] and t["eid"] == r["eid"] and t["vertex"] == r["other"]
    for by in ("degree", "random", "component"):
        moved, names = adjacency.relabel(ordered, scratch, by)
        assert moved.count() == ordered.count() and names.agg(F.max("name")).first()[0] == names.count() - 1


def test_prefix_sum_over_many_ranges(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("k"), (F.col("id") % 13).alias("v"))
    rows = sorted(scan.prefix_sum(df, ["k"], F.col("v"), Scratch(spark, "t")).collect(), key=lambda r: r["k"])
    total = 0
    for r in rows:
        assert r["before"] == total
        total += r["v"]


def test_files_round_trip(spark, tmp_path):
    rows = [(2, 1, -3.0), (1, 2, 5.0), (4, 4, 1.0), (3, 1, 2.0)]
    text = tmp_path / "a.txt"
    text.write_text("# edges\n" + "\n".join(f"{u} {v} {w}" for u, v, w in rows))
    assert {tuple(r) for r in files.read_edges(spark, str(text), "text").collect()} == {(1, 2, 2.0), (1, 3, 2.0)}
    matrix = tmp_path / "a.mtx"
    matrix.write_text("%%MatrixMarket matrix coordinate real symmetric\n4 4 4\n" + "\n".join(f"{u} {v} {w}" for u, v, w in rows))
    assert {tuple(r) for r in files.read_edges(spark, str(matrix), "matrix").collect()} == {(1, 2, 5.0), (1, 3, 2.0)}
    for fmt in ("csv", "json", "parquet"):
        path = str(tmp_path / fmt)
        spark.createDataFrame(rows, "u long, v long, w double").write.option("header", "true").format(fmt).save(path)
        assert files.read_edges(spark, path, fmt).count() == 2
    files.write_result(local_max(frame(spark, [(0, 1, 3)])).matching, str(tmp_path / "out"), partition_by=("phase",))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 1


def test_sql_names(spark):
    names = register_views(spark, SMALL, {"nation_region": graphs.nation_region})
    assert names == ["edges_nation_region", "matching_nation_region"]
    assert spark.sql("select count(*) from matching_nation_region").first()[0] == 5
    register_functions(spark)
    assert spark.sql("select path_optimum(array(1.0D, 5.0D, 3.0D, 4.0D), false)").first()[0] == [1, 3]
    spark.createDataFrame([("a", 0, 1, 5), ("a", 1, 2, 6), ("b", 0, 1, 1)], "grp string, u long, v long, w long").createOrReplaceTempView("small")
    got = {tuple(r) for r in spark.sql("select grp, u, v from local_match(table(select * from small) partition by grp)").collect()}
    assert got == {("a", 1, 2), ("b", 0, 1)}


def test_streams_equal_tables(spark):
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    assert windows.stream_distinct(spark, SMALL).count() == events.count()
    got = {tuple(r) for r in windows.stream_totals(spark, SMALL).collect()}
    assert got == {tuple(r) for r in events.groupBy("event_type").count().collect()}
    result = windows.stream_window_matching(spark, SMALL)
    closed = windows.run_stream(windows.window_graph(windows.read_events(spark, SMALL), "1 day"), "t")
    edges = closed.where("cents > 0").select("window_start", F.col("user_id").alias("u"), windows.type_vertex().alias("v"), F.col("cents").alias("w"))
    day = edges.agg(F.min("window_start")).first()[0]
    one = edges_of(local_max(edges.where(F.col("window_start") == F.lit(day)).select("u", "v", "w")))
    assert one == {(r["u"], r["v"]) for r in result.where(F.col("window_start") == F.lit(day)).collect()}


def test_repair_is_valid_and_maximal(spark):
    edges = canonical_edges(frame(spark, random_graph(6, n=30, m=60)))
    fresh = canonical_edges(frame(spark, random_graph(7, n=30, m=20, weights=40)))
    fixed = windows.repair(edges, local_max(edges).matching, fresh)
    used = [x for r in fixed.collect() for x in (r["u"], r["v"])]
    assert len(used) == len(set(used))
    taken = set(used)
    assert all({r["u"], r["v"]} & taken for r in edges.unionByName(fresh).collect())


def test_plans_have_the_shape_they_should(spark):
    edges = spark.read.parquet(f"{SMALL}/lineitem.parquet")
    live = graphs.part_supp(spark, SMALL).withColumn("eid", F.monotonically_increasing_id()).withColumn("key", F.col("eid"))
    from matchloom.operators.localmax import candidates

    plan = report.plan_text(candidates(live))
    assert "SortAggregate" not in plan.split("\n\n")[0] and "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_extendedprice:double,l_discount:double>" in plan
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,30.0)]" in report.plan_text(edges.where("l_quantity > 30").select("l_partkey"))
    assert report.exchanges(arcs(live).groupBy("vertex").count()) >= 1
