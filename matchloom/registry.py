"""The registered queries of the matching engine: methods, baselines, measures, graphs, operators."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

from . import oracle as sql
from .catalog import load
from .edges import arcs, ordered_edges
from .functions import measures
from .operators import adjacency, baselines, coarsen, crew, paths, scan
from .operators.localmax import local_max, maximal_matching
from .sources import graphs
from .storage import Scratch
from .streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def register(name: str, text: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return keep


BUILD: dict[str, Query] = {
    "part_supp": graphs.part_supp, "order_part": graphs.order_part, "cust_supp": graphs.cust_supp, "cust_part": graphs.cust_part, "copurchase": graphs.copurchase,
    "nation_region": graphs.nation_region, "customer_nation": graphs.customer_nation, "conversation_turn": graphs.conversation_turn, "page_host": graphs.page_host,
    "event_succ": graphs.event_succ, "rising_path": graphs.rising_path, "random_alpha": graphs.random_alpha, "gram": graphs.gram, "doc_near": graphs.doc_near,
    "rgg_events": graphs.rgg_events, "delaunay2d": graphs.delaunay2d, "doc_jaccard": graphs.doc_jaccard,
    "random_alpha_16": lambda s, d: graphs.random_alpha(s, d, 16), "random_alpha_64": lambda s, d: graphs.random_alpha(s, d, 64),
}
RESULT = ("u", "v", "w", "phase")


def matching_query(build: Query, **options) -> Query:
    return lambda spark, d: local_max(build(spark, d), **options).matching.select(*RESULT)


# graphs, and local max on each of them
for _name, _build in BUILD.items():
    register(f"graph_{_name}", sql.GRAPHS[_name])(lambda spark, d, b=_build: b(spark, d).select("u", "v", "w"))
for _name in ("part_supp", "copurchase", "cust_supp", "cust_part", "order_part", "event_succ", "rgg_events", "gram", "doc_near", "doc_jaccard", "random_alpha", "random_alpha_16", "page_host", "delaunay2d"):
    register(f"lm_{_name}", sql.matched(sql.GRAPHS[_name]))(matching_query(BUILD[_name]))
register("lm_star_nation", sql.matched(sql.GRAPHS["nation_region"]))(matching_query(graphs.nation_region))
register("lm_star_customer", sql.matched(sql.GRAPHS["customer_nation"]))(matching_query(graphs.customer_nation))
register("lm_conversation_turn", sql.matched(sql.GRAPHS["conversation_turn"]))(matching_query(graphs.conversation_turn))
register("lm_rising_path", sql.matched(sql.GRAPHS["rising_path_200"]))(matching_query(lambda s, d: graphs.rising_path(s, d, 200)))
register("lm_rising_path_whole")(matching_query(graphs.rising_path, plan="kernel"))
register("graph_windowed_succ", sql.DAYS)(graphs.windowed_succ)
register("graph_rgg2d")(graphs.rgg2d)
register("lm_rgg2d")(matching_query(graphs.rgg2d))
register("lm_grouped_days", sql.matched_by_day(sql.DAYS + " having sum(w) >= 0"))(lambda s, d: local_max(graphs.windowed_succ(s, d), by=("day",)).matching.select("day", *RESULT))

# plans of local max on one graph
_PS = sql.GRAPHS["part_supp"]
for _plan in ("edges", "join", "sql"):
    register(f"lm_plan_{_plan}", sql.matched(_PS))(matching_query(graphs.part_supp, plan=_plan, finish_rows=0))
# the distributed loop to its end, over many phases, on each kind of graph
for _name in ("copurchase", "rgg_events", "random_alpha_16", "random_alpha_64"):
    register(f"lm_loop_{_name}", sql.matched(sql.GRAPHS[_name]))(matching_query(BUILD[_name], finish_rows=0))
register("lm_plan_sort", sql.matched(_PS))(matching_query(graphs.part_supp, plan="sort", finish_rows=0))
register("lm_plan_primitives", sql.matched(_PS))(matching_query(graphs.part_supp, plan="primitives"))
register("lm_plan_levels", sql.matched(_PS))(matching_query(graphs.part_supp, finish_rows=0, levels=2))
register("lm_plan_arcs", sql.matched(_PS))(matching_query(graphs.part_supp, plan="arcs"))
for _name, _owners in (("lm_plan_blocks", {}), ("lm_plan_blocks_hash", {"owner": "hash"})):
    register(_name, sql.matched(_PS, "select u, v, w from matching"))(lambda s, d, o=_owners: local_max(graphs.part_supp(s, d), plan="blocks", owners=o).matching.select("u", "v", "w"))
register("lm_kernel", sql.matched(_PS))(matching_query(graphs.part_supp, plan="kernel"))


@register("lm_phase_log", sql.matched(sql.GRAPHS["copurchase"], """
select s.phase + 1 as phase, count(*) as live_before, sum((k.r is not null)::int)::bigint as matched, count(*) - (select count(*) from steps n where n.phase = s.phase + 1 and not n.hit) as removed,
       (select count(*) from steps n where n.phase = s.phase + 1 and not n.hit) as live_after
from steps s left join (select phase, r from steps where hit) k on k.phase = s.phase + 1 and k.r = s.r
where not s.hit group by s.phase"""))  # fmt: skip
def lm_phase_log(spark: SparkSession, d: str) -> DataFrame:
    return local_max(graphs.copurchase(spark, d)).log_frame().select("phase", "live_before", "matched", "removed", "live_after")


register("mm_unit_portable", sql.unit_renewed(_PS))(lambda s, d: maximal_matching(graphs.part_supp(s, d)).matching.select("u", "v", "phase"))
register("mm_unit_fixed", sql.matched(f"select u, v, 1 as w from ({_PS})"))(matching_query(graphs.part_supp, weight=None))
register("mm_unit_static")(lambda s, d: maximal_matching(graphs.copurchase(s, d), renew=False).matching.select(*RESULT))

# baselines
_GREEDY = sql.matched(_PS, "select u, v, w from matching")
_CN = sql.GRAPHS["customer_nation"]
_SMALL = sql.simple(f"select c_custkey as u, c_nationkey + {graphs.RIGHT} as v, cast(round(c_acctbal * 100) as bigint) as w from customer where c_custkey < 300 union all select c_custkey, c_custkey * 7 % 300, c_custkey % 97 + 1 from customer where c_custkey < 300")


def small_graph(spark: SparkSession, d: str) -> DataFrame:
    """Three hundred customers with their nations and with one another."""
    some = load(spark, d, "customer").where("c_custkey < 300")
    left = some.select(F.col("c_custkey").alias("u"), (F.col("c_nationkey").cast("long") + graphs.RIGHT).alias("v"), graphs.cents("c_acctbal").alias("w"))
    right = some.select(F.col("c_custkey").alias("u"), (F.col("c_custkey") * 7 % 300).alias("v"), (F.col("c_custkey") % 97 + 1).alias("w"))
    return graphs.canonical_edges(left.unionByName(right))


def edges_of(f) -> Query:
    return lambda spark, d: f(spark, d).matching.select("u", "v", "w")


register("greedy_scan", _GREEDY)(edges_of(lambda s, d: baselines.greedy(graphs.part_supp(s, d), engine="auto")))
register("greedy_rounds", _GREEDY)(edges_of(lambda s, d: baselines.greedy(graphs.part_supp(s, d), engine="rounds", finish_rows=0)))
register("pointer_matching", _GREEDY)(edges_of(lambda s, d: baselines.pointer_matching(graphs.part_supp(s, d))))
register("pointer_rounds", _GREEDY)(edges_of(lambda s, d: baselines.pointer_rounds(graphs.part_supp(s, d))))
_RANDOM = "('0x' || substr(md5('42|0|' || x), 1, 12))::bigint"
register("hem_id", sql.heavy_edge(_SMALL))(edges_of(lambda s, d: baselines.heavy_edge(small_graph(s, d), "id", engine="scan")))
register("hem_random_portable", sql.heavy_edge(_SMALL, _RANDOM))(edges_of(lambda s, d: baselines.heavy_edge(small_graph(s, d), "random", engine="scan")))
register("hem_rounds", sql.heavy_edge(_SMALL, _RANDOM))(edges_of(lambda s, d: baselines.heavy_edge(small_graph(s, d), "random", engine="rounds")))
register("red_blue_portable", sql.red_blue(_SMALL))(lambda s, d: baselines.red_blue(small_graph(s, d)).matching.select(*RESULT))
register("hem_id_whole", sql.heavy_edge(_PS))(edges_of(lambda s, d: baselines.heavy_edge(graphs.part_supp(s, d), "id", engine="auto")))
register("hem_random_whole", sql.heavy_edge(_PS, _RANDOM))(edges_of(lambda s, d: baselines.heavy_edge(graphs.part_supp(s, d), "random", engine="auto")))
register("hem_rounds_whole", sql.heavy_edge(_CN, _RANDOM))(edges_of(lambda s, d: baselines.heavy_edge(graphs.customer_nation(s, d), "random", engine="rounds")))
register("red_blue_whole", sql.red_blue(_PS))(lambda s, d: baselines.red_blue(graphs.part_supp(s, d)).matching.select(*RESULT))
register("red_blue_blocks", sql.red_blue(_PS))(lambda s, d: baselines.red_blue_blocks(graphs.part_supp(s, d)).matching.select(*RESULT))
register("random_proposal", sql.random_proposal(_PS))(lambda s, d: baselines.random_proposal(graphs.part_supp(s, d)).matching.select(*RESULT))
register("gpa")(edges_of(lambda s, d: paths.global_paths(graphs.copurchase(s, d))))
register("gpa_rounds")(edges_of(lambda s, d: paths.global_paths(graphs.part_supp(s, d), engine="rounds")))
register("gpa_repeated")(edges_of(lambda s, d: paths.global_paths(graphs.part_supp(s, d), rounds=3, maximal=True)))


@register("path_optimum_long", "select sum(range + 1)::bigint as weight, count(*) as size from range((select count(*) - 1 from orders)) where (range - (select count(*) - 2 from orders)) % 2 = 0")
def path_optimum_long(spark: SparkSession, d: str) -> DataFrame:
    """The heaviest matching of the path of all orders, by list order and segments: every second
    link from the heaviest on."""
    from .operators import pathscan

    scratch = Scratch(spark, "long")
    links = scratch.save(graphs.rising_path(spark, d).select(F.col("u").alias("eid"), "u", "v", "w", F.lit(0).cast("long").alias("comp")), "links")
    taken = pathscan.optimum_links(scratch.save(pathscan.rank_links(links, scratch), "ranked"), scratch)
    return measures.matching_weight(taken.join(links.select("eid", "w"), "eid"))


@register("gpa_growth")
def gpa_growth(spark: SparkSession, d: str) -> DataFrame:
    scratch = Scratch(spark, "growth")
    ordered = ordered_edges(graphs.part_supp(spark, d), scratch)
    grown = paths.grown_links_scan(ordered) if ordered.count() <= paths.SCAN_ROWS else paths.grow_paths(ordered, scratch)
    return grown.select("u", "v", "comp")


def _line_graph_sql(edges: str) -> str:
    return f"with ranked as ({sql.ordered(edges)}), ends as (select u as x, u, v from ranked union all select v, u, v from ranked) select distinct least((a.u, a.v), (b.u, b.v))[1] as u1, least((a.u, a.v), (b.u, b.v))[2] as v1, greatest((a.u, a.v), (b.u, b.v))[1] as u2, greatest((a.u, a.v), (b.u, b.v))[2] as v2 from ends a join ends b on a.x = b.x and (a.u, a.v) < (b.u, b.v)"


def named_line_graph(edges: DataFrame) -> DataFrame:
    edges = Scratch(edges.sparkSession, "linegraph").save(edges.select("u", "v"), "edges")
    pairs = baselines.touching_pairs(edges, "u", "v")
    first = (F.col("a.u") < F.col("b.u")) | (F.col("a.u") == F.col("b.u")) & (F.col("a.v") < F.col("b.v"))
    named = [(c, i, F.when(first, F.col(f"{x}.{c}")).otherwise(F.col(f"{y}.{c}"))) for i, x, y in ((1, "a", "b"), (2, "b", "a")) for c in "uv"]
    return pairs.select(*[value.alias(f"{c}{i}") for c, i, value in named])


register("line_graph", _line_graph_sql(_SMALL))(lambda s, d: named_line_graph(small_graph(s, d)))
register("line_graph_whole", _line_graph_sql(_CN))(lambda s, d: named_line_graph(graphs.customer_nation(s, d)))
_PRIORITY = "('0x' || substr(md5('42|0|' || u || '|' || v), 1, 12))::bigint desc, u desc, v desc"
register("line_graph_matching", sql.matched(_CN, order=_PRIORITY))(lambda s, d: baselines.line_graph_matching(graphs.customer_nation(s, d)).matching.select(*RESULT))
register("exact_weight", "select count(distinct n_regionkey) as weight, count(distinct n_regionkey) as size from nation")(lambda s, d: measures.matching_weight(baselines.exact_matching(graphs.nation_region(s, d)).matching))
register("exact_bipartite")(edges_of(lambda s, d: baselines.exact_bipartite(graphs.part_supp(s, d))))
register("exact_small")(edges_of(lambda s, d: baselines.exact_matching(graphs.nation_region(s, d))))

# measures
_RANKED = f"with ranked as ({sql.ordered(_PS)}), {sql.DEGREES} "
register("upper_bound", f"with e as ({_PS}) select sum(w)::bigint as twice_bound from (select x, max(w) as w from (select u as x, w from e union all select v, w from e) group by x)")(lambda s, d: measures.weight_upper_bound(graphs.part_supp(s, d)))
register("match_probability", _RANKED + "select u, v, a.d + b.d - 1 as around from ranked join degrees a on a.x = u join degrees b on b.x = v")(lambda s, d: measures.match_probability(graphs.part_supp(s, d)))
register("mark_count", sql.matched(_PS, "select sum(a.d + b.d)::bigint as marks from matching join degrees a on a.x = u join degrees b on b.x = v where phase = 1", f", {sql.DEGREES}"))(lambda s, d: measures.mark_count(graphs.part_supp(s, d), local_max(graphs.part_supp(s, d)).matching.where("phase = 1")))
register("balance_check", _RANKED + "select (select count(*) from ranked) as m, max(d) as max_degree, max(d) * 8 <= (select count(*) from ranked) as balanced from degrees")(lambda s, d: measures.balance_check(graphs.part_supp(s, d), 8))
for _name in ("rgg_events", "random_alpha_16"):
    register(f"cut_{_name}", f"with ranked as ({sql.ordered(sql.GRAPHS[_name])}), {sql.OWNERS} select sum((a.o <> b.o)::int)::bigint as cut, count(*) as edges from ranked join own a on a.x = u join own b on b.x = v")(lambda s, d, b=BUILD[_name]: measures.cut_fraction(b(s, d), 8))
register("quality_vs_optimum")(lambda s, d: (lambda e: measures.quality_vs(local_max(e).matching, baselines.exact_bipartite(e).matching))(graphs.part_supp(s, d)))
register("quality_vs_paths")(lambda s, d: (lambda e: measures.quality_vs(local_max(e).matching, paths.global_paths(e).matching))(graphs.part_supp(s, d)))
register("cut_fraction", f"with ranked as ({sql.ordered(_PS)}), {sql.OWNERS} select sum((a.o <> b.o)::int)::bigint as cut, count(*) as edges from ranked join own a on a.x = u join own b on b.x = v")(lambda s, d: measures.cut_fraction(graphs.part_supp(s, d), 8))
register("weight_diversity", f"select count(distinct w) as weights, count(*) as edges from ({sql.GRAPHS['copurchase']})")(lambda s, d: measures.weight_diversity(graphs.copurchase(s, d)))
register("matching_weight", sql.matched(_PS, "select sum(w)::bigint as weight, count(*) as size from matching"))(lambda s, d: measures.matching_weight(local_max(graphs.part_supp(s, d)).matching))

_PHASES = f", {sql.OWNERS}, {sql.LOG} "
register("bound_ratio", sql.matched(_PS, "select 2 * sum(w)::double / (select sum(w) from (select max(w) as w from (select u as x, w from ranked union all select v, w from ranked) group by x)) as ratio from matching"))(
    lambda s, d: measures.bound_ratio(graphs.part_supp(s, d), local_max(graphs.part_supp(s, d)).matching)
)
register("communication", sql.matched(_PS, "select s.phase + 1 as phase, count(*) as live, sum((a.o <> b.o)::int)::bigint as cut, 4 * sum((a.o <> b.o)::int)::bigint as messages from steps s join own a on a.x = s.u join own b on b.x = s.v where not s.hit group by s.phase", _PHASES))(
    lambda s, d: measures.communication(local_max(graphs.part_supp(s, d)).removal_phases(), 8)
)
register("mapreduce_cost", sql.matched(sql.GRAPHS["copurchase"], f"select phase, greatest({sql.levels_above('2 * live', 1, 1000)}, 1) as rounds, 2 * live * greatest({sql.levels_above('2 * live', 1, 1000)}, 1) as traffic from log", _PHASES))(
    lambda s, d: measures.mapreduce_cost(local_max(graphs.copurchase(s, d)).log_frame(), 1000)
)
register("io_cost", sql.matched(sql.GRAPHS["copurchase"], f"select phase, 1 + {sql.levels_above('2 * live', 10000, 100)} as passes, (2 * (1 + {sql.levels_above('2 * live', 10000, 100)}) * ((2 * live + 99) // 100))::bigint as blocks from log", _PHASES))(
    lambda s, d: measures.io_cost(local_max(graphs.copurchase(s, d)).log_frame(), 10_000, 100)
)
register("phase_summary", sql.matched(sql.GRAPHS["copurchase"], "select count(*) as phases, sum(live)::double / max(live) as total_work, sum((4 * (live - after) >= live)::int)::bigint as good_phases from (select *, coalesce(lead(live) over (order by phase), 0) as after from log)", _PHASES))(
    lambda s, d: measures.phase_summary(local_max(graphs.copurchase(s, d)).log_frame()).select(F.col("phases").cast("long").alias("phases"), "total_work", "good_phases")
)


@register("is_maximal", "select 0::bigint as double_use, 0::bigint as loose")
def is_maximal(spark: SparkSession, d: str) -> DataFrame:
    edges = graphs.copurchase(spark, d)
    m = local_max(edges).matching
    twice = measures.double_use(m).agg(F.count("*").alias("double_use"), F.lit(1).alias("k"))
    return twice.join(measures.loose_edges(edges, m).agg(F.count("*").alias("loose"), F.lit(1).alias("k")), "k").drop("k")


METHODS: dict[str, Callable] = {
    "local_max": lambda e: local_max(e), "greedy": lambda e: baselines.greedy(e, engine="auto"), "heavy_edge": lambda e: baselines.heavy_edge(e, "random", engine="auto"),
    "red_blue": lambda e: baselines.red_blue(e), "global_paths": lambda e: paths.global_paths(e),
}
SUITE = ("part_supp", "copurchase", "order_part", "event_succ")


@register("quality_table")
def quality_table(spark: SparkSession, d: str) -> DataFrame:
    """Weight of each method on each graph, over that of global paths."""
    rows = []
    for name in SUITE:
        edges = Scratch(spark, "suite").save(BUILD[name](spark, d), name)
        weights = {m: int(f(edges).weight()) for m, f in METHODS.items()}
        rows += [(name, m, w, weights["global_paths"], w / weights["global_paths"] if weights["global_paths"] else 1.0) for m, w in weights.items()]
    return spark.createDataFrame(rows, "instance string, method string, weight long, reference long, ratio double")


register("suite_summary")(lambda s, d: measures.suite_summary(quality_table(s, d)))


@register("pareto")
def pareto(spark: SparkSession, d: str) -> DataFrame:
    """Methods that no other beats in both weight and time on one graph."""
    scratch = Scratch(spark, "pareto")
    edges = scratch.save(graphs.copurchase(spark, d), "edges")
    ordered_edges(edges, scratch)  # all methods start from it, so no one's time has it
    rows = []
    for name, f in METHODS.items():
        began = time.time()
        rows.append((name, float(f(edges).weight()), time.time() - began))
    return measures.pareto(spark.createDataFrame(rows, "method string, ratio double, seconds double")).select("method", "ratio")


SWEEP_FINISH = 100_000


def timed_parts(spark: SparkSession, d: str, most: int = 8) -> list[tuple[int, float]]:
    """Seconds of local max to its end, with the order of the edges, over 1, 2, 4 .. partitions, on the
    event graph with random weights; a partition is a processor here, so the edges are dealt evenly.
    One task finishes the last ``SWEEP_FINISH`` edges."""
    path = Scratch(spark, "sweep").save(graphs.rgg_events(spark, d, True).repartition(most), "edges")._scratch_path
    rows, p = [], 1
    while p <= most:
        part = spark.newSession()
        part.conf.set("spark.sql.shuffle.partitions", str(p))
        part.conf.set("spark.sql.adaptive.enabled", "false")
        edges = part.read.parquet(path).coalesce(p)
        began = time.time()
        local_max(edges, finish_rows=SWEEP_FINISH).matching.write.format("noop").mode("overwrite").save()
        rows.append((p, time.time() - began))
        p *= 2
    return rows


register("doubling_ratio")(lambda s, d: measures.doubling_ratio(s.createDataFrame(timed_parts(s, d), "p int, seconds double")))


@register("contract_once", sql.matched(sql.GRAPHS["copurchase"], """
select least(coalesce(a.u, e.u), coalesce(b.u, e.v)) as u, greatest(coalesce(a.u, e.u), coalesce(b.u, e.v)) as v, sum(e.w)::bigint as w
from ranked e left join matching a on a.v = e.u left join matching b on b.v = e.v
where coalesce(a.u, e.u) <> coalesce(b.u, e.v) group by all"""))  # fmt: skip
def contract_once(spark: SparkSession, d: str) -> DataFrame:
    edges = graphs.copurchase(spark, d)
    return coarsen.contract(edges, local_max(edges).matching)[1]


@register("coarsen_levels")
def coarsen_levels(spark: SparkSession, d: str) -> DataFrame:
    levels = coarsen.coarsen(graphs.copurchase(spark, d), rating="expansion2", max_levels=None)
    rows = [(x["level"], x["edges"].count(), x["coarse"].count(), len(x["log"])) for x in levels]
    return spark.createDataFrame(rows, "level int, edges long, coarse_edges long, phases int")


# array operators, on the cells of one graph; eid is 0..m-1 by falling order here
_CELLS = f"with ranked as ({sql.ordered(_PS)}), {sql.DEGREES}, cells as (select x as vertex, y as other, r, row_number() over (order by x, r desc) - 1 as pos from (select u as x, v as y, r from ranked union all select v, u, r from ranked)) "


def _cells(spark: SparkSession, d: str) -> tuple[Scratch, DataFrame, DataFrame, DataFrame]:
    scratch = Scratch(spark, "cells")
    ordered = ordered_edges(graphs.part_supp(spark, d), scratch)
    vertices, cells = adjacency.build_adjacency(ordered, scratch)
    return scratch, ordered, vertices, cells


register("adjacency", _CELLS + "select x as vertex, d as degree, (sum(d) over (order by x) - d)::bigint as offset from degrees")(lambda s, d: _cells(s, d)[2].select("vertex", "degree", F.col("offset").cast("long").alias("offset")))
register("twin_positions", _CELLS + sql.TWINS)(lambda s, d: adjacency.twin_positions(_cells(s, d)[3]).select("pos", "vertex", "other", "twin_pos"))


@register("vertex_reduce_max", f"with e as ({_PS}) select x as vertex, max(w) as reduced from (select u as x, w from e union all select v, w from e) group by x")
def vertex_reduce_max(spark: SparkSession, d: str) -> DataFrame:
    return adjacency.vertex_reduce(arcs(graphs.part_supp(spark, d), "w"), "w", "max", spread=False)


register("vertex_reduce_callable", f"with e as ({_PS}) select x as vertex, min(w) as reduced from (select u as x, w from e union all select v, w from e) group by x")(
    lambda s, d: adjacency.vertex_reduce(arcs(graphs.part_supp(s, d), "w"), "w", min, spread=False)
)
register("segmented_sum", f"select u, v, sum(w) over (partition by u order by v rows unbounded preceding)::bigint as scan from ({_PS})")(lambda s, d: scan.segmented_scan(graphs.part_supp(s, d), ["u"], ["v"], "w").select("u", "v", "scan"))
register("prefix_sum", f"select u, v, (sum(w) over (order by u, v rows unbounded preceding) - w)::bigint as before from ({_PS})")(lambda s, d: scan.prefix_sum(graphs.part_supp(s, d), ["u", "v"], F.col("w"), Scratch(s, "prefix")).select("u", "v", "before"))
register("scatter", f"select u as pos, max(w) as w from ({_PS}) group by u")(lambda s, d: scan.scatter(graphs.part_supp(s, d), "u", "w"))
register("gather", f"with e as ({_PS}), top as (select u, max(w) as top from e group by u) select e.u, e.v, top.top from e join top on e.u = top.u")(
    lambda s, d: scan.gather(graphs.part_supp(s, d), "u", scan.scatter(graphs.part_supp(s, d), "u", "w").withColumnRenamed("w", "top")).select("u", "v", "top")
)


@register("compact", _CELLS + "select pos - sum((w % 2 = 0)::int) over (order by pos) as pos, vertex, other from (select cells.*, w from cells join ranked using (r)) qualify w % 2 = 1")
def compact(spark: SparkSession, d: str) -> DataFrame:
    scratch, ordered, _, cells = _cells(spark, d)
    numbered = scan.prefix_sum(ordered, ["eid"], F.lit(1), scratch, "pos")
    flagged = scratch.save(numbered.withColumn("deleted", F.col("w") % 2 == 0), "flagged")
    pointed = cells.join(flagged.select("eid", F.col("pos").alias("edge_pos")), "eid")
    return scan.compact(flagged, pointed, scratch)[1].select("pos", "vertex", "other")


@register("crew_phase_one", sql.matched(_PS, "select k.u, k.v, m.r is not null as matched, not exists (select 1 from steps s where s.phase = 1 and s.r = k.r and not s.hit) as deleted from ranked k left join matching m on m.r = k.r and m.phase = 1"))
def crew_phase_one(spark: SparkSession, d: str) -> DataFrame:
    ordered = ordered_edges(graphs.part_supp(spark, d), Scratch(spark, "crew"))
    return crew.phase_flags(arcs(ordered, "eid")).where("vertex < other").select(F.col("vertex").alias("u"), F.col("other").alias("v"), "matched", "deleted")


# surrounding operators on matchings
def _pair(spark: SparkSession, d: str) -> DataFrame:
    return local_max(graphs.part_supp(spark, d)).matching


register("join_mates", sql.matched(_PS, "select x as vertex, case when m.u = x then m.v else m.u end as mate from (select distinct x from (select u as x from ranked union all select v from ranked)) left join matching m on m.u = x or m.v = x"))(
    lambda s, d: local_max(graphs.part_supp(s, d)).mates()
)
register("join_free_vertices", sql.matched(_PS, "select x as vertex from (select u as x from ranked union select v from ranked) where x not in (select u from matching) and x not in (select v from matching)"))(
    lambda s, d: local_max(graphs.part_supp(s, d)).free_vertices()
)
register("join_asof_events", f"""
    select a.event_id, a.user_id, b.user_id as other from events a asof left join (select ts, max(user_id) as user_id from events group by ts) b on a.ts > b.ts
    where a.ts - b.ts <= interval 10 minute""")(lambda s, d: asof_events(s, d))  # fmt: skip


def asof_events(spark: SparkSession, d: str, minutes: int = 10) -> DataFrame:
    """Each event with the last earlier moment's user (the greatest id at that moment), no older
    than the tolerance. Moments are bucketed by the tolerance, so the search is an equi-join."""
    events = load(spark, d, "events").select("event_id", "user_id", graphs.micros("ts").alias("t"))
    width = minutes * 60_000_000
    moments = events.groupBy("t").agg(F.max("user_id").alias("other")).select(F.col("t").alias("past"), "other", F.explode(F.array(F.floor(F.col("t") / width), F.floor(F.col("t") / width) + 1)).alias("b"))
    met = events.withColumn("b", F.floor(F.col("t") / width)).join(moments, "b").where((F.col("past") < F.col("t")) & (F.col("t") - F.col("past") <= width))
    return met.groupBy("event_id", "user_id").agg(F.max_by("other", "past").alias("other"))


register("agg_rollup_nations", sql.matched(sql.GRAPHS["customer_nation"], f"select r_name, n_name, count(*) as pairs, sum(w)::bigint as weight from matching join nation on n_nationkey + {graphs.RIGHT} = v join region on r_regionkey = n_regionkey group by rollup (r_name, n_name)"))(
    lambda s, d: local_max(graphs.customer_nation(s, d)).matching.join(load(s, d, "nation").withColumn("v", F.col("n_nationkey").cast("long") + graphs.RIGHT), "v")
    .join(load(s, d, "region"), F.col("r_regionkey") == F.col("n_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("pairs"), F.sum("w").alias("weight"))
)
register("agg_cube_events", "select event_type, user_id % 10 as bucket, count(*) as n from events group by cube (event_type, user_id % 10)")(
    lambda s, d: load(s, d, "events").withColumn("bucket", F.col("user_id") % 10).cube("event_type", "bucket").agg(F.count("*").alias("n"))
)
register("agg_percentiles", f"select quantile_cont(w, 0.25) as p25, quantile_cont(w, 0.5) as p50, quantile_cont(w, 0.9) as p90 from ({_PS})")(
    lambda s, d: measures.percentiles(graphs.part_supp(s, d), "w", {"p25": 0.25, "p50": 0.5, "p90": 0.9})
)
register("agg_pivot_phases", sql.matched(_PS, "select w % 5 as k, count(*) filter (phase = 1) as p1, count(*) filter (phase = 2) as p2 from matching group by w % 5"))(
    lambda s, d: _pair(s, d).withColumn("k", F.col("w") % 5).groupBy("k").pivot("phase", [1, 2]).agg(F.count(F.lit(1))).select("k", F.coalesce("1", F.lit(0)).alias("p1"), F.coalesce("2", F.lit(0)).alias("p2"))
)
@register("win_ranked_edges", f"select u, v, w, rank() over (partition by u order by w desc, v) as place, ntile(4) over (partition by u order by w desc, v) as quarter from ({_PS}) qualify rank() over (partition by u order by w desc, v) <= 3")
def win_ranked_edges(spark: SparkSession, d: str) -> DataFrame:
    """The three heaviest edges of each left vertex."""
    falling = W.partitionBy("u").orderBy(F.col("w").desc(), "v")
    return graphs.part_supp(spark, d).select("u", "v", "w", F.rank().over(falling).alias("place"), F.ntile(4).over(falling).alias("quarter")).where("place <= 3")


register("win_analytic", f"select u, v, dense_rank() over g as place, percent_rank() over g as share, nth_value(v, 2) over (partition by u order by w desc, v rows between unbounded preceding and unbounded following) as second from ({_PS}) window g as (partition by u order by w desc, v)")(
    lambda s, d: (lambda g, whole: graphs.part_supp(s, d).select("u", "v", F.dense_rank().over(g).alias("place"), F.percent_rank().over(g).alias("share"), F.nth_value("v", 2).over(whole).alias("second")))(
        W.partitionBy("u").orderBy(F.col("w").desc(), "v"), W.partitionBy("u").orderBy(F.col("w").desc(), "v").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    )
)
register("agg_grouping_sets", sql.matched(_PS, "select phase, w % 5 as k, count(*) as n, grouping(phase, w % 5) as gid from matching group by grouping sets ((phase, w % 5), (phase), ())"))(
    lambda s, d: _pair(s, d).withColumn("k", F.col("w") % 5).groupingSets([["phase", "k"], ["phase"], []], "phase", "k").agg(F.count("*").alias("n"), F.grouping_id("phase", "k").alias("gid"))
)
register("agg_approx_distinct", f"select count(distinct u) as vertices, true as near from ({_PS})")(
    lambda s, d: graphs.part_supp(s, d).agg(F.countDistinct("u").alias("vertices"), F.approx_count_distinct("u", 0.02).alias("about")).select("vertices", (F.abs(F.col("about") - F.col("vertices")) <= 0.1 * F.col("vertices")).alias("near"))
)
for _hint in ("shuffle_hash", "merge"):
    register(f"join_{_hint}", sql.matched(_PS, "select u, v from ranked where u not in (select u from matching)"))(
        lambda s, d, h=_hint: (lambda r: r.edges.join(r.matching.select("u").hint(h), "u", "left_anti").select("u", "v"))(local_max(graphs.part_supp(s, d)))
    )
register("fn_props_map", "select event_id, list_sort(json_keys(props)) as names, props::json->>'k' as k from events")(
    lambda s, d: load(s, d, "events").withColumn("m", F.from_json("props", "map<string,string>")).select("event_id", F.array_sort(F.map_keys("m")).alias("names"), F.element_at("m", F.lit("k")).alias("k"))
)
register("graph_knn_events", sql.KNN)(graphs.knn_events)
register("set_intersect", sql.matched(_PS, "select u, v from matching where w % 2 = 0 intersect select u, v from matching where phase = 1"))(lambda s, d: (lambda m: m.where("w % 2 = 0").select("u", "v").intersect(m.where("phase = 1").select("u", "v")))(_pair(s, d)))
register("set_except", sql.matched(_PS, "select u, v from ranked except select u, v from matching"))(lambda s, d: (lambda r: r.edges.select("u", "v").exceptAll(r.matching.select("u", "v")))(local_max(graphs.part_supp(s, d))))
register("topk_heaviest", sql.matched(_PS, "select u, v, w from matching order by w desc, u, v limit 10"))(lambda s, d: _pair(s, d).orderBy(F.col("w").desc(), "u", "v").limit(10).select("u", "v", "w"))
register("fn_json_weight", "select event_type, sum((props::json->>'k')::bigint)::bigint as total, count(*) as n from events group by event_type")(
    lambda s, d: load(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total"), F.count("*").alias("n"))
)
register("fn_sampled_edges", f"select u, v from ({_PS}) where {sql.h48(chr(39) + 's|' + chr(39) + ' || u || ' + chr(39) + '|' + chr(39) + ' || v')} % 100 < 10")(
    lambda s, d: graphs.part_supp(s, d).where(graphs.portable_hash(F.lit("s"), F.col("u"), F.col("v")) % 100 < 10).select("u", "v")
)

# streams, against the same tables at rest
_TYPE = f"{sql.h48('event_type')} + {graphs.RIGHT}"
_SEEN, _STAMP = sql.SEEN, sql.STAMP


def _window_sql(starts: str, length: str) -> str:
    """Closed windows: those that end before the watermark."""
    grouped = f"select win, user_id, event_type, count(*) as n, sum(cast(round(value * 100) as bigint))::bigint as cents from (select *, unnest({starts}) as win from events) group by all"
    return f"select strftime(win, '{_STAMP}') as window_start, user_id, event_type, n, cents from ({grouped}) where win + interval {length} <= {_SEEN}"


def stamped(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.date_format(c, "yyyy-MM-dd HH:mm:ss") for c in columns})


register("stream_tumbling", _window_sql("[date_trunc('day', ts)]", "1 day"))(lambda s, d: stamped(windows.run_stream(windows.window_graph(windows.read_events(s, d), "1 day"), "tumbling"), "window_start"))
register("stream_sliding", _window_sql("[date_trunc('day', ts), date_trunc('day', ts) - interval 1 day]", "2 day"))(
    lambda s, d: stamped(windows.run_stream(windows.window_graph(windows.read_events(s, d), "2 days", "1 day"), "sliding"), "window_start")
)
_MATCHED_DAYS = f"from ({sql.matched_by_day(sql.TYPED_DAYS)})"
register("stream_matching", f"select day as window_start, u, v, w, phase {_MATCHED_DAYS}")(lambda s, d: stamped(windows.stream_window_matching(s, d), "window_start"))
register("stream_session", f"""
select user_id, strftime(min(ts), '{_STAMP}') as session_start, strftime(max(ts) + interval 30 minute, '{_STAMP}') as session_end, count(*) as n
from (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as s
      from (select *, (coalesce(ts - lag(ts) over (partition by user_id order by ts, event_id), interval 1 day) > interval 30 minute)::int as fresh from events))
group by user_id, s having max(ts) + interval 30 minute <= {_SEEN}""")(lambda s, d: stamped(windows.stream_sessions(s, d), "session_start", "session_end"))  # fmt: skip
register("stream_dedup", "select event_id, user_id from events")(windows.stream_distinct)
register("stream_static_join", "select event_id, user_id, count(*) over (partition by user_id) as degree from events")(windows.stream_static_join)
register("stream_totals", "select event_type, count(*) as n from events group by event_type")(windows.stream_totals)
register("stream_updates", "select event_type, count(*) as n from events group by event_type")(windows.stream_updates)
register("stream_mate_store", f"select day as window_start, u, v, w {_MATCHED_DAYS}")(windows.stream_mate_store)
register("stream_interval_join", """
    select a.user_id, a.event_id as first_id, b.event_id as then_id from events a join events b on a.user_id = b.user_id
    where a.event_type = 'view' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 10 minute""")(windows.stream_interval_join)  # fmt: skip
register("stream_late", "select count(*) filter (epoch_us(ts) >= m) as kept, count(*) filter (epoch_us(ts) < m) as late from events, (select min(epoch_us(ts)) + (max(epoch_us(ts)) - min(epoch_us(ts))) // 3 as m from events)")(windows.stream_late)
