"""Graphs from the given tables. Every builder takes (spark, sf_dir) and returns canonical
edges ``(u, v, w)`` with BIGINT weights; right-hand sides of bipartite graphs are shifted by
RIGHT so that vertex ids stay apart.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window as W, functions as F

from ..catalog import load
from ..edges import canonical_edges
from ..storage import Scratch

RIGHT = 1_000_000_000
STEPS = 1_000_000
#: Factor of the radius of random geometric graphs.
RADIUS_FACTOR = 0.55


def cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("long")


def micros(column: str) -> Column:
    return F.unix_micros(F.col(column).cast("timestamp"))


def portable_hash(*parts: Column) -> Column:
    """48 bits of md5, as a long."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 12), 16, 10).cast("long")


def bipartite(df: DataFrame, left: Column, right: Column, weight: Column, combine: str = "sum", nonpositive: str = "drop") -> DataFrame:
    return canonical_edges(df.select(left.cast("long").alias("u"), (right.cast("long") + RIGHT).alias("v"), weight.alias("w")), combine, nonpositive)


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts and their suppliers, weight: revenue in cents times percent."""
    return bipartite(load(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"), cents("l_extendedprice") * (100 - cents("l_discount")))


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(load(spark, sf_dir, "lineitem"), F.col("l_orderkey"), F.col("l_partkey"), F.col("l_quantity").cast("long"))


def _ordered_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return load(spark, sf_dir, "lineitem").join(orders, "l_orderkey")


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(_ordered_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_suppkey"), cents("l_extendedprice"))


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(_ordered_lines(spark, sf_dir), F.col("o_custkey"), F.col("l_partkey"), F.col("l_quantity").cast("long"))


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of the same order, weight: pairs of lines they share. An order has few lines, so
    the pairs of an order are few; each order is a key of its own."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("u"))
    pairs = lines.join(lines.withColumnRenamed("u", "v"), "l_orderkey").where("u < v")
    return pairs.groupBy("u", "v").agg(F.count("*").alias("w"))


def nation_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(load(spark, sf_dir, "nation"), F.col("n_nationkey"), F.col("n_regionkey"), F.lit(1).cast("long"))


def customer_nation(spark: SparkSession, sf_dir: str, nonpositive: str = "drop") -> DataFrame:
    return bipartite(load(spark, sf_dir, "customer"), F.col("c_custkey"), F.col("c_nationkey"), cents("c_acctbal"), nonpositive=nonpositive)


def conversation_turn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(load(spark, sf_dir, "conversations"), F.col("conv_id"), F.col("turn"), F.length("text").cast("long"))


def page_host(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the hosts of their addresses, weight: length of the page."""
    host = F.regexp_extract("url", "^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1)
    return bipartite(load(spark, sf_dir, "pages").where(F.col("url").isNotNull() & F.col("html").isNotNull()), F.col("page_id"), portable_hash(host), F.length("html").cast("long"))


def _successions(events: DataFrame, *day: str) -> DataFrame:
    """Users that follow each other in time. The order of a whole stream is one sequence, so
    the window is split by day where ``day`` is given, and the seams of days joined otherwise."""
    following = W.partitionBy("day").orderBy("ts", "event_id")
    rows = events.withColumn("day", F.date_trunc("day", F.col("ts").cast("timestamp")))
    marked = rows.withColumn("next_user", F.lead("user_id").over(following))
    inside = marked.where("next_user is not null").select("day", F.col("user_id").alias("u"), F.col("next_user").alias("v"), cents("value").alias("w"))
    if day:
        return inside
    ends = rows.groupBy("day").agg(
        F.min_by("user_id", F.struct("ts", "event_id")).alias("first_user"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last_user"), F.max_by(cents("value"), F.struct("ts", "event_id")).alias("w"),
    )
    seam = ends.withColumn("v", F.lead("first_user").over(W.orderBy("day"))).where("v is not null")  # one row a day
    return inside.unionByName(seam.select("day", F.col("last_user").alias("u"), "v", "w"))


def event_succ(spark: SparkSession, sf_dir: str) -> DataFrame:
    return canonical_edges(_successions(load(spark, sf_dir, "events")).select("u", "v", "w"), nonpositive="keep")


def windowed_succ(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(day, u, v, w)``: a graph of successions for each day."""
    rows = _successions(load(spark, sf_dir, "events"), "day").where("u <> v")
    return rows.groupBy(F.date_format("day", "yyyy-MM-dd").alias("day"), F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.sum("w").alias("w"))


def rising_path(spark: SparkSession, sf_dir: str, limit: int | None = None) -> DataFrame:
    """Consecutive orders, weights rising along the path: the most phases a method can need."""
    n = load(spark, sf_dir, "orders").count()
    return spark.range((n if limit is None else min(n, limit)) - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"), (F.col("id") + 1).alias("w"))


def random_graph(spark: SparkSession, n: int, alpha: int, vertices: DataFrame | None = None) -> DataFrame:
    """n vertices, alpha hashed draws each, hashed weights. ``vertices(id)``: those that draw, all
    if none are given."""
    drawing = spark.range(n) if vertices is None else vertices
    draws = drawing.select(F.col("id"), F.explode(F.sequence(F.lit(1), F.lit(alpha))).alias("k"))
    ends = draws.select(F.col("id").alias("a"), (portable_hash(F.lit("end"), F.col("id"), F.col("k")) % n).alias("b")).where("a <> b")
    pairs = ends.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
    return pairs.withColumn("w", portable_hash(F.lit("w"), F.col("u"), F.col("v")) % STEPS + 1)


def random_alpha(spark: SparkSession, sf_dir: str, alpha: int = 4) -> DataFrame:
    """A random graph of parts, as many as the largest power of two: each draws partners by its key."""
    parts = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
    n = 1 << int(math.log2(parts.count()))
    tasks = max(spark.sparkContext.defaultParallelism, n * alpha >> 19)  # keys are few bytes, their draws are many
    return random_graph(spark, n, alpha, parts.where(F.col("id") < n).repartition(tasks))


def points2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first two components of the embeddings as integers."""
    at = lambda k: F.floor(F.col("embedding")[k].cast("double") * STEPS).cast("long")
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), at(0).alias("x"), at(1).alias("y"))


def event_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in the unit square: time as a fraction of the span, value as a fraction of its range."""
    events = load(spark, sf_dir, "events").select(F.col("event_id").alias("id"), micros("ts").alias("t"), cents("value").alias("c"))
    low = events.agg(F.min("t"), F.max("t"), F.min("c"), F.max("c")).first()
    scale = lambda col, lo, hi: F.floor((F.col(col) - lo) * F.lit(STEPS) / max(hi - lo, 1)).cast("long")
    return events.select("id", scale("t", low[0], low[1]).alias("x"), scale("c", low[2], low[3]).alias("y"))


def radius_steps(n: int) -> int:
    """0.55 sqrt(ln n / n) in integer steps of the unit square."""
    return int(RADIUS_FACTOR * math.sqrt(math.log(max(n, 2)) / max(n, 2)) * STEPS)


def radius_edges(points: DataFrame, radius: int) -> DataFrame:
    """Pairs of points nearer than ``radius``; weight: squared distance (0 counts as 1).

    Points meet over grid cells of the radius' width: each point looks into its own and four
    of the eight cells around it, so a pair meets once. Points are few bytes, their pairs are many:
    the tasks go by the number of points, not by their size.
    """
    tasks = max(points.sparkSession.sparkContext.defaultParallelism, points.count() >> 14)
    cell = points.withColumn("cx", F.floor(F.col("x") / radius)).withColumn("cy", F.floor(F.col("y") / radius))
    ahead = F.explode(F.array(*[F.struct(F.lit(dx).alias("dx"), F.lit(dy).alias("dy")) for dx, dy in ((0, 0), (1, -1), (1, 0), (1, 1), (0, 1))]))
    looking = cell.select(F.col("id").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay"), "cx", "cy", ahead.alias("d")).select("a", "ax", "ay", (F.col("cx") + F.col("d.dx")).alias("cx"), (F.col("cy") + F.col("d.dy")).alias("cy"), "d").repartition(tasks, "cx", "cy")
    met = looking.join(cell.select(F.col("id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"), "cx", "cy"), ["cx", "cy"])
    met = met.where("a <> b and (d.dx <> 0 or d.dy <> 0 or a < b)")
    squared = (F.col("ax") - F.col("bx")) * (F.col("ax") - F.col("bx")) + (F.col("ay") - F.col("by")) * (F.col("ay") - F.col("by"))
    near = met.withColumn("w", squared).where(F.col("w") < F.lit(radius * radius))
    return near.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), F.greatest(F.col("w"), F.lit(1)).alias("w"))


def rgg_events(spark: SparkSession, sf_dir: str, random_weights: bool = False) -> DataFrame:
    points = event_points(spark, sf_dir)
    edges = radius_edges(points, radius_steps(points.count()))
    return edges.withColumn("w", portable_hash(F.lit("w"), F.col("u"), F.col("v")) % STEPS + 1) if random_weights else edges


def rgg2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Random geometric graph of the embeddings' first two components, scaled to the unit square."""
    raw = points2d(spark, sf_dir)
    low = raw.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y"), F.count("*")).first()
    scale = lambda c, lo, hi: F.floor((F.col(c) - lo) * F.lit(STEPS) / max(hi - lo, 1)).cast("long")
    return radius_edges(raw.select("id", scale("x", low[0], low[1]).alias("x"), scale("y", low[2], low[3]).alias("y")), radius_steps(low[4]))


def floored_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Absolute inner products of all rows in millionths, rounded down, each as if summed component
    by component, in the order that SQL engines add. A matrix product may differ in the last
    digits, so entries nearer to a whole number than both errors together are summed in order."""
    with np.errstate(invalid="ignore", over="ignore"):
        value = np.abs(a @ b.T) * STEPS
        size = np.linalg.norm(a, axis=1)[:, None] * np.linalg.norm(b, axis=1)[None, :]
        slack = (4 * a.shape[1] + 8) * np.finfo(float).eps * STEPS * size
        w = np.floor(value)
        r, c = np.nonzero(~((np.floor(value - slack) == w) & (np.floor(value + slack) == w)))
        for k in range(0, len(r), 1 << 18):
            i, j = r[k : k + (1 << 18)], c[k : k + (1 << 18)]
            total = np.zeros(len(i))
            for d in range(a.shape[1]):
                total += a[i, d] * b[j, d]
            w[i, j] = np.floor(np.abs(total) * STEPS)
        return w.astype(np.int64)


def gram(spark: SparkSession, sf_dir: str, least: int = 200_000) -> DataFrame:
    """Absolute inner products of the embeddings in millionths, from ``least`` on.

    Rows are dealt into blocks, and every pair of blocks is a matrix product. The edges are
    written: whoever sorts them by range would have them made twice."""
    import pyarrow as pa

    vectors = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("x"))
    blocks = max(1, -(-vectors.count() // 1024))
    dealt = vectors.withColumn("mine", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    keyed = dealt.select("id", "x", "mine", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"))

    def products(table: pa.Table) -> pa.Table:
        ids, mine = table.column("id").to_numpy(), table.column("mine").to_numpy()
        x = np.array(table.column("x").to_pylist(), dtype=np.float64)
        first = mine == table.column("i")[0].as_py()
        second = mine == table.column("j")[0].as_py()
        a, b = np.flatnonzero(first), np.flatnonzero(second)
        w = floored_products(x[a], x[b])
        r, c = np.nonzero((w >= least) & ((ids[a][:, None] < ids[b][None, :]) | (table.column("i")[0].as_py() != table.column("j")[0].as_py())))
        u, v = ids[a[r]], ids[b[c]]
        return pa.table({"u": np.minimum(u, v), "v": np.maximum(u, v), "w": w[r, c]})

    # few bytes go in and many edges come out, so the tasks go by the number of products
    tasks = max(spark.sparkContext.defaultParallelism, blocks * (blocks + 1) // 32)
    edges = keyed.repartition(tasks, "i", "j").groupBy("i", "j").applyInArrow(products, "u long, v long, w long")
    return Scratch(spark, "gram").save(edges, "edges")


def delaunay2d(spark: SparkSession, sf_dir: str, limit: int | None = None) -> DataFrame:
    """Exact Delaunay edges of the embeddings' first two components, weight: squared length."""
    from .delaunay import delaunay_edges

    points = points2d(spark, sf_dir).groupBy("x", "y").agg(F.min("id").alias("id")).select("id", "x", "y")
    # written: whoever sorts the edges by range would have them made twice
    return Scratch(spark, "delaunay").save(delaunay_edges(points if limit is None else points.where(F.col("id") < limit)), "edges")


def doc_near(spark: SparkSession, sf_dir: str, gap: int = 20) -> DataFrame:
    """Documents of one language and source whose lengths differ by at most ``gap``, weight:
    how close they are. Lengths meet over buckets of the gap's width."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.col("n_chars").alias("n"), F.floor(F.col("n_chars") / gap).alias("b"))
    looking = docs.select(F.col("doc_id").alias("a"), "lang", "source", F.col("n").alias("an"), F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"), F.col("b").alias("home"))
    met = looking.join(docs.select(F.col("doc_id").alias("o"), "lang", "source", F.col("n").alias("bn"), "b"), ["lang", "source", "b"])
    near = met.where((F.col("a") != F.col("o")) & ((F.col("b") != F.col("home")) | (F.col("a") < F.col("o"))) & (F.abs(F.col("an") - F.col("bn")) <= gap))
    return near.select(F.least("a", "o").alias("u"), F.greatest("a", "o").alias("v"), (gap + 1 - F.abs(F.col("an") - F.col("bn"))).alias("w")).distinct()


def knn(edges: DataFrame, k: int) -> DataFrame:
    """Of a graph of distances, the edges that are among the ``k`` shortest of one of their ends."""
    from ..edges import arcs

    nearest = W.partitionBy("vertex").orderBy("w", "other")
    near = arcs(edges, "w").withColumn("place", F.row_number().over(nearest)).where(F.col("place") <= k)
    return near.select(F.least("vertex", "other").alias("u"), F.greatest("vertex", "other").alias("v"), "w").distinct()


def knn_events(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """The nearest neighbours of event points, as far as they lie within the radius of the
    random geometric graph."""
    return knn(rgg_events(spark, sf_dir), k)


def doc_jaccard(spark: SparkSession, sf_dir: str, size: int = 5, least: float = 0.8) -> DataFrame:
    """Documents whose sets of word shingles have a Jaccard similarity of ``least`` or more, weight:
    the similarity in millionths. Exact: of a set of n shingles in any common order, the first
    n - ceil(least n) + 1 hold one of those of each such partner; rare shingles come first here,
    so that passages of many documents do not bring these together."""
    words = F.filter(F.split(F.translate("text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "[\\x20\\x09-\\x0D]+"), lambda x: x != "")
    scratch = Scratch(spark, "shingles")
    # both are written: an array under a lambda would be made anew for each of its places
    docs = scratch.save(load(spark, sf_dir, "documents").where("doc_id is not null and text is not null").select("doc_id", words.alias("words")), "words").where(F.size("words") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.size("words") - size + 1, F.lit(1)))
    shingles = F.array_distinct(F.transform(starts, lambda i: F.xxhash64(F.array_join(F.slice("words", i, size), " "))))
    sets = scratch.save(docs.select("doc_id", shingles.alias("items")), "sets")
    rows = sets.select("doc_id", F.size("items").alias("n"), F.explode("items").alias("item"))
    common = rows.groupBy("item").agg(F.count("*").alias("common")).where("common > 1")
    place = F.row_number().over(W.partitionBy("doc_id").orderBy(F.coalesce("common", F.lit(1)), "item"))
    first = F.col("n") - F.ceil(F.col("n") * F.lit(least) - F.lit(1e-9)) + 1
    keys = rows.join(common, "item", "left").withColumn("place", place).where((F.col("place") <= first) & F.col("common").isNotNull()).select("doc_id", "n", "item")
    near = (F.col("n") >= F.lit(least) * F.col("m") - F.lit(1e-9)) & (F.col("m") >= F.lit(least) * F.col("n") - F.lit(1e-9))
    pairs = keys.select(F.col("doc_id").alias("u"), "n", "item").join(keys.select(F.col("doc_id").alias("v"), F.col("n").alias("m"), "item"), "item").where(near & (F.col("u") < F.col("v"))).select("u", "v").distinct()
    for c, name in (("u", "a"), ("v", "b")):
        pairs = pairs.join(sets.select(F.col("doc_id").alias(c), F.col("items").alias(name)), c)
    shared = F.size(F.array_intersect("a", "b"))
    both = pairs.select("u", "v", shared.alias("shared"), (F.size("a") + F.size("b") - shared).alias("all"))
    return both.where(F.col("shared") >= F.lit(least) * F.col("all") - F.lit(1e-9)).select("u", "v", F.floor(F.col("shared").cast("long") * F.lit(STEPS) / F.col("all")).alias("w"))
