"""Approximate nearest neighbours: a neighbour graph by NN-descent, searched greedily.

Every vector starts with its nearest in cells of bounded size (random hyperplanes through the
middle of a sample, and one table of random cells), and lists that are still short are filled
up from a few drawn nodes of the same length, so that each node has ``degree`` neighbours, or
all others where there are fewer. Rounds of joins then refine the graph: around every node its
new and old neighbours meet, and a hashed choice, drawn anew each round, of those that list it;
pairs of which one is new are measured, and each node keeps the nearest. Rounds end when less
than ``SETTLED`` of all list entries are new. Equal vectors are one node that knows its
smallest ids.

Queries walk the graph side by side from their own node: each step opens the nearest unopened
nodes of every query, joins their lists, and ends for a query when nothing unopened is left in
its beam. A query's own list already holds at least ``k`` nodes if there are so many.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, Window as W

from .storage import Scratch
from .textkernels import tidy
from .vectors import decode, distinct_vectors, packed

DEGREE = 32
TABLES = 10
LEAF = 256
#: Rows of the bounded sample through whose middle the hyperplanes go.
FIT_SAMPLE = 4096
#: Drawn nodes of each vector length for lists that the cells left short.
ANCHORS = 64
#: Nearest candidates that a node is offered around each shared node in a round.
OFFERS = 8
#: Rounds end when the share of new list entries is below this.
SETTLED = 0.05
MOST_ROUNDS = 60
BEAM = 128
OPEN = 48
MOST_STEPS = 400
NAMES = 16


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Euclidean distances of all rows of x to all of y, in double precision, by differences."""
    out = np.empty((len(x), len(y)))
    strip = max(1, (1 << 21) // max(1, y.size))
    for i in range(0, len(x), strip):
        with np.errstate(over="ignore", under="ignore"):
            gap = x[i : i + strip, None, :] - y[None]
            d = np.sqrt((gap**2).sum(axis=2))
            odd = ~np.isfinite(d) | (d < 1e-140)
            if odd.any():  # squares out of range
                most = np.abs(gap[odd]).max(axis=1, keepdims=True)
                part = np.divide(gap[odd], most, out=np.zeros_like(gap[odd]), where=(most > 0) & np.isfinite(most))
                d[odd] = np.where(np.isfinite(most), most, np.inf)[:, 0] * np.where(np.isfinite(most[:, 0]), np.sqrt((part**2).sum(axis=1)), 1.0)
        out[i : i + strip] = d
    return out


def squares(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances by one matrix product around a row of middle length, for ranking inside
    the graph: neither a common offset nor a few far rows cost the near ones their digits."""
    with np.errstate(over="ignore", invalid="ignore"):
        both = (y**2).sum(axis=1)
        centre = y[np.argpartition(both, len(y) // 2)[len(y) // 2]]
        x, y = x - centre, y - centre
        out = np.maximum((x**2).sum(axis=1)[:, None] + (y**2).sum(axis=1)[None, :] - 2 * x @ y.T, 0)
    return out if np.isfinite(out).all() else distances(x, y)


class Codec:
    """Vectors as bytes: single precision where that loses nothing for any row, else double."""

    def __init__(self, narrow: bool):
        self.kind = np.float32 if narrow else np.float64
        self.width = np.dtype(self.kind).itemsize

    def rows(self, blobs: list[bytes]) -> np.ndarray:
        return np.frombuffer(b"".join(blobs), self.kind).reshape(len(blobs), -1).astype(np.float64)


def lossless(points: DataFrame, scratch: Scratch) -> tuple[DataFrame, Codec]:
    """``(id, dim, vec)`` in the narrowest form that keeps every component as it is."""

    def fits(batches):
        for batch in batches:
            with np.errstate(over="ignore"):
                ok = [bool((v.astype(np.float32) == v).all()) for v in (np.frombuffer(b, np.float64) for b in batch.column(0).to_pylist())]
            yield pa.RecordBatch.from_arrays([pa.array([all(ok)])], names=["fits"])

    codec = Codec(points.select("vec").mapInArrow(fits, "fits boolean").agg(F.bool_and("fits")).first()[0] is not False)

    def shrink(batches):
        for batch in batches:
            held = [np.frombuffer(v, np.float64) for v in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(v) for v in held], pa.int64()), pa.array([v.astype(codec.kind).tobytes() for v in held], pa.binary())], names=["id", "dim", "vec"])

    return scratch.save(points.select("id", "vec").mapInArrow(shrink, "id long, dim long, vec binary"), "narrow"), codec


def whole_keys(batches, key: str, rows: int = 8192) -> Iterator[pa.Table]:
    """Tables of some rows, each with all rows of its keys, from batches sorted by the key."""
    kept, n, wait = [], 0, rows
    for batch in batches:
        if not len(batch):
            continue
        kept.append(batch)
        n += len(batch)
        if n < wait:
            continue
        table = pa.Table.from_batches(kept).combine_chunks()
        values = table.column(key).to_numpy()
        cut = int(np.searchsorted(values, values[-1]))
        if cut:
            yield table.slice(0, cut)
        kept, n = table.slice(cut).to_batches(), len(table) - cut
        wait = max(rows, 2 * n)
    if kept:
        yield pa.Table.from_batches(kept).combine_chunks()


def runs(values: np.ndarray) -> list[tuple[int, int]]:
    """Starts and ends of the runs of equal values."""
    turn = (np.flatnonzero(values[1:] != values[:-1]) + 1).tolist()
    return list(zip([0, *turn], [*turn, len(values)])) if len(values) else []


LISTS = "id long, near array<long>, far array<double>, fresh array<boolean>"


def list_rows(ids, sizes, near, far, fresh) -> pa.RecordBatch:
    """Lists of neighbours from flat arrays."""
    at = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
    parts = [pa.ListArray.from_arrays(at, pa.array(x)) for x in (near, far, fresh)]
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *parts], names=["id", "near", "far", "fresh"])


class Offers:
    """Collects candidate lists and hands them out in batches of some size."""

    def __init__(self, degree: int):
        self.degree, self.ids, self.sizes, self.near, self.far = degree, [], [], [], []

    def add(self, ids: np.ndarray, others: np.ndarray, d: np.ndarray, wanted: np.ndarray) -> None:
        """For each row of the matrix d its nearest wanted columns, ``degree`` at most."""
        k = min(self.degree, d.shape[1])
        d = np.where(wanted, d, np.inf)
        best = np.argpartition(d, k - 1, axis=1)[:, :k] if k < d.shape[1] else np.broadcast_to(np.arange(k), d.shape)
        dist = np.take_along_axis(d, best, axis=1)
        good = np.isfinite(dist)
        count = good.sum(axis=1)
        some = count > 0
        if some.any():
            self.ids.append(ids[some])
            self.sizes.append(count[some])
            self.near.append(others[best[good]])
            self.far.append(dist[good])

    def flush(self, least: int = 0) -> Iterator[pa.RecordBatch]:
        if self.ids and sum(map(len, self.near)) >= least:
            near = np.concatenate(self.near)
            yield list_rows(np.concatenate(self.ids), np.concatenate(self.sizes), near, np.concatenate(self.far), np.ones(len(near), bool))
            self.ids, self.sizes, self.near, self.far = [], [], [], []


def plane_middles(points: DataFrame, codec: Codec, n: int, draw) -> dict[int, np.ndarray]:
    """For each vector length of a bounded sample, the middle of its rows along each normal."""
    share = min(1.0, FIT_SAMPLE / max(n, 1))
    rows = points.where(F.pmod(F.xxhash64("id"), F.lit(1 << 30)) < F.lit(int(share * (1 << 30)))).select("dim", "vec").collect()
    held: dict[int, list] = {}
    for r in rows:
        held.setdefault(r["dim"], []).append(bytes(r["vec"]))
    return {dim: np.median(codec.rows(v) @ draw(dim), axis=0) for dim, v in held.items()}


def first_lists(points: DataFrame, codec: Codec, n: int, degree: int, tables: int, seed: int = 5) -> DataFrame:
    """Neighbour lists inside the cells of ``tables`` choices of hyperplanes and one of hashes."""
    bits = max(int(n > LEAF), math.ceil(math.log2(max(n, 1) / (2 * LEAF))))

    def draw(dim: int) -> np.ndarray:
        return np.random.default_rng([seed, dim]).normal(size=(dim, tables * bits))

    middles = plane_middles(points, codec, n, draw) if bits else {}

    def place(batches):
        for batch in batches:
            dims = batch.column(1).to_numpy()
            for dim in np.unique(dims):
                take = pa.array(np.flatnonzero(dims == dim))
                ids, dim_column, vecs = (c.take(take) for c in batch.columns)
                x, size = codec.rows(vecs.to_pylist()), len(take)
                with np.errstate(over="ignore", invalid="ignore"):
                    side = (x @ draw(int(dim)) > middles.get(int(dim), 0)).reshape(size, tables, bits)
                cell = side @ (1 << np.arange(bits)) if bits else np.zeros((size, tables), np.int64)
                for t in range(tables):
                    yield pa.RecordBatch.from_arrays([ids, dim_column, vecs, pa.array(np.full(size, t, np.int64)), pa.array(cell[:, t].astype(np.int64))], names=["id", "dim", "vec", "tab", "cell"])

    placed = points.select("id", "dim", "vec").mapInArrow(place, "id long, dim long, vec binary, tab long, cell long")
    chance = points.select("id", "dim", "vec", F.lit(tables).cast("long").alias("tab"), F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << bits)).alias("cell"))
    placed = placed.unionByName(chance)
    crowds = placed.groupBy("dim", "tab", "cell").agg(F.ceil(F.count("*") / (4 * LEAF)).cast("int").alias("parts"))
    slot = F.xxhash64("dim", "tab", "cell", F.pmod(F.xxhash64("id", "tab"), F.col("parts")))
    dealt = placed.join(crowds, ["dim", "tab", "cell"]).select(slot.alias("slot"), "dim", "id", "vec")

    def link(batches):
        offers = Offers(degree)
        for table in whole_keys(batches, "slot", 4 * LEAF):
            dims = table.column("dim").to_numpy()
            for lo, hi in runs(table.column("slot").to_numpy()):
                for dim in np.unique(dims[lo:hi]):  # one, unless hashes of cells collide
                    rows = np.flatnonzero(dims[lo:hi] == dim) + lo
                    part = table.take(pa.array(rows))
                    ids, x = part.column("id").to_numpy(), codec.rows(part.column("vec").to_pylist())
                    offers.add(ids, ids, squares(x, x), ids[:, None] != ids[None, :])
            yield from offers.flush(1 << 16)
        yield from offers.flush()

    return dealt.repartition("slot").sortWithinPartitions("slot").mapInArrow(tidy(link), LISTS)


def anchor_lists(graph: DataFrame, points: DataFrame, codec: Codec, degree: int, scratch: Scratch) -> DataFrame:
    """Lists over drawn nodes for nodes whose lists hold fewer than ``degree`` and than all others."""
    crowd = points.groupBy("dim").agg((F.count("*") - 1).alias("others"))
    have = graph.select("id", F.size("near").alias("have"))
    short = scratch.save(points.join(crowd, "dim").join(have, "id", "left").where(F.coalesce("have", F.lit(0)) < F.least(F.col("others"), F.lit(degree))).select("id", "dim", "vec"), "short")
    drawn = W.partitionBy("dim").orderBy(F.xxhash64("id"), "id")
    anchors = scratch.save(points.withColumn("place", F.row_number().over(drawn)).where(F.col("place") <= max(ANCHORS, degree + 1)).select("dim", F.col("id").alias("other"), F.col("vec").alias("there")), "anchors")
    met = short.join(anchors, "dim").where("id <> other").select("id", "vec", "other", "there")

    def link(batches):
        offers = Offers(degree)
        for table in whole_keys(batches, "id"):
            ids = table.column("id").to_numpy()
            for lo, hi in runs(ids):
                part = table.slice(lo, hi - lo)
                d = distances(codec.rows(part.column("vec").to_pylist()[:1]), codec.rows(part.column("there").to_pylist())) ** 2
                offers.add(ids[lo : lo + 1], part.column("other").to_numpy(), d, np.ones(d.shape, bool))
            yield from offers.flush(1 << 16)
        yield from offers.flush()

    return met.repartition("id").sortWithinPartitions("id").mapInArrow(tidy(link), LISTS)


def merged(lists: DataFrame, degree: int) -> DataFrame:
    """The ``degree`` nearest of each node over all its lists; an entry that any list knows as
    old is old."""

    def run(batches):
        for table in whole_keys(batches, "id"):
            ids = table.column("id").to_numpy()
            column = table.column("near").combine_chunks()
            sizes = column.value_lengths().to_numpy()
            who, near = np.repeat(ids, sizes), column.flatten().to_numpy()
            far, fresh = (table.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False) for c in ("far", "fresh"))
            order = np.lexsort((fresh, near, who))
            who, near, far, fresh = who[order], near[order], far[order], fresh[order]
            first = np.ones(len(who), bool)
            first[1:] = (who[1:] != who[:-1]) | (near[1:] != near[:-1])
            who, near, far, fresh = who[first], near[first], far[first], fresh[first]
            order = np.lexsort((near, far, who))
            who, near, far, fresh = who[order], near[order], far[order], fresh[order]
            starts = np.flatnonzero(np.concatenate([[True], who[1:] != who[:-1]])) if len(who) else np.zeros(0, np.int64)
            counts = np.diff(np.append(starts, len(who)))
            keep = np.arange(len(who)) - np.repeat(starts, counts) < degree
            yield list_rows(who[starts], np.minimum(counts, degree), near[keep], far[keep], fresh[keep])

    return lists.repartition("id").sortWithinPartitions("id").mapInArrow(tidy(run), LISTS)


def descend(graph: DataFrame, points: DataFrame, codec: Codec, degree: int, turn: int) -> DataFrame:
    """One NN-descent round: candidate lists from the pairs around each shared node of which one
    is new there."""
    entries = graph.select("id", F.explode(F.arrays_zip("near", "fresh")).alias("e")).select("id", F.col("e.near").alias("near"), F.col("e.fresh").alias("fresh"))
    ahead = entries.select(F.col("id").alias("hub"), F.col("near").alias("id"), "fresh", F.lit(0).alias("side"))
    behind = entries.select(F.col("near").alias("hub"), "id", "fresh", F.lit(1).alias("side"))
    own = graph.select(F.col("id").alias("hub"), "id", F.lit(False).alias("fresh"), F.lit(0).alias("side"))
    chosen = W.partitionBy("hub", "side").orderBy(F.col("fresh").desc(), F.xxhash64("hub", "id", F.lit(turn)))
    members = ahead.unionByName(behind).unionByName(own).repartition("hub").withColumn("k", F.row_number().over(chosen)).where((F.col("side") == 0) | (F.col("k") <= degree))
    members = members.withColumn("stirred", F.bool_or("fresh").over(W.partitionBy("hub"))).where("stirred").select("hub", "id", "fresh")
    bounds = graph.select("id", F.when(F.size("near") >= degree, F.element_at("far", -1)).alias("bound"))
    met = members.join(points.select("id", "vec").join(bounds, "id", "left"), "id")

    def run(batches):
        offers = Offers(min(degree, OFFERS))
        for table in whole_keys(batches, "hub"):
            ids, hubs = table.column("id").to_numpy(), table.column("hub").to_numpy()
            fresh = table.column("fresh").to_numpy()
            bound = table.column("bound").to_numpy(zero_copy_only=False).astype(np.float64)
            bound = np.where(np.isnan(bound), np.inf, bound)
            blobs = table.column("vec").to_pylist()
            for lo, hi in runs(hubs):
                # a node that stands on both sides is one member, new if either says so
                order = np.lexsort((~fresh[lo:hi], ids[lo:hi])) + lo
                order = order[np.concatenate([[True], ids[order][1:] != ids[order][:-1]])]
                new, names = fresh[order], ids[order]
                x = codec.rows([blobs[i] for i in order.tolist()])
                d = squares(x, x)
                wanted = (d < bound[order, None]) & (new[:, None] | new[None, :])
                np.fill_diagonal(wanted, False)
                if wanted.any():
                    offers.add(names, names, d, wanted)
            yield from offers.flush(1 << 16)
        yield from offers.flush()

    return met.select("hub", "id", "vec", "fresh", "bound").repartition("hub").sortWithinPartitions("hub").mapInArrow(tidy(run), LISTS)


def build_graph(points: DataFrame, codec: Codec, scratch: Scratch, degree: int = DEGREE, tables: int = TABLES) -> DataFrame:
    """``(id, near, far, fresh)``: of each node its nearest nodes found and their squared
    distances. A node without any other of its length has no row."""
    n = points.count()
    first = scratch.save(merged(first_lists(points, codec, n, degree, tables), degree), "graph")
    graph = scratch.save(merged(first.unionByName(anchor_lists(first, points, codec, degree, scratch)), degree), "graph")
    scratch.drop(first)
    for turn in range(MOST_ROUNDS):
        old = graph.withColumn("fresh", F.transform("fresh", lambda _: F.lit(False)))
        after = scratch.save(merged(old.unionByName(descend(graph, points, codec, degree, turn)), degree), "graph")
        scratch.drop(graph)
        graph = after
        moved, size = graph.agg(F.sum(F.size(F.filter("fresh", lambda x: x))), F.sum(F.size("near"))).first()
        if (moved or 0) <= SETTLED * (size or 0):
            return graph
    raise RuntimeError(f"the neighbour graph did not settle in {MOST_ROUNDS} rounds")


def both_ways(graph: DataFrame, most: int = DEGREE) -> DataFrame:
    """``(id, near)``: what a node lists and a hashed choice of those that list it."""
    links = graph.select("id", F.explode("near").alias("other"))
    chosen = W.partitionBy("id").orderBy(F.xxhash64("id", "other"))
    back = links.select(F.col("other").alias("id"), F.col("id").alias("other")).withColumn("k", F.row_number().over(chosen)).where(F.col("k") <= most).drop("k")
    return links.unionByName(back).groupBy("id").agg(F.collect_set("other").alias("near"))


def search(graph: DataFrame, points: DataFrame, queries: DataFrame, codec: Codec, scratch: Scratch, beam: int = BEAM) -> DataFrame:
    """Queries ``(query_id, vec, entry)`` to ``(query_id, vec, ids, far)``: the ``beam`` nearest
    nodes found, nearest first. ``entry`` is the node of the query's own vector."""
    ddl = "query_id long, vec binary, ids array<long>, far array<double>, opened array<boolean>"
    ways = scratch.save(both_ways(graph), "ways")
    state = scratch.save(queries.select("query_id", "vec", F.array("entry").alias("ids"), F.array(F.lit(0.0)).alias("far"), F.array(F.lit(False)).alias("opened")), "beam")

    def widen(batches):
        for table in whole_keys(batches, "query_id"):
            out = []
            kinds = table.column("kind").to_numpy()
            for lo, hi in runs(table.column("query_id").to_numpy()):
                # a query that is listed twice stands twice at the head of its rows
                heads = lo + int(np.count_nonzero(kinds[lo:hi] == 0))
                met = table.column("id").slice(heads, hi - heads).to_numpy()
                there = codec.rows(table.column("vec").slice(heads, hi - heads).to_pylist()) if hi > heads else None
                for head in range(lo, heads):
                    row = table.slice(head, 1).to_pylist()[0]
                    ids, far, opened = np.array(row["ids"], np.int64), np.array(row["far"]), np.array(row["opened"])
                    opened[np.flatnonzero(~opened)[:OPEN]] = True
                    if there is not None:
                        new = ~np.isin(met, ids)
                        d = distances(codec.rows([row["vec"]]), there[new])[0]
                        ids, far, opened = np.concatenate([ids, met[new]]), np.concatenate([far, d]), np.concatenate([opened, np.zeros(len(d), bool)])
                    order = np.lexsort((ids, far))[:beam]
                    out.append((row["query_id"], row["vec"], ids[order], far[order], opened[order]))
            if out:
                kinds = (pa.int64(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.float64()), pa.list_(pa.bool_()))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=["query_id", "vec", "ids", "far", "opened"])

    for _ in range(MOST_STEPS):
        # the nearest unopened nodes of each query; beams hold nearest first
        todo = F.slice(F.filter(F.arrays_zip("ids", "opened"), lambda x: ~x["opened"]), 1, OPEN)
        front = state.select("query_id", F.explode(todo).alias("x")).select("query_id", F.col("x.ids").alias("id"))
        if front.isEmpty():
            return state.select("query_id", "vec", "ids", "far")
        reached = front.join(ways, "id").select("query_id", F.explode("near").alias("id")).distinct()
        fresh = reached.join(points.select("id", "vec"), "id").select("query_id", F.lit(1).alias("kind"), "id", "vec")
        both = state.withColumn("kind", F.lit(0)).unionByName(fresh, allowMissingColumns=True)
        after = scratch.save(both.repartition("query_id").sortWithinPartitions("query_id", "kind").mapInArrow(tidy(widen), ddl), "beam")
        scratch.drop(state)
        state = after
    raise RuntimeError(f"searches did not end in {MOST_STEPS} steps")


def nearest(vectors: DataFrame, every: int = 100, k: int = 10, scratch: Scratch | None = None, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the ``k`` nearest found of each row whose id is
    divisible by ``every``, nearest first, ties to the smaller id.

    Every query gets ``k`` rows, or all candidates where there are fewer. Vectors that are null,
    empty, zero or hold null or non-finite components take no part, as query or candidate, and
    vectors of different length never meet. A row is not its own candidate; another row with an
    equal vector is. Rows with a null id take no part, repeated ids count once. An empty table
    gives an empty result; extra columns are ignored.
    """
    if k >= NAMES or k >= DEGREE:
        raise ValueError("k must stay below NAMES and DEGREE")
    scratch = scratch or Scratch(vectors.sparkSession, "neighbours")
    rows = scratch.save(packed(vectors, id_col, vector_col).where("vec is not null and vec_id is not null").distinct(), "packed")
    points, codec = lossless(distinct_vectors(rows), scratch)
    # the smallest ids of each vector: enough to name k neighbours besides the query itself
    ranked = rows.withColumn("place", F.row_number().over(W.partitionBy("vec").orderBy("vec_id"))).where(F.col("place") <= NAMES)
    names = scratch.save(ranked.groupBy("vec").agg(F.min("vec_id").alias("id"), F.sort_array(F.collect_set("vec_id")).alias("members")).select("id", "members"), "names")
    graph = build_graph(points, codec, scratch)
    owner = rows.groupBy("vec").agg(F.min("vec_id").alias("entry"))
    asked = rows.where(F.col("vec_id") % every == 0).join(owner, "vec").select(F.col("vec_id").alias("query_id"), "entry")
    asked = asked.join(points.select(F.col("id").alias("entry"), "vec"), "entry")
    found = search(graph, points, asked, codec, scratch)
    pairs = found.select("query_id", F.explode(F.arrays_zip("ids", "far")).alias("x")).select("query_id", F.col("x.ids").alias("id"), F.col("x.far").alias("score"))
    each = pairs.join(names, "id").select("query_id", "score", F.explode("members").alias("vec_id")).where("vec_id <> query_id")
    order = W.partitionBy("query_id").orderBy("score", "vec_id")
    return each.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
