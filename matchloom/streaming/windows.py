"""Matching on event streams: graphs of time windows, and the usual stream operators around.

``run_stream`` drains what is there (availableNow) into a table of the shared folder, through
foreachBatch, so a batch that is repeated after a failure overwrites its own folder.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..catalog import make_importable
from ..edges import canonical_edges
from ..operators.localmax import local_max
from ..storage import Scratch

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str, watermark: str = "1 hour") -> DataFrame:
    """The events table as a stream, with event time ``at``."""
    make_importable(spark)
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet") if _is_folder(spark, sf_dir) else spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("at", F.col("ts").cast("timestamp")).drop("ts").withWatermark("at", watermark)


def _is_folder(spark: SparkSession, sf_dir: str) -> bool:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()


def run_stream(stream: DataFrame, label: str, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None, numbered: bool = False, progress: list[int] | None = None) -> DataFrame:
    """All output rows of a stream as a table; in complete mode the last batch replaces the folder.
    ``numbered`` adds the number of the batch that wrote a row, ``progress`` gets the rows that
    each batch dropped as late."""
    spark = stream.sparkSession
    scratch = Scratch(spark, label)
    schema = (each(spark.createDataFrame([], stream.schema)) if each else spark.createDataFrame([], stream.schema)).schema

    def keep(batch: DataFrame, number: int) -> None:
        out = each(batch) if each else batch
        target = f"{scratch.root}/rows" if mode == "complete" else f"{scratch.root}/rows/batch={number}"
        out.write.mode("overwrite").parquet(target)

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{scratch.root}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()
    if progress is not None:
        progress += [op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators]
    if numbered:
        return spark.read.schema(schema.add("batch", "long")).parquet(f"{scratch.root}/rows")
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{scratch.root}/rows")


def window_graph(events: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """``(window_start, user_id, event_type, n, cents)``: use of event types by users per window."""
    window = F.window("at", length, slide) if slide else F.window("at", length)
    grouped = events.groupBy(window.alias("win"), "user_id", "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return grouped.select(F.col("win.start").alias("window_start"), "user_id", "event_type", "n", "cents")


def match_windows(edges: DataFrame) -> DataFrame:
    """Local max in each window of a table ``(window_start, u, v, w)``."""
    return local_max(edges, by=("window_start",)).matching.select("window_start", "u", "v", "w", "phase")


def type_vertex() -> F.Column:
    return F.conv(F.substring(F.md5(F.col("event_type")), 1, 12), 16, 10).cast("long") + 1_000_000_000


def typed_edges(graph: DataFrame) -> DataFrame:
    """Users and event types of windows as edges ``(window_start, u, v, w)``."""
    return graph.where("cents > 0").select("window_start", F.col("user_id").alias("u"), type_vertex().alias("v"), F.col("cents").alias("w"))


def stream_window_matching(spark: SparkSession, sf_dir: str, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Matching of users with event types in each closed window; every batch matches the windows
    that it closes, inside foreachBatch."""
    graph = window_graph(read_events(spark, sf_dir), length, slide)
    return run_stream(graph, "windows", each=lambda batch: match_windows(typed_edges(batch)))


STORE = "window_start string, u long, v long, w long"


def stream_mate_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(window_start, u, v, w)``: the same matching of closed days, kept as state. A day's state
    holds its edges and their weights; when the watermark passes the day, its edges are taken by
    falling weight, and the state goes."""
    import hashlib

    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    day = F.date_trunc("day", F.col("at"))
    rows = read_events(spark, sf_dir).select(F.date_format(day, "yyyy-MM-dd HH:mm:ss").alias("day"), F.unix_millis(day).alias("start"), "at", F.col("user_id").alias("u"), type_vertex().alias("v"), F.round(F.col("value") * 100).cast("long").alias("cents"))

    def keep(key, parts, state: GroupState):
        if state.hasTimedOut:
            u, v, w = (list(x) for x in state.get)
            state.remove()
            order = sorted(range(len(u)), key=lambda k: (-w[k], hashlib.md5(f"42|{u[k]}|{v[k]}".encode()).hexdigest(), u[k], v[k]))
            used, out = set(), []
            for k in order:
                if w[k] > 0 and u[k] not in used and v[k] not in used:
                    used |= {u[k], v[k]}
                    out.append((key[0], u[k], v[k], w[k]))
            yield pd.DataFrame(out, columns=["window_start", "u", "v", "w"])
            return
        held = dict(zip(zip(state.get[0], state.get[1]), state.get[2])) if state.exists else {}
        start = 0
        for part in parts:
            start = int(part["start"].iloc[0])
            for (u, v), cents in part.groupby(["u", "v"])["cents"].sum().items():
                held[u, v] = held.get((u, v), 0) + int(cents)
        state.update(([int(u) for u, _ in held], [int(v) for _, v in held], list(held.values())))
        state.setTimeoutTimestamp(start + 86_400_000)

    stored = rows.groupBy("day").applyInPandasWithState(keep, STORE, "u array<long>, v array<long>, w array<long>", "append", GroupStateTimeout.EventTimeTimeout)
    return run_stream(stored, "mates")


def stream_interval_join(spark: SparkSession, sf_dir: str, first: str = "view", then: str = "purchase", minutes: int = 10) -> DataFrame:
    """Pairs of events of one user, ``then`` at most some minutes after ``first``; both sides carry a
    watermark, so the state of either is dropped when no partner can come."""
    events = read_events(spark, sf_dir)
    left = events.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), "user_id", F.col("at").alias("began"))
    right = read_events(spark, sf_dir).where(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("who"), F.col("at").alias("ended"))
    near = F.expr(f"user_id = who and ended >= began and ended <= began + interval {minutes} minutes")
    return run_stream(left.join(right, near).select("user_id", "first_id", "then_id"), "interval")


def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(kept, late)``: the newest third of the time comes first, then the middle, then the oldest.
    The watermark of a batch judges the batch after the next, so the middle is kept and the oldest
    rows are dropped and counted."""
    scratch = Scratch(spark, "late")
    events = spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")
    moment = F.unix_micros(F.col("ts").cast("timestamp"))
    least, most = (x or 0 for x in events.agg(F.min(moment), F.max(moment)).first())
    third = (most - least) // 3
    folder = f"{scratch.root}/arrivals"
    for low, high in ((least + 2 * third, most + 1), (least + third, least + 2 * third), (least, least + third)):
        events.where((moment >= low) & (moment < high)).coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.2)  # files arrive in the order of their times
    stream = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(folder)
    once = stream.withColumn("at", F.col("ts").cast("timestamp")).drop("ts").withWatermark("at", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    dropped: list[int] = []
    kept = run_stream(once.select("event_id"), "late", progress=dropped).count()
    return spark.createDataFrame([(kept, sum(dropped))], "kept long, late long")


def stream_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals by event type in update mode: each batch writes what changed, the last word counts."""
    grouped = read_events(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n"))
    rows = run_stream(grouped, "updates", mode="update", numbered=True)
    return rows.groupBy("event_type").agg(F.max_by("n", "batch").alias("n"))


def stream_sessions(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """Sessions of users that have closed: ``(user_id, session_start, session_end, n)``."""
    events = read_events(spark, sf_dir)
    grouped = events.groupBy(F.session_window("at", gap).alias("s"), "user_id").agg(F.count("*").alias("n"))
    return run_stream(grouped.select("user_id", F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), "n"), "sessions")


def stream_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events once each, within the watermark."""
    return run_stream(read_events(spark, sf_dir).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "distinct")


def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the number of events of their user, from the table at rest."""
    static = spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet").groupBy("user_id").agg(F.count("*").alias("degree"))
    return run_stream(read_events(spark, sf_dir).join(static, "user_id").select("event_id", "user_id", "degree"), "static")


def stream_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals by event type in complete mode."""
    return run_stream(read_events(spark, sf_dir).groupBy("event_type").agg(F.count("*").alias("n")), "totals", mode="complete")


def repair(edges: DataFrame, matching: DataFrame, fresh: DataFrame) -> DataFrame:
    """A maximal matching of ``edges`` and ``fresh`` from one of ``edges``: a new edge enters if
    it outweighs the matched edges that it touches; around what that frees, free vertices are
    matched anew. Valid and maximal; its weight is that of a local repair."""
    from ..edges import arcs
    from ..operators.localmax import drop_covered

    scratch = Scratch(edges.sparkSession, "repair")
    held = arcs(matching, "w").select("vertex", F.col("w").alias("held"))
    rated = fresh
    for c in "uv":
        rated = rated.join(held.select(F.col("vertex").alias(c), F.col("held").alias(f"h{c}")), c, "left")
    strong = rated.where(F.col("w") > F.coalesce("hu", F.lit(0)) + F.coalesce("hv", F.lit(0))).select("u", "v", "w")
    entering = scratch.save(local_max(strong, scratch=scratch).matching.select("u", "v", "w"), "entering")
    kept = scratch.save(drop_covered(matching.select("u", "v", "w"), entering, [], False).unionByName(entering), "kept")
    everything = canonical_edges(edges.select("u", "v", "w").unionByName(fresh.select("u", "v", "w")), combine="max")
    rest = local_max(drop_covered(everything, kept, [], False).select("u", "v", "w"), scratch=scratch).matching.select("u", "v", "w")
    return kept.unionByName(rest)
