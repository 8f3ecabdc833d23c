"""Mixing sources to target weights, in DataFrame operations only.

Words of each source are packed into blocks of ``block`` words. The output is a row of slots
in shards of ``shard`` slots. A pseudorandom permutation deals the slots to the sources by their
quotas, so the counts of a shard are a multinomial draw given that the totals meet the targets;
every shard is mixed, and nothing has to be cut or filled up. A source's slots are numbered
through all shards; slot j of a source takes block P(j mod n) of its n blocks, P a pseudorandom
permutation that changes with every turn j div n, and slots meet blocks by that index.

A hot source is packed in buckets of about BUCKET_WORDS words, each packed by its own task; rows of
a doc_id that is repeated very often are dealt by row. Running sums over sources, buckets and
shards go by ranges, so no step gathers a source, or all sources. Hashes are md5 based, so that
SQL engines can follow them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..operators.scan import prefix_sum
from .storage import Scratch

WORD = r"[^\x20\x09-\x0D]+"
BLOCK_WORDS = 64
SHARD_SLOTS = 1 << 16
BUCKET_WORDS = 1 << 20
CELLS = 1024
MOST_TURNS = 3
SEED = 17
#: Rows of one doc_id that a bucket takes at most, and rows of a table that is broadcast.
SAME_ID_ROWS = 1 << 12
BROADCAST_ROWS = 1 << 19
#: Rows whose running sum one task makes; more go by ranges.
WINDOW_ROWS = 1 << 16
#: Primes just above 2^20, one of which does not divide a given count below 2^40.
MULTIPLIERS = (1048583, 1048589)


def hash48(*parts: Column | str) -> Column:
    """The first 48 bits of an md5 over the parts, as a long."""
    parts = [F.col(p) if isinstance(p, str) else p for p in parts]
    text = F.concat_ws("|", F.lit(str(SEED)), *[F.coalesce(p.cast("string"), F.lit("-")) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long")


def permuted(x: Column, n: Column, key: Column) -> Column:
    """Position of x under the permutation of 0..n-1 that the 48-bit key names (n < 2^40)."""
    first, second = (F.when(n % p == 0, F.lit(q)).otherwise(F.lit(p)) for p, q in (MULTIPLIERS, MULTIPLIERS[::-1]))
    width = F.length(F.bin(n)) - 1
    low = F.call_function("shiftleft", F.lit(1).cast("long"), width) - 1
    half = F.greatest((width + 1).cast("int") / 2, F.lit(1)).cast("int")

    def fold(v: Column) -> Column:
        return v.bitwiseXOR(F.call_function("shiftright", v, half))

    y = (x * first + key % n) % n
    mixed = fold((fold(y) * F.lit(668265) + key % 1000003).bitwiseAND(low))
    y = F.when(y <= low, mixed).otherwise(y)
    return (y * second + F.floor(key / 4096).cast("long") % n) % n


def small(table: DataFrame) -> DataFrame:
    """The written table, marked for broadcast if its rows are few."""
    return F.broadcast(table) if table.count() <= BROADCAST_ROWS else table


def running(table: DataFrame, order: list[str], values: dict[str, Column], scratch: Scratch) -> DataFrame:
    """Exclusive running sums of ``values`` in ``order``, which tells all rows apart."""
    table = scratch.save(table, "summed")
    if table.count() <= WINDOW_ROWS:
        before = W.orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
        return table.select("*", *[F.coalesce(F.sum(v).over(before), F.lit(0)).alias(out) for out, v in values.items()])
    for out, v in values.items():
        table = prefix_sum(table, order, v, scratch, out)
    return table


def source_targets(sizes: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """``(source, source_no, weight, source_size, target)`` from rows ``(source, size)``.

    Weights go 1, 2, 3 and again, by code point, null last. All words are shared by weight, no
    source above MOST_TURNS times its own size; the level is that of the first source, in
    order of size by weight, that stays below its limit once all before it are at theirs.
    """
    scratch = scratch or Scratch(sizes.sparkSession, "targets")
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.lit(1).cast("long").alias("one")).withColumn("last", F.col("source").isNull())
    placed = running(per, ["last", "source"], {"source_no": F.col("one")}, scratch)
    named = scratch.save(placed.withColumn("weight", (F.col("source_no") % 3 + 1).cast("double")).withColumn("ratio", F.col("source_size") / F.col("weight")), "named")
    limit = F.lit(float(MOST_TURNS)) * F.col("source_size")
    everything = named.agg(F.sum("source_size"), F.sum("weight")).first()
    words, weights = float(everything[0] or 0), float(everything[1] or 0)
    tight = ["ratio", "source_no"]
    filled = running(named, tight, {"limits": limit, "weights": F.col("weight")}, scratch)
    level = (F.lit(words) - F.col("limits")) / (F.lit(weights) - F.col("weights"))
    free = filled.withColumn("level", level).where(F.col("level") * F.col("weight") <= limit)
    top = free.agg(F.min(F.struct(*tight, "level"))["level"]).first()[0] or 0.0
    return named.select("source", F.col("source_no").cast("int"), "weight", "source_size", F.least(limit, F.lit(top) * F.col("weight")).alias("target"))


class Mix:
    """A drawn mix. ``targets``: of each source; ``pieces``: parts of documents in blocks;
    ``turns``: how often each block is taken; ``slots``: shard, source, slot, turn, block.

    ``sized`` is a written table ``(doc_id, source, size[, row])``."""

    def __init__(self, sized: DataFrame, scratch: Scratch, block: int = BLOCK_WORDS, shard: int = SHARD_SLOTS):
        self.sized, self.scratch = sized, scratch
        buckets = F.greatest(F.lit(1), F.ceil(F.col("source_size") / F.lit(BUCKET_WORDS))).cast("long")
        self.targets = scratch.save(source_targets(sized, scratch).withColumn("buckets", buckets), "targets")
        keyed = sized.join(small(self.targets).select("source", "source_no", "buckets"), sized["source"].eqNullSafe(self.targets["source"])).drop(self.targets["source"])
        worded = self._spread(keyed.where("size > 0")).withColumn("hash", hash48("doc_id", "deal")).withColumn("bucket", F.col("hash") % F.col("buckets"))
        packed = W.partitionBy("source_no", "bucket").orderBy("hash", "doc_id", "deal", "size", *[c for c in ("row",) if c in sized.columns])
        end = F.sum("size").over(packed.rowsBetween(W.unboundedPreceding, 0))
        self.placed = scratch.save(worded.withColumn("start", end - F.col("size")).drop("hash", "buckets", "deal"), "placed")
        filled = self.placed.groupBy("source_no", "bucket").agg(F.ceil(F.sum("size") / F.lit(block)).cast("long").alias("n"))
        filled = scratch.save(running(filled, ["source_no", "bucket"], {"ahead": F.col("n")}, scratch), "filled")
        counts = filled.groupBy("source_no").agg(F.sum("n").alias("blocks"), F.min("ahead").alias("first"))
        bases = filled.join(counts, "source_no").select("source_no", "bucket", (F.col("ahead") - F.col("first")).alias("base"))
        # the few rows of buckets may be broadcast, those of documents never, however small their file is
        bases = bases.hint("broadcast" if filled.count() <= BROADCAST_ROWS else "merge")
        share = F.least(F.round(F.col("target") / F.col("source_size") * F.col("blocks")).cast("long"), MOST_TURNS * F.col("blocks"))
        quotas = self.targets.join(counts, "source_no").select("source_no", "blocks", share.alias("quota"))
        self.quotas = scratch.save(running(quotas, ["source_no"], {"lo": F.col("quota")}, scratch).withColumn("hi", F.col("lo") + F.col("quota")), "quotas")
        self.slots = self._draw(sized.sparkSession, shard)
        first, last = F.floor(F.col("start") / block), F.floor((F.col("start") + F.col("size") - 1) / block)
        spread = self.placed.join(bases, ["source_no", "bucket"]).withColumn("first", first.cast("long")).withColumn("last", last.cast("long"))
        spread = spread.withColumn("from", F.explode(F.sequence("first", "last", F.lit(4096).cast("long"))))
        spread = spread.withColumn("local", F.explode(F.sequence("from", F.least(F.col("from") + 4095, F.col("last")))))
        begin = F.greatest(F.col("start"), F.col("local") * block)
        until = F.least(F.col("start") + F.col("size"), (F.col("local") + 1) * block)
        self.pieces = spread.select(
            *self.placed.columns, (F.col("base") + F.col("local")).alias("index"),
            (begin - F.col("start")).alias("word_from"), (until - begin).alias("words"),
        )
        # slots grow out of a few short runs, by which Spark would take their blocks for a table to broadcast
        self.turns = self.slots.groupBy("source_no", "index").agg(F.count("*").alias("turns")).hint("merge")

    def _spread(self, keyed: DataFrame) -> DataFrame:
        """Rows with a number ``deal`` that parts those of a doc_id with very many rows; 0 for others."""
        counts = self.sized.groupBy("doc_id").count().where(F.col("count") > SAME_ID_ROWS)
        hot = self.scratch.save(counts.select(F.col("doc_id").alias("hot"), F.ceil(F.col("count") / SAME_ID_ROWS).cast("long").alias("parts")), "hot")
        none = F.lit(0).cast("long")
        if hot.isEmpty():
            return keyed.withColumn("deal", none)
        part = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.col("parts"))
        numbered = keyed.join(small(hot), keyed["doc_id"].eqNullSafe(hot["hot"]), "left")
        return numbered.withColumn("deal", F.coalesce(part, none)).drop("hot", "parts")

    def _draw(self, spark, shard: int) -> DataFrame:
        total = self.quotas.agg(F.sum("quota")).first()[0] or 0
        width = max(1, -(-total // CELLS))
        cells = self.quotas.where("quota > 0").withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
        ticket = permuted(F.col("id"), F.lit(max(total, 1)).cast("long"), hash48(F.lit("draw")))
        drawn = spark.range(total).select(F.floor(F.col("id") / shard).alias("shard"), ticket.alias("ticket"))
        drawn = drawn.withColumn("cell", F.floor(F.col("ticket") / width))
        hits = drawn.join(cells, "cell").where("ticket >= lo and ticket < hi").groupBy("source_no", "shard").agg(F.count("*").alias("n"))
        runs = running(hits, ["source_no", "shard"], {"ahead": F.col("n")}, self.scratch).join(self.quotas.select("source_no", "lo", "blocks"), "source_no")
        # source ranges of tickets follow one another, so what lies ahead of a source is its lo
        runs = runs.withColumn("at", F.col("ahead") - F.col("lo"))
        # runs are cut by turn, so that a turn's key is made once, and dealt out before they grow
        first, last = F.floor(F.col("at") / F.col("blocks")).cast("long"), F.floor((F.col("at") + F.col("n") - 1) / F.col("blocks")).cast("long")
        turns = runs.withColumn("turn", F.explode(F.sequence(first, last))).withColumn("key", hash48(F.lit("turn"), F.col("source_no"), F.col("turn")))
        begin = F.greatest(F.col("at"), F.col("turn") * F.col("blocks"))
        until = F.least(F.col("at") + F.col("n"), (F.col("turn") + 1) * F.col("blocks")) - 1
        dealt = turns.withColumn("begin", begin).withColumn("until", until).repartition(max(1, min(8192, total >> 17)), "shard", "source_no", "turn")
        slots = dealt.select("shard", "source_no", "blocks", "turn", "key", F.explode(F.sequence("begin", "until")).alias("slot"))
        return slots.select("shard", "source_no", "slot", "turn", permuted(F.col("slot") % F.col("blocks"), F.col("blocks"), F.col("key")).alias("index"))

    def taken(self) -> DataFrame:
        """Words taken of each row that has words."""
        return self.pieces.join(self.turns, ["source_no", "index"]).groupBy(*self.placed.columns).agg(F.sum(F.col("words") * F.col("turns")).alias("taken"))


def sized_documents(docs: DataFrame, *extra: Column) -> DataFrame:
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", size.alias("size"), *extra)


def mix_report(docs: DataFrame, scratch: Scratch | None = None, block: int = BLOCK_WORDS) -> DataFrame:
    """``(doc_id, size, source_size, target, taken)``, one row per input row.

    A null text has size 0, a null source is a source of its own, repeated rows are mixed each
    for itself, sources without words have target 0; an empty table gives an empty result.
    Extra columns are ignored.
    """
    scratch = scratch or Scratch(docs.sparkSession, "mixing")
    sized = scratch.save(sized_documents(docs), "sized")
    mix = Mix(sized, scratch, block)
    targets = small(mix.targets)
    none = sized.where("size = 0").join(targets.select("source", "source_no"), sized["source"].eqNullSafe(mix.targets["source"])).select("doc_id", "size", "source_no", F.lit(0).cast("long").alias("taken"))
    rows = mix.placed.join(mix.taken().select("source_no", "bucket", "start", "taken"), ["source_no", "bucket", "start"], "left").select("doc_id", "size", "source_no", F.coalesce("taken", F.lit(0).cast("long")).alias("taken"))
    return rows.unionByName(none).join(targets.select("source_no", "source_size", "target"), "source_no").select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, scratch: Scratch | None = None, block: int = BLOCK_WORDS) -> DataFrame:
    """The mix itself, with the columns of ``docs``: a row for each document and turn, with the
    words that the turn took. A text that a turn takes whole is left as it is; of the others
    the words are joined by single spaces. ``n_chars``, where there is one, follows the text.
    """
    scratch = scratch or Scratch(docs.sparkSession, "mixed")
    # the documents travel as one struct, so that no column of theirs meets a helper's name
    rows = scratch.save(docs.select(F.struct(*docs.columns).alias("doc"), F.monotonically_increasing_id().alias("row")), "rows", "zstd")
    mix = Mix(scratch.save(sized_documents(rows.select("doc.doc_id", "doc.text", "doc.source", "row"), F.col("row")), "sized"), scratch, block)
    taken = mix.pieces.join(mix.turns, ["source_no", "index"])
    each = taken.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("turns").cast("int"))))
    spans = (
        each.groupBy("row", "copy", "size")
        .agg(F.sum("words").alias("got"), F.sort_array(F.collect_list(F.struct("word_from", "words"))).alias("spans"))
        .select("row", (F.col("got") == F.col("size")).alias("whole"), "spans")
    )
    words = F.when(~F.col("whole"), F.regexp_extract_all("doc.text", F.lit(WORD), F.lit(0)))
    joined = spans.hint("merge").join(rows, "row").withColumn("list", words)
    cut = F.array_join(F.flatten(F.transform("spans", lambda s: F.slice(F.col("list"), (s["word_from"] + 1).cast("int"), s["words"].cast("int")))), " ")
    out = joined.withColumn("words", F.when(F.col("whole"), F.col("doc.text")).otherwise(cut))
    values = {c: F.col(f"doc.`{c}`") for c in docs.columns}
    values["text"] = F.col("words")
    if "n_chars" in docs.columns:
        values["n_chars"] = F.length("words").cast(dict(docs.dtypes)["n_chars"])
    return out.select(*[v.alias(c) for c, v in values.items()])


def _permuted_sql(x: str, n: str, key: str) -> str:
    """``permuted`` over columns of a subquery, step by step."""
    return f"""
    select *, (y2 * (case when n % {MULTIPLIERS[1]} = 0 then {MULTIPLIERS[0]} else {MULTIPLIERS[1]} end) + (key // 4096) % n) % n as place from (
      select *, case when y <= low then xor((xor(y, y >> half) * 668265 + key % 1000003) & low, ((xor(y, y >> half) * 668265 + key % 1000003) & low) >> half) else y end as y2 from (
        select *, ({x} * (case when n % {MULTIPLIERS[0]} = 0 then {MULTIPLIERS[1]} else {MULTIPLIERS[0]} end) + key % n) % n as y,
               (1::bigint << (length(bin(n)) - 1)::bigint) - 1 as low, greatest(length(bin(n)) // 2, 1)::bigint as half
        from (select *, {n} as n, {key} as key from slots)))"""


def _hash_sql(text: str) -> str:
    return f"('0x' || substr(md5('{SEED}|' || {text}), 1, 12))::bigint"


#: ``mix_report`` of documents in SQL, where no doc_id has more than SAME_ID_ROWS rows. How the slots
#: of a source fall into shards does not change how often each is taken, so shards are left out.
MIX_REPORT_SQL = rf"""
with sized as (
  select row_number() over () as r, doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}'))::bigint as size from documents
),
per as (
  select *, (source_no % 3 + 1)::double as weight, source_size / (source_no % 3 + 1)::double as ratio, {MOST_TURNS}.0::double * source_size as most
  from (select source, sum(size)::bigint as source_size, row_number() over (order by source nulls last) - 1 as source_no from sized group by source)
),
levels as (
  select *, (sum(source_size) over () - (sum(most) over along - most)) / (sum(weight) over () - (sum(weight) over along - weight)) as level
  from per window along as (order by ratio, source_no rows unbounded preceding)
),
targets as (
  select source, source_no, source_size, greatest(1, ceil(source_size / {BUCKET_WORDS}))::bigint as buckets,
         least(most, coalesce((select arg_min(level, (ratio, source_no)) from levels where level * weight <= most), 0.0) * weight) as target
  from per
),
worded as (
  select s.r, s.doc_id, s.size, t.source_no, {_hash_sql("coalesce(s.doc_id::varchar, '-') || '|0'")} as hash, t.buckets
  from sized s join targets t on s.source is not distinct from t.source where s.size > 0
),
placed as (
  select *, (sum(size) over (partition by source_no, bucket order by hash, doc_id, size, r rows unbounded preceding) - size)::bigint as start
  from (select *, hash % buckets as bucket from worded)
),
filled as (select source_no, bucket, ceil(sum(size) / {BLOCK_WORDS})::bigint as n from placed group by all),
bases as (select *, (sum(n) over (partition by source_no order by bucket rows unbounded preceding) - n)::bigint as base from filled),
counts as (select source_no, sum(n)::bigint as blocks from filled group by source_no),
quotas as (select source_no, blocks, least(round(target / source_size * blocks)::bigint, {MOST_TURNS} * blocks) as quota from targets join counts using (source_no)),
slots as (
  select source_no, blocks, slot % blocks as x, {_hash_sql("'turn|' || source_no || '|' || (slot // blocks)")} as k
  from (select source_no, blocks, unnest(range(quota)) as slot from quotas)
),
turns as (select source_no, place as index, count(*) as turns from ({_permuted_sql("x", "blocks", "k")}) group by all),
pieces as (
  select r, source_no, base + local as index, least(start + size, (local + 1) * {BLOCK_WORDS}) - greatest(start, local * {BLOCK_WORDS}) as words
  from (select p.*, b.base, unnest(range(start // {BLOCK_WORDS}, (start + size - 1) // {BLOCK_WORDS} + 1)) as local from placed p join bases b using (source_no, bucket))
),
taken as (select r, sum(words * turns)::bigint as taken from pieces join turns using (source_no, index) group by r)
select s.doc_id, s.size, t.source_size, t.target, coalesce(k.taken, 0)::bigint as taken
from sized s join targets t on s.source is not distinct from t.source left join taken k using (r)"""
