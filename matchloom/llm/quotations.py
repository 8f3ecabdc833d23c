"""Chat formatting by quotation linking, in DataFrame operations only.

Lines that begin with ``>`` marks are quotations, the number of marks their level. A passage is a
run of lines of one level without a blank line; it is normalised (A-Z lowered, line breaks and
other white space one space, trimmed), so a quotation that was wrapped anew is still the same,
and hashed. Quoted passages meet the passages that messages of the same conversation wrote
themselves; the lines of a passage that nobody wrote as a whole meet their lines. The original
is the first message that wrote the passage or line. The parent of a message is the original of
the most quoted text at its lowest level that has one, whole passages before lines. Threads are
then read in the order of their first message, messages in the order of their turns, and
quotations are gone from the text.

Originals are a grouped minimum, so a line that is everywhere, or a conversation with a third
of all rows, costs one row per task before the shuffle and never pairs with itself.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .storage import Scratch

MARKS = r"^[ \t]*>([ \t]*>)*"
#: White space is the ASCII set.
BLANK = r"[ \t\n\x0B\f\r]+"
MOST_DOUBLINGS = 40


def normalised(line: Column) -> Column:
    low = F.translate(line, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.trim(F.regexp_replace(low, BLANK, " "))


def parse(messages: DataFrame) -> DataFrame:
    """Messages with ``content`` (own lines), ``own`` and ``quoted`` (passages as level and lines),
    and ``n_quoted`` (quoted lines). Columns ``conv_id, turn, role, text``."""
    level = lambda x: F.length(F.regexp_replace(F.regexp_extract(x, MARKS, 0), "[^>]", ""))
    cut = messages.withColumn("raw", F.split(F.coalesce("text", F.lit("")), r"\r?\n"))
    cells = F.transform("raw", lambda x: F.struct(level(x).alias("level"), normalised(F.regexp_replace(x, MARKS, "")).alias("line")))
    marked = cut.withColumn("cells", cells).withColumn("at", F.sequence(F.lit(0), F.size("raw") - 1))

    def border(i: Column, step: int) -> Column:
        here, there = F.get("cells", i), F.get("cells", i + step)
        return (here["line"] != "") & (there.isNull() | (there["line"] == "") | (there["level"] != here["level"]))

    ends = marked.withColumn("first", F.filter("at", lambda i: border(i, -1))).withColumn("last", F.filter("at", lambda i: border(i, 1)))
    run = lambda z: F.struct(F.get("cells", z["first"])["level"].alias("level"), F.transform(F.slice("cells", z["first"] + 1, z["last"] - z["first"] + 1), lambda c: c["line"]).alias("lines"))
    passages = ends.withColumn("passages", F.transform(F.arrays_zip("first", "last"), run))
    content = F.array_join(F.filter("raw", lambda x: ~x.rlike(MARKS)), "\n")
    return passages.select(
        "conv_id", "turn", "role", F.regexp_replace(content, r"^[ \t\n\x0B\f\r]+|[ \t\n\x0B\f\r]+$", "").alias("content"),
        F.filter("passages", lambda p: p["level"] == 0).alias("own"), F.filter("passages", lambda p: p["level"] > 0).alias("quoted"),
        F.size(F.filter("raw", lambda x: x.rlike(MARKS))).cast("long").alias("n_quoted"),
    )


def parents(parsed: DataFrame) -> DataFrame:
    """``(conv_id, turn, parent_turn)`` of the messages whose quotations have an original."""
    whole, line = F.array_join("p.lines", " "), F.explode("lines").alias("said")
    wrote = parsed.select("conv_id", "turn", F.explode("own").alias("p")).select("conv_id", "turn", whole.alias("said"), "p.lines")

    def originals(texts: DataFrame) -> DataFrame:
        return texts.groupBy("conv_id", F.md5("said").alias("h")).agg(F.min("turn").alias("origin"))

    def earlier(quotes: DataFrame, first: DataFrame) -> DataFrame:
        found = quotes.withColumn("h", F.md5("said")).join(first, ["conv_id", "h"], "left")
        return found.withColumn("origin", F.when(F.col("origin") < F.col("turn"), F.col("origin")))

    quotes = parsed.select("conv_id", "turn", F.explode("quoted").alias("p")).select("conv_id", "turn", "p.level", whole.alias("said"), "p.lines")
    passages = earlier(quotes, originals(wrote))
    rest = passages.where("origin is null").select("conv_id", "turn", "level", line)
    lines = earlier(rest, originals(wrote.select("conv_id", "turn", line)))
    hits = passages.withColumn("part", F.lit(0)).select("conv_id", "turn", "level", "part", "origin", "said").unionByName(lines.withColumn("part", F.lit(1)).select("conv_id", "turn", "level", "part", "origin", "said"))
    votes = hits.where("origin is not null").groupBy("conv_id", "turn", "level", "part", "origin").agg(F.sum(F.length("said")).alias("votes"))
    best = F.min(F.struct("level", "part", (-F.col("votes")).alias("votes"), (-F.col("origin")).alias("origin")))
    return votes.groupBy("conv_id", "turn").agg(best.alias("b")).select("conv_id", "turn", (-F.col("b.origin")).alias("parent_turn"))


def thread_roots(links: DataFrame, scratch: Scratch) -> DataFrame:
    """``(conv_id, turn, thread_turn)``: the first ancestor, by doubling the links."""
    state = scratch.save(links.select("conv_id", "turn", F.col("parent_turn").alias("up")), "up")
    for _ in range(MOST_DOUBLINGS):
        higher = state.select("conv_id", F.col("turn").alias("up"), F.col("up").alias("further"))
        joined = state.join(higher, ["conv_id", "up"], "left")
        if joined.where("further is not null").isEmpty():
            break
        fresh = scratch.save(joined.select("conv_id", "turn", F.coalesce("further", "up").alias("up")), "up")
        scratch.drop(state)
        state = fresh
    return state.select("conv_id", "turn", F.col("up").alias("thread_turn"))


def reply_order(messages: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """``(conv_id, turn, role, content, n_quoted, parent_turn, thread_turn)``, a row per message.

    Read in the order (conv_id, thread_turn, turn) a conversation is in reply order: parents
    come before their replies, and a conversation without quotations keeps its turns. A null
    text is empty; a null role is ``user``; messages with a null conv_id or turn are kept and
    link with nothing; rows of the same conversation and turn share parent and thread;
    quotations without an original are dropped from the text like others. Extra columns are
    ignored and an empty table gives an empty result.
    """
    scratch = scratch or Scratch(messages.sparkSession, "quotations")
    parsed = parse(messages.select("conv_id", "turn", "role", "text"))
    links = scratch.save(parents(parsed), "links")
    roots = thread_roots(links, scratch)
    threads = links.join(roots, ["conv_id", "turn"])
    return parsed.join(threads, ["conv_id", "turn"], "left").select(
        "conv_id", "turn", F.coalesce("role", F.lit("user")).alias("role"), "content", "n_quoted",
        "parent_turn", F.coalesce("thread_turn", "turn").alias("thread_turn"),
    )


def chat_lines(messages: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """``reply_order`` with ``chat``, the message as a line of a chat log, laid out so that
    conversations are contiguous and in reply order over the partitions. Ranges may cut a long
    conversation, whose parts stay in order; none is gathered into one row."""
    chat = F.concat(F.lit("<|"), "role", F.lit("|>\n"), "content", F.lit("\n"))
    keys = ["conv_id", "thread_turn", "turn"]
    return reply_order(messages, scratch).withColumn("chat", chat).repartitionByRange(*keys).sortWithinPartitions(*keys)


#: The rows of ``chat_lines`` in SQL: quotation marks and white space as above, ancestors by recursion.
REPLY_ORDER_SQL = r"""
with recursive split as (
  select row_number() over () as r, conv_id, turn, role,
         string_split_regex(coalesce(text, ''), '\r?\n') as lines
  from conversations
),
parsed as (
  select r, conv_id, turn, coalesce(role, 'user') as role,
         list_filter(lines, lambda x: not regexp_matches(x, '^[ \t]*>')) as own,
         list_filter(lines, lambda x: regexp_matches(x, '^[ \t]*>')) as quoted
  from split
),
cells as (
  select r, conv_id, turn, i, length(regexp_replace(regexp_extract(x, '^[ \t]*>([ \t]*>)*'), '[^>]', '', 'g')) as level,
         trim(regexp_replace(translate(regexp_replace(x, '^[ \t]*>([ \t]*>)*', ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \t\n\x0B\f\r]+', ' ', 'g')) as line
  from (select r, conv_id, turn, generate_subscripts(lines, 1) as i, unnest(lines) as x from split)
),
turns as (
  select *, sum(case when before is null or before = '' or level_before <> level then 1 else 0 end) over (partition by r order by i) as run
  from (select *, lag(line) over (partition by r order by i) as before, lag(level) over (partition by r order by i) as level_before from cells)
),
passages as (
  select r, conv_id, turn, level, run, string_agg(line, ' ' order by i) as said
  from turns where line <> '' group by all
),
wrote as (select conv_id, said, min(turn) as origin from passages where level = 0 group by all),
wrote_lines as (select conv_id, line as said, min(turn) as origin from cells where level = 0 and line <> '' group by all),
met as (
  select p.*, case when w.origin < p.turn then w.origin end as origin
  from passages p left join wrote w on p.conv_id = w.conv_id and p.said = w.said where level > 0
),
met_lines as (
  select t.conv_id, t.turn, t.level, w.origin, t.line as said
  from turns t join met m on t.r = m.r and t.run = m.run and m.origin is null
       join wrote_lines w on t.conv_id = w.conv_id and t.line = w.said and w.origin < t.turn
  where t.line <> ''
),
votes as (
  select conv_id, turn, level, part, origin, sum(length(said)) as votes
  from (select conv_id, turn, level, 0 as part, origin, said from met where origin is not null
        union all select conv_id, turn, level, 1, origin, said from met_lines)
  group by all
),
links as (
  select conv_id, turn, origin as parent_turn from (
    select *, row_number() over (partition by conv_id, turn order by level, part, votes desc, origin desc) as k from votes
  ) where k = 1
),
climb as (
  select conv_id, turn, parent_turn, parent_turn as up from links
  union all
  select c.conv_id, c.turn, c.parent_turn, l.parent_turn from climb c join links l on c.conv_id = l.conv_id and c.up = l.turn
),
threads as (select conv_id, turn, parent_turn, min(up) as thread_turn from climb group by all)
select *, '<|' || role || '|>' || chr(10) || content || chr(10) as chat from (
  select p.conv_id, p.turn, p.role,
         regexp_replace(array_to_string(own, chr(10)), '^[ \t\n\x0B\f\r]+|[ \t\n\x0B\f\r]+$', '', 'g') as content,
         len(quoted) as n_quoted, t.parent_turn, coalesce(t.thread_turn, p.turn) as thread_turn
  from parsed p left join threads t on p.conv_id = t.conv_id and p.turn = t.turn
)
"""
