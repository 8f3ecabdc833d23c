"""The registered queries in SQL (DuckDB), from the definitions of the graphs up."""

from __future__ import annotations

RIGHT = 1_000_000_000
STEPS = 1_000_000
#: Windows of streams that have closed end before this moment.
SEEN = "(select max(ts) - interval 1 hour from events)"
STAMP = "%Y-%m-%d %H:%M:%S"


def h48(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 12))::bigint"


def simple(rows: str, combine: str = "sum", where: str = "w > 0") -> str:
    """Canonical edges of rows (u, v, w)."""
    return f"select * from (select least(u, v) as u, greatest(u, v) as v, {combine}(w)::bigint as w from ({rows}) where u is not null and v is not null and w is not null and u <> v group by all) where {where}"


CENTS = "cast(round({} * 100) as bigint)"
LINES = "(select l.*, o.o_custkey from lineitem l join orders o on o.o_orderkey = l.l_orderkey)"

HOST = "regexp_extract(url, '^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)', 1)"

GRAPHS = {
    "part_supp": simple(f"select l_partkey as u, l_suppkey + {RIGHT} as v, {CENTS.format('l_extendedprice')} * (100 - {CENTS.format('l_discount')}) as w from lineitem"),
    "order_part": simple(f"select l_orderkey as u, l_partkey + {RIGHT} as v, cast(l_quantity as bigint) as w from lineitem"),
    "cust_supp": simple(f"select o_custkey as u, l_suppkey + {RIGHT} as v, {CENTS.format('l_extendedprice')} as w from {LINES}"),
    "cust_part": simple(f"select o_custkey as u, l_partkey + {RIGHT} as v, cast(l_quantity as bigint) as w from {LINES}"),
    "copurchase": "select a.l_partkey as u, b.l_partkey as v, count(*) as w from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey group by all",
    "nation_region": simple(f"select n_nationkey as u, n_regionkey + {RIGHT} as v, 1 as w from nation"),
    "customer_nation": simple(f"select c_custkey as u, c_nationkey + {RIGHT} as v, {CENTS.format('c_acctbal')} as w from customer"),
    "conversation_turn": simple(f"select conv_id as u, turn + {RIGHT} as v, length(text) as w from conversations"),
    "page_host": simple(f"select page_id as u, {h48(HOST)} + {RIGHT} as v, length(html) as w from pages"),
    "event_succ": simple(f"select user_id as u, lead(user_id) over (order by ts, event_id) as v, {CENTS.format('value')} as w from events", where="true"),
    "rising_path": "select range as u, range + 1 as v, range + 1 as w from range((select count(*) - 1 from orders))",
    "rising_path_200": "select range as u, range + 1 as v, range + 1 as w from range(199)",
    "random_alpha_4": f"""
        select u, v, {h48("'w|' || u || '|' || v")} % {STEPS} + 1 as w from (
          select distinct least(a, b) as u, greatest(a, b) as v from (
            select a, {h48("'end|' || a || '|' || k")} % n as b
            from (select p_partkey as a, n from (select (1 << floor(log2(count(*)))::int)::bigint as n from part), part where p_partkey < n),
                 (select unnest([1, 2, 3, 4]) as k))
          where a <> b)""",
    "gram": f"""
        select a.vec_id as u, b.vec_id as v, floor(abs(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: z[1]::double * z[2]::double))) * {STEPS})::bigint as w
        from embeddings a join embeddings b on a.vec_id < b.vec_id
        where floor(abs(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: z[1]::double * z[2]::double))) * {STEPS})::bigint >= 200000""",
    "doc_near": """
        select a.doc_id as u, b.doc_id as v, 21 - abs(a.n_chars - b.n_chars) as w
        from documents a join documents b on a.lang = b.lang and a.source = b.source and a.doc_id < b.doc_id and abs(a.n_chars - b.n_chars) <= 20""",
    "delaunay2d": f"""
        with p as (select min(vec_id) as id, x, y from (select vec_id, floor(embedding[1]::double * {STEPS})::bigint as x, floor(embedding[2]::double * {STEPS})::bigint as y from embeddings) group by x, y),
        sides as (
          select a.id as u, b.id as v, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) as w,
                 (b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) as turned, (a.x - c.x) * (b.x - c.x) + (a.y - c.y) * (b.y - c.y) as dot
          from p a join p b on a.id < b.id join p c on c.id <> a.id and c.id <> b.id)
        select u, v, any_value(w) as w from sides group by u, v
        having coalesce(min(dot / turned) filter (turned > 0), 1e300) + coalesce(min(-dot / turned) filter (turned < 0), 1e300) >= 0
           and coalesce(bool_and(dot >= 0) filter (turned = 0), true)""",
}
GRAPHS["random_alpha"] = GRAPHS["random_alpha_4"]
for _alpha in (16, 64):
    GRAPHS[f"random_alpha_{_alpha}"] = GRAPHS["random_alpha_4"].replace("(select unnest([1, 2, 3, 4]) as k)", f"(select unnest(range(1, {_alpha + 1})) as k)")
_WORDS = r"list_filter(regexp_split_to_array(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '')"
GRAPHS["doc_jaccard"] = f"""
    with d as (select doc_id, {_WORDS} as words from documents where doc_id is not null and text is not null),
    s as (select distinct doc_id, array_to_string(words[i : i + 4], ' ') as item from (select doc_id, words, unnest(range(1, greatest(len(words) - 4, 1) + 1)) as i from d where len(words) > 0)),
    n as (select doc_id, count(*) as n from s group by doc_id),
    c as (select a.doc_id as u, b.doc_id as v, count(*) as shared from s a join s b on a.item = b.item and a.doc_id < b.doc_id group by all)
    select u, v, floor(shared * {STEPS} / (a.n + b.n - shared))::bigint as w
    from c join n a on a.doc_id = u join n b on b.doc_id = v where shared >= 0.8 * (a.n + b.n - shared) - 1e-9"""
DAYS = f"""
    select day, least(u, v) as u, greatest(u, v) as v, sum(w)::bigint as w from (
      select strftime(ts, '%Y-%m-%d') as day, user_id as u, lead(user_id) over (partition by date_trunc('day', ts) order by ts, event_id) as v, {CENTS.format("value")} as w from events)
    where v is not null and u <> v group by all"""

EVENT_POINTS = f"""
    select event_id as id, floor((epoch_us(ts) - t0) * {STEPS} / t1)::bigint as x, floor(({CENTS.format("value")} - c0) * {STEPS} / c1)::bigint as y
    from events, (select min(epoch_us(ts)) as t0, greatest(max(epoch_us(ts)) - min(epoch_us(ts)), 1)::double as t1,
                         min({CENTS.format("value")}) as c0, greatest(max({CENTS.format("value")}) - min({CENTS.format("value")}), 1)::double as c1 from events)"""
_RADIUS = f"(select floor(0.55 * sqrt(ln(greatest(count(*), 2)) / greatest(count(*), 2)) * {STEPS})::bigint as r from events)"
GRAPHS["rgg_events"] = f"""
    with p as ({EVENT_POINTS}), q as (select p.*, r, x // r as cx, y // r as cy from p, {_RADIUS})
    select least(a.id, b.id) as u, greatest(a.id, b.id) as v, greatest((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y), 1) as w
    from (select q.*, unnest([cx - 1, cx, cx + 1]) as lx from q) a0
    join lateral (select unnest([a0.cy - 1, a0.cy, a0.cy + 1]) as ly) l on true
    join q b on b.cx = a0.lx and b.cy = l.ly and a0.id < b.id
    join q a on a.id = a0.id
    where (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) < a.r * a.r"""


FALLING = "w desc, md5('42|' || u || '|' || v), u, v"


def ordered(edges: str, order: str = FALLING) -> str:
    """Edges with r, their place in falling order."""
    return f"select u, v, w, row_number() over (order by {order}) as r from ({edges})"


def matched(edges: str, out: str = "select u, v, w, phase from matching", more: str = "", order: str = FALLING) -> str:
    """A statement over ``ranked`` and ``matching`` of a graph."""
    return f"""
with recursive ranked as materialized ({ordered(edges, order)}),
steps(phase, u, v, r, hit) as (
  select 0, u, v, r, false from ranked
  union all
  (with live as (select phase, u, v, r from steps where not hit),
   top as (select x, min(r) as r from (select u as x, r from live union all select v, r from live) group by x),
   won as (select l.r, l.u, l.v from live l join top a on a.x = l.u and a.r = l.r join top b on b.x = l.v and b.r = l.r),
   used as (select u as x from won union all select v from won)
   select l.phase + 1, l.u, l.v, l.r, w.r is not null
   from live l left join won w on w.r = l.r
   where w.r is not null or not exists (select 1 from used where x = l.u) and not exists (select 1 from used where x = l.v))
),
matching as (select s.u, s.v, k.w, s.r, s.phase from steps s join ranked k on k.r = s.r where s.hit){more}
{out}"""


def matched_by_day(edges: str) -> str:
    return f"""
with recursive ranked as materialized (select day, u, v, w, row_number() over (order by w desc, md5('42|' || u || '|' || v), u, v, day) as r from ({edges})),
steps(phase, day, u, v, r, hit) as (
  select 0, day, u, v, r, false from ranked
  union all
  (with live as (select phase, day, u, v, r from steps where not hit),
   top as (select day, x, min(r) as r from (select day, u as x, r from live union all select day, v, r from live) group by day, x),
   won as (select l.* from live l join top a on a.day = l.day and a.x = l.u and a.r = l.r join top b on b.day = l.day and b.x = l.v and b.r = l.r),
   used as (select day, u as x from won union all select day, v from won)
   select l.phase + 1, l.day, l.u, l.v, l.r, w.r is not null
   from live l left join won w on w.r = l.r
   where w.r is not null or not exists (select 1 from used n where n.day = l.day and n.x = l.u) and not exists (select 1 from used n where n.day = l.day and n.x = l.v))
)
select s.day, s.u, s.v, k.w, s.phase from steps s join ranked k on k.r = s.r where s.hit"""


def unit_renewed(edges: str) -> str:
    key = "('0x' || substr(md5('42|' || (phase + 1) || '|' || u || '|' || v), 1, 12))::bigint"
    return f"""
with recursive e as materialized ({edges}),
steps(phase, u, v, hit) as (
  select 0, u, v, false from e
  union all
  (with live as (select phase, u, v, {key} as k from steps where not hit),
   top as (select x, max(k) as k from (select u as x, k from live union all select v, k from live) group by x),
   won as (select l.u, l.v from live l join top a on a.x = l.u and a.k = l.k join top b on b.x = l.v and b.k = l.k),
   used as (select u as x from won union all select v from won)
   select l.phase + 1, l.u, l.v, w.u is not null
   from live l left join won w on w.u = l.u and w.v = l.v
   where w.u is not null or not exists (select 1 from used where x = l.u) and not exists (select 1 from used where x = l.v))
)
select u, v, phase from steps where hit"""


def red_blue(edges: str) -> str:
    coin = lambda x: f"('0x' || substr(md5('42|' || (phase + 1) || '|' || {x}), 1, 12))::bigint < 140737488355328"
    return f"""
with recursive ranked as materialized ({ordered(edges)}),
steps(phase, u, v, r, hit) as (
  select 0, u, v, r, false from ranked
  union all
  (with live as (select phase, u, v, r, {coin("u")} as bu, {coin("v")} as bv from steps where not hit and phase < 400),
   asked as (select x, min(r) as r, min_by(y, r) as y from (select u as x, v as y, r from live where bu and not bv union all select v, u, r from live where bv and not bu) group by x),
   won as (select y, min(r) as r from asked group by y),
   taken as (select l.r, l.u, l.v from live l join won on won.r = l.r),
   used as (select u as x from taken union all select v from taken)
   select l.phase + 1, l.u, l.v, l.r, t.r is not null
   from live l left join taken t on t.r = l.r
   where t.r is not null or not exists (select 1 from used where x = l.u) and not exists (select 1 from used where x = l.v))
)
select s.u, s.v, k.w, s.phase from steps s join ranked k on k.r = s.r where s.hit"""


def random_proposal(edges: str) -> str:
    coin = lambda seed, k, x: f"('0x' || substr(md5({seed} || '|' || {k} || '|' || {x} || '|' || u || '|' || v), 1, 12))::bigint"
    return f"""
with recursive ranked as materialized ({ordered(edges)}),
steps(phase, u, v, r, hit) as (
  select 0, u, v, r, false from ranked
  union all
  (with live as (select phase, u, v, r from steps where not hit and phase < 400),
   cells as (select phase, u as x, v as y, u, v, r from live union all select phase, v, u, u, v, r from live),
   draw as (select x, y, u, v, r, phase from cells qualify row_number() over (partition by x order by {coin("'42'", "(phase + 1)", "x")}, u, v) = 1),
   kept as (select r from draw qualify row_number() over (partition by y order by {coin("'-42'", "(phase + 1)", "y")}, u, v) = 1),
   last as (select x, r from cells where r in (select r from kept) qualify row_number() over (partition by x order by {coin("'42'", "(-phase - 1)", "x")}, u, v) = 1),
   won as (select r from last group by r having count(*) = 2),
   taken as (select l.* from live l where r in (select r from won)),
   used as (select u as x from taken union all select v from taken)
   select l.phase + 1, l.u, l.v, l.r, t.r is not null
   from live l left join taken t on t.r = l.r
   where t.r is not null or not exists (select 1 from used where x = l.u) and not exists (select 1 from used where x = l.v))
)
select s.u, s.v, k.w, s.phase from steps s join ranked k on k.r = s.r where s.hit"""


def heavy_edge(edges: str, rank: str = "x") -> str:
    """Vertices one after the other: place k of the order decides in step k."""
    return f"""
with recursive ranked as materialized ({ordered(edges)}),
ends as materialized (select u as x, v as y, r from ranked union all select v, u, r from ranked),
turns as materialized (select x, row_number() over (order by {rank}, x) as k from (select distinct x from ends)),
steps(k, used, picked) as (
  select 0::bigint, []::bigint[], []::bigint[]
  union all
  select s.k + 1,
         case when b.r is null then s.used else list_append(list_append(s.used, t.x), b.y) end,
         case when b.r is null then s.picked else list_append(s.picked, b.r) end
  from steps s join turns t on t.k = s.k + 1
  left join lateral (select min(r) as r, min_by(y, r) as y from ends e where e.x = t.x and not list_contains(s.used, t.x) and not list_contains(s.used, e.y)) b on true
)
select u, v, w from ranked where r in (select unnest(picked) from (select picked from steps order by k desc limit 1))"""


DEGREES = "degrees as (select x, count(*) as d from (select u as x from ranked union all select v from ranked) group by x)"

OWNERS = "own as (select x, (row_number() over (order by x) - 1) * 8 // count(*) over () as o from (select u as x from ranked union select v from ranked))"
LOG = "log as (select phase + 1 as phase, count(*) as live from steps where not hit group by phase)"
KNN = f"""
    with e as ({GRAPHS["rgg_events"]}),
    ends as (select u as x, v as y, w from e union all select v, u, w from e)
    select distinct least(x, y) as u, greatest(x, y) as v, w from (select *, row_number() over (partition by x order by w, y) as k from ends) where k <= 4"""

#: Users and event types of closed days, as a graph for each day.
TYPED_DAYS = f"""
    select strftime(day, '{STAMP}') as day, user_id as u, {h48("event_type")} + {RIGHT} as v, cents as w
    from (select date_trunc('day', ts) as day, user_id, event_type, sum(cast(round(value * 100) as bigint))::bigint as cents from events group by all)
    where cents > 0 and day + interval 1 day <= {SEEN}"""


def levels_above(size: str, start: int, fan: int) -> str:
    return " + ".join(f"({size} > {start * fan ** k})::int" for k in range(4))


#: A cell's twin is the other cell of its edge, next to it when cells lie by edge.
TWINS = """
    select pos, vertex, other, coalesce(lag(pos) over pair, lead(pos) over pair) as twin_pos
    from cells window pair as (partition by r order by vertex)"""
