"""DuckDB SQL for the queries of ``catalog``, built from the raw tables."""

from __future__ import annotations

from geoherald.sources.workload import LIFE

CELL = 65536
N = 64
#: Numbers of the timed workload in the catalog.
MU = 1000


def _text(column: str) -> str:
    return rf"coalesce(list_filter(regexp_split_to_array(lower({column}), '[^\p{{L}}]+'), lambda x: length(x) > 1), [])"


def _slice(a: str, start: str, n: str) -> str:
    return f"list_slice({a}, {start}, {start} + {n} - 1)"


def _set(a: str) -> str:
    return f"list_sort(list_distinct({a}))"


def objects(world: str = "wide") -> str:
    """CTE ``obj``."""
    if world == "wide":
        spread = lambda centre, prime: f"greatest(0, least(4194303, {centre} + (cents * 16 * ((event_id * {prime}) % 2001)) // 2000 - cents * 8))::bigint"
        return f"""
toks as (select doc_id, {_text("text")} as t from documents),
ev as (
  select event_id, ts, round(value * 100)::bigint as cents, c_nationkey as nk, n_regionkey as rk, t
  from events join customer on c_custkey = user_id join nation on c_nationkey = n_nationkey
  join toks on doc_id = (event_id * 7919) % (select count(*) from documents)),
obj as (
  select event_id as obj_id, ts, {spread("rk * 838860 + 419430", 104729)} as x, {spread("(nk // 5) * 838860 + 419430", 1299709)} as y,
    {_set(_slice("t", "(1 + (event_id * 31) % greatest(len(t) - 11, 1))", "12"))} as terms from ev)"""
    place = lambda e, prime: f"greatest(0, least(1048575, floor(({e} + 0.5) * 1048576)::bigint + ((doc_id // nv) * {prime}) % 4096))::bigint"
    return f"""
vec as (select vec_id, embedding[1]::double as e1, embedding[2]::double as e2, count(*) over () as nv from embeddings),
obj as (
  select doc_id as obj_id, {place("e1", 7919)} as x, {place("e2", 104729)} as y, {_set(_text("text"))} as terms
  from documents join vec on doc_id % nv = vec_id)"""


LEXICON = """
lex0 as (select term, count(*) as df from (select unnest(terms) as term from obj) group by term),
lex as (select term, df, row_number() over (order by df desc, term) as rk from lex0)"""


def subs(group: str, world: str = "wide", all_rare: bool = False, flips: str = "0") -> str:
    """CTE ``subs``, after ``obj`` and ``lex``."""
    step = 419431 if world == "wide" else 104858
    style = {"Q1": "false", "Q2": "true"}.get(group, f"(rx + ry + {flips}) % 2 = 1")
    words2 = _set("list_concat([rare], list_slice(k1, 2, 3))")
    rare_filter = "list_filter(w2, lambda t: not list_contains(common, t))" if all_rare else "w2"
    common = "(select coalesce(list(term), []) from lex where rk * 100 <= (select count(*) from lex))" if all_rare else "[]::varchar[]"
    return f"""
least_term as (
  select obj_id as kw, term as rare, rk as rare_rk from (
    select obj_id, term, rk, row_number() over (partition by obj_id order by df, term) as r
    from (select obj_id, unnest(terms) as term from obj) join lex using (term)) where r = 1),
pick as (
  select o_orderkey as q, o_custkey as owner, a.x as cx, a.y as cy, k.terms as kt, k.obj_id as kw,
    least(9, a.x // {step}) as rx, least(9, a.y // {step}) as ry
  from orders join obj a on a.obj_id = (o_orderkey * 48271) % (select count(*) from obj)
  join obj k on k.obj_id = (o_orderkey * 16807 + 11) % (select count(*) from obj) where len(k.terms) > 0),
styled as (
  select *, 10 * ry + rx as g, {_slice("kt", "(1 + q % greatest(len(kt) - 2, 1))", "(1 + q % 3)")} as k1 from pick),
drawn as (
  select s.*, {style} as two, rare, rare_rk from styled s join least_term using (kw)),
worded as (
  select *, {words2} as w2, {common} as common from drawn where not two or rare_rk * 100 > (select count(*) from lex)),
kept as (select *, case when two then {rare_filter} else k1 end as words, (1000 + (q * 69621) % (case when two then 99001 else 49001 end)) // 2 as half from worded),
subs as (
  select q as sub_id, owner, cx - half as x0, cx + half as x1, cy - half as y0, cy + half as y1,
    case when (q // 3) % 3 = 1 then list_sort(list_transform(words, lambda w: [w]))
      when (q // 3) % 3 = 2 and len(words) >= 3 then [list_sort(list_slice(words, 1, 2)), list_slice(words, 3, 3)]
      else [{_set("words")}] end as dnf
  from kept where len(words) > 0)"""


PAIRS = """
clause as (select sub_id, generate_subscripts(dnf, 1) as c, unnest(dnf) as words from subs),
wanted as (select sub_id, c, len(words) as need, unnest(words) as term from clause),
has as (select obj_id, x, y, unnest(terms) as term from obj),
hit as (
  select w.sub_id, h.obj_id from wanted w join has h using (term) join subs s on s.sub_id = w.sub_id
  where h.x between s.x0 and s.x1 and h.y between s.y0 and s.y1
  group by w.sub_id, w.c, w.need, h.obj_id having count(*) = w.need),
pairs as (select distinct sub_id, obj_id from hit)"""


def base(group: str = "Q1", world: str = "wide", **kw) -> str:
    return f"with {objects(world)}, {LEXICON}, {subs(group, world, **kw)}"


def match(group: str, world: str = "wide", **kw) -> str:
    return f"{base(group, world, **kw)}, {PAIRS} select sub_id, obj_id from pairs"


def timed() -> str:
    """CTEs ``tsubs`` and ``tobj`` with places in the stream, after ``subs``."""
    s = " + ".join(f"((r * {m} + {i * 97 + 13}) * {m % 9973 + 1}) % 10007" for i, m in enumerate(LIFE))
    return f"""
numbered as (select *, row_number() over (order by sub_id) - 1 as r from subs),
lived as (select *, greatest(1, ({MU} * greatest({s} - 10001, 0)) // 50035) as life from numbered),
tobj as (select *, 12 * ((row_number() over (order by obj_id) - 1) // 10) + (row_number() over (order by obj_id) - 1) % 10 as seq from obj),
tsubs as (
  select * exclude (r, life), case when r < {MU} then r - {MU} else 12 * (r - {MU}) + 10 end as reg_seq,
    case when r + life < {MU} then r + life - {MU} else 12 * (r + life - {MU}) + 11 end as cancel_seq
  from lived where (case when r < {MU} then r - {MU} else 12 * (r - {MU}) + 10 end) < (select max(seq) from tobj))"""


def match_timed() -> str:
    return f"""{base("Q1")}, {timed()}, {PAIRS}
select p.sub_id, p.obj_id from pairs p join tsubs s using (sub_id) join tobj o using (obj_id)
where reg_seq < seq and (cancel_seq is null or seq < cancel_seq)"""


AXIS = "least(greatest(floor({v} / 65536.0)::int, 0), 63)"
ROUTE = f"""
freq as (select term, df from lex),
route as (
  select distinct sub_id, term from (
    select sub_id, c, term, row_number() over (partition by sub_id, c order by coalesce(df, 0), term) as r
    from (select sub_id, c, unnest(words) as term from (select sub_id, generate_subscripts(dnf, 1) as c, unnest(dnf) as words from subs))
    left join freq using (term)) where r = 1),
cols as (select sub_id, unnest(range({AXIS.format(v="x0")}, {AXIS.format(v="x1")} + 1)) as cx from subs),
spots as (select sub_id, cx, unnest(range({AXIS.format(v="y0")}, {AXIS.format(v="y1")} + 1)) as cy from cols join subs using (sub_id)),
posting as (select sub_id, (cy * 64 + cx)::int as cell, term from spots join route using (sub_id)),
probe as (select obj_id, ({AXIS.format(v="y")} * 64 + {AXIS.format(v="x")})::int as cell, unnest(terms) as term from obj),
sent as (select distinct obj_id, cell from probe join (select distinct cell, term from posting) using (cell, term))"""


def routed(select: str) -> str:
    return f"{base('Q1')}, {ROUTE} {select}"


def simple() -> dict[str, str]:
    """The statistics and the operators around the methods."""
    o = objects()
    return {
        "wide_objects": f"with {o} select obj_id, x, y, terms from obj",
        "small_objects": f"with {objects('small')} select obj_id, x, y, terms from obj",
        "lexicon": f"with {o}, {LEXICON} select term, df, rk from lex",
        "top1pct_terms": f"with {o}, {LEXICON} select term, df, rk from lex where rk * 100 <= (select count(*) from lex)",
        "subs_q1": f"{base('Q1')} select * from subs",
        "subs_q2": f"{base('Q2')} select * from subs",
        "subs_q2_rare": f"{base('Q2', all_rare=True)} select * from subs",
        "subs_q3": f"{base('Q3')} select * from subs",
        "subs_small_q3": f"{base('Q3', 'small')} select * from subs",
        "subs_q3_drift": f"{base('Q3', flips=f'((q // {MU}) + (g * 7) % 10) // 10')} select * from subs",
        "tuple_mix": f"""{base('Q1')}, {timed()}
select seq, 'obj' as op, obj_id, null::bigint as sub_id from tobj union all
select reg_seq, 'reg', null, sub_id from tsubs union all
select cancel_seq, 'cancel', null, sub_id from tsubs where cancel_seq <= (select max(seq) from tobj)""",
        "live_counts": f"""{base('Q1')}, {timed()},
steps as (select reg_seq as seq, 1 as step from tsubs union all select cancel_seq, -1 from tsubs where cancel_seq <= (select max(seq) from tobj))
select seq, sum(sum(step)) over (order by seq rows unbounded preceding)::bigint as live from steps group by seq""",
        "grid_histogram": f"with {o} select ({AXIS.format(v='y')} * 64 + {AXIS.format(v='x')})::int as cell, count(*) as n from obj group by 1",
        "routed_objects": routed("select obj_id, cell from sent"),
        "dropped_objects": routed("select obj_id from obj where obj_id not in (select obj_id from sent)"),
        "postings_per_cell": routed("select cell, term, count(*) as n from posting group by all"),
        "cell_load": routed(""", stored as (select cell, count(*) as n_sub, sum(bytes)::bigint as size_bytes from (
    select distinct cell, sub_id, 48 + list_sum(list_transform(flatten(dnf), lambda t: strlen(t) + 4)) as bytes from posting join subs using (sub_id)) group by cell),
  seen as (select cell, count(*) as n_obj from sent group by cell)
select cell, coalesce(n_obj, 0)::bigint as n_obj, coalesce(n_sub, 0)::double as avg_subs, (coalesce(n_obj, 0) * coalesce(n_sub, 0))::double as load, coalesce(size_bytes, 0)::bigint as size_bytes
from stored full join seen using (cell)"""),
        "single_worker_load": routed("""select 0 as worker, n_obj, n_reg, 0::bigint as n_cancel, (n_obj * n_reg + n_obj + n_reg)::double as load
from (select count(distinct obj_id)::bigint as n_obj from sent), (select count(distinct sub_id)::bigint as n_reg from posting)"""),
        "replication": routed("""select (select count(distinct obj_id) from sent)::double / (select count(*) from obj) as sends_per_object, 1.0::double as copies_per_sub,
  ((select count(*) from obj) - (select count(distinct obj_id) from sent))::double / (select count(*) from obj) as dropped_share"""),
        "cosine_regions": f"""{base('Q1')},
ot as (select least(9, x // 419431) + 10 * least(9, y // 419431) as g, unnest(terms) as term from obj),
st as (select least(9, greatest(0, (x0 + x1) // 2) // 419431) + 10 * least(9, greatest(0, (y0 + y1) // 2) // 419431) as g, unnest(flatten(dnf)) as term from subs),
both_sides as (
  select coalesce(a.g, b.g) as g, coalesce(n, 0) as n, coalesce(m, 0) as m from (select g, term, count(*) as n from ot group by all) a
  full join (select g, term, count(*) as m from st group by all) b on a.g = b.g and a.term = b.term)
select g::bigint as g, round(case when sum(n * n) > 0 and sum(m * m) > 0 then sum(n * m) / (sqrt(sum(n * n)) * sqrt(sum(m * m))) else 0 end, 6) as sim from both_sides group by g""",
        "dispatcher_sends": routed("""select (obj_id % 4)::int as dispatcher, count(*) as n_obj, count(*) filter (obj_id in (select obj_id from sent))::bigint as sends from obj group by 1"""),
        "routing_cell_maps": routed("select cell, count(distinct term) as n_terms, count(*) as n_live from posting group by cell"),
        "owner_deliveries": f"{base('Q1')}, {PAIRS} select to_json({{'owner': owner, 'sub_id': sub_id, 'obj_id': obj_id}})::varchar as delivery from pairs join subs using (sub_id)",
        "routed_cancels": f"{base('Q1')}, {timed()}, {ROUTE} select sub_id, cell, term from posting join tsubs using (sub_id) where cancel_seq <= (select max(seq) from tobj)",
        "averaged_cell_subs": f"""{base('Q1')}, {timed()}, {ROUTE}, ends as (select max(seq) as e from tobj),
spans as (select distinct cell, sub_id, greatest(least(coalesce(cancel_seq, e), e) - greatest(reg_seq, 0), 0) as span from posting join tsubs using (sub_id), ends)
select cell, round(sum(span) / max(e)::double * 1000)::bigint as thousandths from spans, ends group by cell""",
        "subs_small_q1": f"{base('Q1', 'small')} select * from subs",
        "subs_small_q2": f"{base('Q2', 'small')} select * from subs",
        "product_lexicon": """select term, count(*) as df from (
  select unnest(list_distinct(list_concat(string_split(lower(p_name), ' '), [lower(p_type)]))) as term
  from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join part on l_partkey = p_partkey) group by term""",
        "conversation_terms": "select conv_id * 1000 + turn as obj_id, ((conv_id * 1000 + turn) * 48271) % 1048576 as x, ((conv_id * 1000 + turn) * 69621) % 1048576 as y, " + _set(_text("text")) + " as terms from conversations",
        "load_per_window": f"with {o} select time_bucket(interval '4 hours', ts, timestamp '1970-01-01') as start, count(*) as n from obj group by 1",
        "sliding_load": f"with {o}, starts as (select obj_id, unnest(range(0, 4)) as back, ts from obj) select time_bucket(interval '1 hour', ts, timestamp '1970-01-01') - to_hours(back) as start, count(*) as n from starts group by 1",
        "session_users": """with gaps as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval '6 hours' then 0 else 1 end as fresh from events),
marked as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as s from gaps)
select user_id, min(ts) as start, count(*) as n from marked group by user_id, s""",
        "asof_registration": """with r as (select o_custkey, o_orderkey % 43200 as minute, max(o_orderkey) as o_orderkey from orders group by all),
e as (select event_id, user_id, event_id % 43200 as minute from events)
select event_id, user_id, o_orderkey from e asof left join r on e.user_id = r.o_custkey and e.minute >= r.minute""",
        "rollup_matches": f"""{base('Q1')}, {PAIRS} select n_regionkey, n_nationkey, count(*) as n, grouping(n_regionkey, n_nationkey)::bigint as level
from pairs join subs using (sub_id) join customer on owner = c_custkey join nation on c_nationkey = n_nationkey group by rollup (n_regionkey, n_nationkey)""",
        "cube_ops": f"""{base('Q1')}, {timed()}, t as (select seq, 'obj' as op from tobj union all select reg_seq, 'reg' from tsubs union all select cancel_seq, 'cancel' from tsubs where cancel_seq <= (select max(seq) from tobj))
select op, (seq % 12)::bigint as slot, count(*) as n from t group by cube (op, (seq % 12)::bigint)""",
        "ntile_tiles": f"""with {o}, c as (select cx, cy, count(*) as n from (select {AXIS.format(v='x')} as cx, {AXIS.format(v='y')} as cy from obj) group by all),
s as (select *, ntile(8) over (order by cx, cy) as slab from c)
select slab, ntile(8) over (partition by slab order by cy, cx) as tile, cx, cy, n from s""",
        "json_props": "select event_type, sum((props::json->>'$.k')::bigint)::bigint as k, count(*) as n from events group by event_type",
        "owner_top3": f"""{base('Q1')}, {PAIRS}, n as (select owner, sub_id, count(*) as n from pairs join subs using (sub_id) group by all)
select owner, sub_id, n, r from (select *, row_number() over (partition by owner order by n desc, sub_id) as r from n) where r <= 3""",
        "trailing_activity": "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 14400000000 preceding and current row) as n, epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) as gap from events",
        "pivot_types": "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view, count(*) as n from events group by user_id",
        "page_terms": r"""with plain as (select page_id, regexp_replace(regexp_replace(html, '(?s)<(script|style).*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g') as text from pages)
select page_id as obj_id, (page_id * 48271) % 1048576 as x, (page_id * 69621) % 1048576 as y, """ + _set(_text("text")) + " as terms from plain",
    }


def _cells() -> str:
    return routed(f""", stored as (select cell, count(*) as n_sub, sum(bytes)::bigint as size from (
    select distinct cell, sub_id, 48 + list_sum(list_transform(flatten(dnf), lambda t: strlen(t) + 4)) as bytes from posting join subs using (sub_id)) group by cell),
  seen as (select cell, count(*) as n_obj from sent group by cell),
  heavy as (select cell, (n_obj * n_sub)::double as load, size from stored join seen using (cell)),
  goal as (select floor(sum(load) / 3) as tau from heavy)""")


def selections() -> dict[str, str]:
    """Selectors on all cells of one worker. The exact one is out of reach for SQL; it is tested against all subsets."""
    ratio = """, nth as (select *, row_number() over (order by size / load, cell) as k from heavy),
  scan as (
    select 1 as k, 0::double as load, 0::bigint as size union all
    select s.k + 1, s.load + case when s.load + n.load < tau then n.load else 0 end, s.size + case when s.load + n.load < tau then n.size else 0 end
    from scan s join nth n on n.k = s.k, goal)"""
    return {
        "select_random": f"""{_cells()} select cell from (
  select *, coalesce(sum(load) over (order by (cell * 48271 + 7919) % 65537, cell rows between unbounded preceding and 1 preceding), 0) as before from heavy), goal where before < tau""",
        "select_ratio_greedy": (_cells() + ratio).replace("with ", "with recursive ", 1)
        + " select min(s.size + n.size)::bigint as size from scan s join nth n on n.k = s.k, goal where s.load + n.load >= tau",
        "select_largest_first": f"""{_cells()} select cell, load, size from (
  select *, coalesce(sum(load) over (order by size desc, cell rows between unbounded preceding and 1 preceding), 0) as before from heavy), goal where before < tau""",
    }
