"""DuckDB SQL with the results of the queries that SQL can express."""

WORDS = r"""regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"""

URL_RULES = """
with rules(verdict, host_rule, path_rule) as (values
  ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('block', 'net', '/de/'),
  ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
parts as (
  select page_id, url,
    case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
split as (
  select page_id,
    translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) as path from parts),
fits as (
  select s.*, r.host_rule || r.path_rule as rule, r.verdict,
    row_number() over (partition by s.page_id order by length(r.host_rule || r.path_rule) desc) as nth
  from split s left join rules r
    on (s.host = r.host_rule or s.host like '%.' || r.host_rule) and starts_with(s.path, r.path_rule))
select page_id, host, path, rule, coalesce(verdict, 'allow') as verdict from fits where nth = 1
"""

MIXING = r"""
with sized as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size from documents),
per as (
  select source, sum(size)::bigint as source_size,
    (case (row_number() over (order by source is null, source) - 1) % 3 when 0 then 5 when 1 then 2 else 1 end)::double as weight
  from sized group by source),
ordered as (
  select *, 3.0::double * source_size as ceiling, sum(source_size) over () as whole,
    row_number() over (order by 3.0::double * source_size / weight, source is null, source) as k from per),
levels as (
  select *, (whole - coalesce(sum(ceiling) over (order by k rows between unbounded preceding and 1 preceding), 0))
      / sum(weight) over (order by k rows between current row and unbounded following) as level from ordered),
chosen as (select min(k) as k from levels where ceiling >= level * weight),
goal as (
  select source, source_size, round(least(ceiling, coalesce((select level from levels where k = (select k from chosen)), 1e300) * weight), 6)::double as target from levels),
rated as (
  select s.doc_id, s.size, g.source_size, g.target,
    case when g.source_size > 0 then g.target / g.source_size else 0 end as rate,
    ('0x' || substr(md5('7:' || coalesce(s.doc_id::varchar, '')), 1, 13))::bigint::double / 4503599627370496.0::double as draw
  from sized s join goal g on s.source is not distinct from g.source)
select doc_id, size, source_size, target,
  size * (floor(rate)::bigint + case when draw < rate - floor(rate) then 1 else 0 end) as taken from rated
"""


def near_dedup(shingle: int, num: int, den: int) -> str:
    return f"""
with recursive tokens as (select doc_id, {WORDS} as w from documents),
sets as (
  select doc_id, case when len(w) = 0 then []
    when len(w) < {shingle} then [array_to_string(w, ' ')]
    else list_distinct(list_transform(range(1, len(w) - {shingle} + 2), lambda i: array_to_string(w[i:i + {shingle - 1}], ' '))) end as s
  from tokens),
sized as (select doc_id, len(s) as n_shingles, hash(list_sort(s)) as h, list_sort(s) as s from sets),
classes as (select min(doc_id) as rep, h, any_value(n_shingles) as n, any_value(s) as s from sized where n_shingles > 0 group by h),
flat as (select rep, n, unnest(s) as g from classes),
useful as (select g from flat group by g having count(*) > 1),
shared as (
  select x.rep as a, y.rep as b, x.n as na, y.n as nb, count(*) as m
  from flat x join flat y on x.g = y.g and x.rep < y.rep
  where x.g in (select g from useful) and {den} * least(x.n, y.n) >= {num} * greatest(x.n, y.n) group by all),
links as (select a, b from shared where {den} * m >= {num} * (na + nb - m)),
two_way as (select a, b from links union all select b, a from links),
reach(node, other) as (select rep, rep from classes union select r.node, l.b from reach r join two_way l on l.a = r.other),
component as (select node, min(other) as component_id from reach group by node)
select d.doc_id, d.n_shingles, coalesce(k.component_id, d.doc_id) as component_id, d.doc_id = coalesce(k.component_id, d.doc_id) as kept
from sized d left join classes c on c.h = d.h and d.n_shingles > 0 left join component k on k.node = c.rep
"""


def leaks(shingle: int, num: int, den: int) -> str:
    grams = f"""case when len(w) = 0 then [] when len(w) < {shingle} then [array_to_string(w, ' ')]
    else list_distinct(list_transform(range(1, len(w) - {shingle} + 2), lambda i: array_to_string(w[i:i + {shingle - 1}], ' '))) end"""
    return f"""
with items as (select item_id, {grams} as s from (select item_id, {WORDS} as w from benchmark)),
docs as (select doc_id, {grams} as s from (select doc_id, {WORDS} as w from documents)),
item_grams as (select item_id, len(s)::bigint as n_item, unnest(s) as g from items),
doc_grams as (select doc_id, unnest(s) as g from docs)
select doc_id, item_id, n_item, count(*)::bigint as n_shared
from doc_grams join item_grams using (g) group by all having {den} * count(*) >= {num} * n_item
"""
