"""DuckDB SQL for the queries that SQL expresses on whole tables."""

_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[0-9a-z\x{80}-\x{10FFFF}]+')"

OP1 = rf"""
with d as (select doc_id, row_number() over () as rid, {_WORDS} as w from documents),
b as (select item_id, {_WORDS} as w from benchmark where item_id is not null),
win as (
  select item_id, least(len(w), 10) as n,
    array_to_string(list_slice(w, k, k + least(len(w), 10) - 1), ' ') as key
  from b, lateral (select unnest(generate_series(1, greatest(len(w) - 9, 1))) as k) where len(w) > 0
),
sizes as (select distinct n from win),
hits as (
  select d.rid, s.k, z.n, win.item_id
  from d, sizes z, lateral (select unnest(generate_series(1, len(d.w) - z.n + 1)) as k) s
  join win on win.n = z.n and win.key = array_to_string(list_slice(d.w, s.k, s.k + z.n - 1), ' ')
),
words as (select rid, count(distinct p) as n_hit from (select rid, unnest(generate_series(k, k + n - 1)) as p from hits) group by rid),
items as (
  select rid, count(*) as n_items, string_agg(item_id::varchar, ',' order by item_id::varchar) as ids
  from (select distinct rid, item_id from hits) group by rid
)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items,
  sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join words using (rid) left join items using (rid)
"""

OP6 = """
with v as (
  select vec_id, list_transform(embedding, lambda x: x::double) as e,
    sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))) as norm
  from embeddings where embedding is not null
),
ok as (
  select vec_id, e, norm from v
  where norm > 0 and not isnan(norm) and not isinf(norm) and len(list_filter(e, lambda x: x is null)) = 0
),
l as (
  select a.vec_id as a, b.vec_id as b from ok a join ok b on a.vec_id <> b.vec_id and len(a.e) = len(b.e)
  where list_dot_product(a.e, b.e) / (a.norm * b.norm) >= 0.9
),
walk as (
  with recursive r(node, root) as (
    select vec_id, vec_id from embeddings
    union
    select l.b, r.root from r join l on l.a = r.node where r.root < l.b
  )
  select node, min(root) as component_id from r group by node
)
select e.vec_id, coalesce(n.n, 0)::bigint as n_links, w.component_id, e.vec_id = w.component_id as kept
from embeddings e join walk w on w.node = e.vec_id left join (select a, count(*) as n from l group by a) n on n.a = e.vec_id
"""

OP7 = r"""
with p as (
  select page_id, row_number() over () as rid,
    translate(regexp_extract(coalesce(url, ''), '^(?s:.*?)://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(coalesce(url, ''), '^(?s:.*?)://([^/?#]*)([^?#]*)', 2) as path
  from pages
),
r(h, q, v) as (values ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
m as (
  select rid, max_by(h || q, length(h || q)) as rule, max_by(v, length(h || q)) as verdict
  from p join r on (host = h or ends_with(host, '.' || h)) and starts_with(path, q) group by rid
)
select page_id, host, path, rule, coalesce(verdict, 'allow') as verdict from p left join m using (rid)
"""

OP10 = r"""
with d as (select row_number() over () as rid, doc_id, string_split(coalesce(text, ''), chr(10)) as ls from documents),
x as (
  select rid, doc_id, k, ls[k] as line,
    translate(trim(ls[k], ' ' || chr(9) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key
  from d, lateral (select unnest(generate_series(1, len(ls))) as k)
),
shared as (select key, min(doc_id) as first from x where length(key) >= 10 group by key having count(distinct doc_id) > 1),
y as (select x.*, s.first is not null and x.doc_id is not null and x.doc_id <> s.first as gone from x left join shared s on x.key = s.key)
select doc_id, count(*)::bigint as n_lines, coalesce(sum(case when gone then 1 else 0 end), 0)::bigint as n_dropped,
  sha256(coalesce(string_agg(line, chr(10) order by k) filter (where not gone), '')) as kept_sha256
from y group by rid, doc_id
"""

ORACLE_SQL = {"op1_decontaminate": OP1, "op6_embeddings": OP6, "op7_urls": OP7, "op10_linededup": OP10}
