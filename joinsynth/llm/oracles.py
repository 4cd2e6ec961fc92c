"""DuckDB SQL over the given tables for the queries that SQL can express on whole tables."""

from __future__ import annotations

_LOWER = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _reach(vertices: str, edges: str) -> str:
    """CTEs ``reach(v, component)``: the least vertex reachable, itself included."""
    return f"""
  both_ways as (select a, b from {edges} union select b, a from {edges}),
  walk(v, w) as (select v, v from {vertices} union select walk.v, both_ways.b from walk join both_ways on both_ways.a = walk.w),
  reach as (select v, min(w) as component from walk group by v)"""


_OP1 = f"""
with recursive
  words as (select doc_id, regexp_extract_all({_LOWER}, '[^\\x20\\x09-\\x0D]+') as w from documents),
  shingles as (
    select distinct doc_id, s from (
      select doc_id, unnest(case when len(w) = 0 or w is null then [] when len(w) < 5 then [array_to_string(w, ' ')]
        else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' ')) end) as s from words)),
  sizes as (select doc_id, count(*) as n from shingles group by doc_id),
  meets as (select x.doc_id as a, y.doc_id as b, count(*) as m from shingles x join shingles y on x.s = y.s and x.doc_id < y.doc_id group by 1, 2),
  links as (select a, b from meets join sizes p on p.doc_id = a join sizes q on q.doc_id = b where 100 * m >= 75 * (p.n + q.n - m)),
  ids as (select distinct doc_id as v from documents),{_reach("ids", "links")}
select d.doc_id, coalesce(n, 0)::bigint as n_shingles, component as component_id, d.doc_id = component as kept
from documents d left join sizes s on s.doc_id = d.doc_id join reach on v = d.doc_id
"""

_OP3 = f"""
with
  doc_words as (select doc_id, regexp_extract_all(coalesce({_LOWER}, ''), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as w from documents),
  item_words as (select cast(item_id as varchar) as item_id, regexp_extract_all(coalesce({_LOWER}, ''), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as w from benchmark),
  windows as (
    select distinct item_id, k, win from (
      select item_id, least(10, len(w)) as k, unnest(list_transform(range(1, greatest(1, len(w) - 9) + 1), lambda i: array_to_string(w[i : i + 9], ' '))) as win from item_words where len(w) > 0)),
  sizes as (select distinct k from windows),
  places as (
    select doc_id, k, i, array_to_string(w[i : i + k - 1], ' ') as win from (
      select doc_id, w, k, unnest(range(1, len(w) - k + 2)) as i from doc_words, sizes where len(w) >= k)),
  found as (select doc_id, item_id, i, k from places join windows using (k, win)),
  hits as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + k)) as p from found) group by doc_id),
  items as (select doc_id, count(*) as n_items, string_agg(item_id, ',' order by item_id) as names from (select distinct doc_id, item_id from found) group by doc_id)
select d.doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(names, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from doc_words d left join hits using (doc_id) left join items using (doc_id)
"""

_OP6 = """
with
  split as (select doc_id, string_split(text, chr(10)) as ls from documents),
  lines as (select doc_id, unnest(ls) as line, generate_subscripts(ls, 1) as i, len(ls) as n from split),
  hashed as (select *, md5(line) as m, ('0x' || substr(md5(line), 1, 15))::bigint as h, trim(line, ' ') <> '' as filled from lines),
  rolled as (select *, xor(xor(h, coalesce(lag(h, 1) over w, 0) >> 1), coalesce(lag(h, 2) over w, 0) >> 2) as roll from hashed window w as (partition by doc_id order by i)),
  marked as (select *, i = n or (roll & 3) = 0 as ends from rolled),
  numbered as (select *, coalesce(sum(ends::int) over (partition by doc_id order by i rows between unbounded preceding and 1 preceding), 0) as place from marked),
  chunks as (select doc_id, place, count(*) filter (filled) as filled, string_agg(line, chr(10) order by i) as body from numbered group by doc_id, place),
  ranked as (select doc_id, filled >= 2 and row_number() over (partition by body order by doc_id, place) > 1 as gone from chunks),
  by_chunk as (select doc_id, count(*) as n_chunks, count(*) filter (gone) as n_gone from ranked group by doc_id),
  pairs as (select doc_id, i as s, lead(i) over (partition by doc_id order by i) as e from hashed where filled),
  bodies as (select p.doc_id, s, e, array_to_string(ls[s:e], chr(10)) as body from pairs p join split using (doc_id) where e is not null),
  repeats as (select * from (select *, row_number() over (partition by body order by doc_id, s) as k from bodies) where k > 1),
  lost as (select distinct doc_id, unnest(range(s, e + 1)) as i from repeats),
  kept as (
    select l.doc_id, max(n) as n_lines, count(x.i) as n_lost, coalesce(string_agg(line, chr(10) order by l.i) filter (x.i is null), '') as body
    from lines l left join lost x on x.doc_id = l.doc_id and x.i = l.i group by l.doc_id)
select k.doc_id, n_lines::bigint as n_lines, n_chunks::bigint as n_chunks, n_gone::bigint as n_removed_chunks, n_lost::bigint as n_removed_lines, md5(body) as kept_md5
from kept k join by_chunk using (doc_id)
"""

_OP8 = r"""
with recursive
  cut as (select page_id, url, html, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
  parts as (
    select page_id, url, html, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
      regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from cut),
  rules(verdict, h, p) as (values ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
  fitting as (
    select page_id, arg_max(h || p, length(h || p)) as rule, arg_max(verdict, length(h || p)) as verdict
    from parts join rules on (host = h or ends_with(host, '.' || h)) and starts_with(path, p) group by page_id),
  links as (
    select regexp_replace(url, '#.*$', '') as a, regexp_extract(regexp_extract(html, '(?i)<link\b[^>]*\brel\s*=\s*["'']?canonical\b[^>]*>'), '(?i)\bhref\s*=\s*["'']?([^"''\s>]+)', 1) as b from pages
    union all
    select regexp_replace(url, '#.*$', ''), regexp_extract(regexp_extract(html, '(?i)<meta\b[^>]*\bhttp-equiv\s*=\s*["'']?refresh\b[^>]*>'), '(?i)\burl\s*=\s*["'']?([^"''\s>;]+)', 1) from pages),
  edges as (select a, regexp_replace(b, '#.*$', '') as b from links where strpos(b, '://') > 0),
  both_ways as (select a, b from edges union select b, a from edges),
  walk(v, w) as (select a, a from both_ways union select walk.v, both_ways.b from walk join both_ways on both_ways.a = walk.w),
  bad as (
    select distinct v from walk join (select regexp_replace(url, '#.*$', '') as u from parts join fitting using (page_id) where verdict = 'block') on u = w)
select p.page_id, host, path, rule, coalesce(f.verdict, case when bad.v is not null then 'block' else 'allow' end) as verdict
from parts p left join fitting f using (page_id) left join bad on bad.v = regexp_replace(p.url, '#.*$', '')
"""

_OP10 = f"""
with recursive
  ids as (select vec_id as v from embeddings),
  links as (
    select x.vec_id as a, y.vec_id as b from embeddings x join embeddings y on x.vec_id < y.vec_id
    where list_cosine_similarity(x.embedding::double[], y.embedding::double[]) >= 0.9),{_reach("ids", "links")},
  degree as (select a, count(*) as n from both_ways group by a)
select v as vec_id, coalesce(n, 0)::bigint as n_links, component as component_id, v = component as kept from reach left join degree on a = v
"""

ORACLES: dict[str, str] = {
    "op1_minhash_near_dedup": _OP1, "op3_benchmark_decontamination": _OP3, "op6_line_dedup": _OP6, "op8_url_filters": _OP8, "op10_embedding_near_dedup": _OP10,
}
