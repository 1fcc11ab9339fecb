"""DuckDB SQL for the queries of this folder that SQL can express over whole tables."""

from __future__ import annotations

_LOWERED = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _words(pattern: str) -> str:
    return f"coalesce(regexp_extract_all({_LOWERED}, '{pattern}'), [])"


#: Every pair of distinct shingle sets within the size bound is compared; labels spread until they rest.
NEAR_DUPLICATES = rf"""with recursive d as (select doc_id, {_words(r'[^\x20\x09-\x0D]+')} ws from documents),
s as (select doc_id, case when len(ws) >= 2 then list_sort(list_distinct(list_transform(generate_series(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1]))) else ws end sh from d),
cls as materialized (select sh, min(doc_id) cid, len(sh) n from s where len(sh) > 0 group by sh),
tok as materialized (select cid, n, unnest(sh) t from cls),
both_ as (select a.cid a, b.cid b, any_value(a.n) na, any_value(b.n) nb, count(*) c from tok a join tok b on a.t = b.t and a.cid < b.cid and 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) group by 1, 2),
link as materialized (select a, b from both_ where 100 * c >= 80 * (na + nb - c)),
arc as materialized (select a, b from link union select b, a from link),
reach as (select cid v, cid r from cls union select reach.v, arc.b from reach join arc on arc.a = reach.r),
comp as (select v, min(r) c from reach group by v)
select s.doc_id, cast(len(s.sh) as bigint) as n_shingles, coalesce(comp.c, s.doc_id) as component_id, s.doc_id = coalesce(comp.c, s.doc_id) as kept
from s left join cls on cls.sh = s.sh left join comp on comp.v = cls.cid"""

_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

CONTAMINATION = rf"""with d as materialized (select doc_id, {_words(_ALNUM)} ws from documents),
b as (select cast(item_id as varchar) item, {_words(_ALNUM)} ws from benchmark),
sized as (select item, ws, least(13, len(ws)) l from b where len(ws) > 0),
iw as materialized (select distinct item, l, array_to_string(ws[i:i + l - 1], ' ') k from (select item, ws, l, unnest(generate_series(1, len(ws) - l + 1)) i from sized)),
dw as (select doc_id, l, i, array_to_string(ws[i:i + l - 1], ' ') k from (select doc_id, ws, l, unnest(generate_series(1, len(ws) - l + 1)) i from d, (select distinct l from iw) where len(ws) >= l)),
hit as materialized (select doc_id, item, i, dw.l from dw join iw on dw.l = iw.l and dw.k = iw.k),
hw as (select distinct doc_id, w from (select doc_id, unnest(generate_series(i, i + l - 1)) w from hit)),
at_ as (select doc_id, count(*) n_hit, count(*) filter (where w <> b + 1) + 1 n_spans from (select doc_id, w, coalesce(lag(w) over (partition by doc_id order by w), w - 1) b from hw) group by doc_id),
its as (select doc_id, list_sort(list(distinct item)) items from hit group by doc_id)
select d.doc_id, cast(len(ws) as bigint) as n_words, coalesce(n_hit, 0) as n_hit, cast(coalesce(len(items), 0) as bigint) as n_items, coalesce(n_spans, 0) as n_spans,
  sha256(coalesce(array_to_string(items, ','), '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(ws) as contaminated
from d left join at_ on at_.doc_id = d.doc_id left join its on its.doc_id = d.doc_id"""


#: Conversations without explicit calls: a user turn calls, the assistant turn right after it answers.
TOOL_CHAT = """with c as (select conv_id, turn, coalesce(role, '') as who, coalesce(text, '') as said from conversations),
e as (select c.*, case who when 'user' then 'call' when 'assistant' then 'result' else 'message' end as kind, row_number() over (partition by conv_id order by turn) - 1 as position from c),
l as (select e.*, o.turn as link_turn from e left join e o on o.conv_id = e.conv_id and (e.kind = 'call' and o.kind = 'result' and o.turn = e.turn + 1 or e.kind = 'result' and o.kind = 'call' and o.turn = e.turn - 1)),
n as (select *, case kind when 'call' then 'turn-' || turn when 'result' then 'turn-' || (turn - 1) end as call_id from l)
select conv_id, position, turn, kind, call_id, link_turn is not null as linked, link_turn, cast(case when link_turn is not null then 0 end as integer) as link_place, false as cycle, '' as errors,
  case kind when 'call' then '{"arguments":{"prompt":' || to_json(said) || ',"turn":' || turn || '},"call_id":"' || call_id || '","kind":"call","linked":' || (link_turn is not null) || ',"name":"respond","role":' || to_json(who) || '}'
  when 'result' then '{"call_id":"' || call_id || '","content":' || to_json(said) || ',"kind":"result","linked":' || (link_turn is not null) || ',"role":' || to_json(who) || '}'
  else '{"content":' || to_json(said) || ',"kind":"message","linked":false,"role":' || to_json(who) || '}' end as json
from n"""
