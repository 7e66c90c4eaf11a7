"""DuckDB twins of the queries that SQL can express."""

from __future__ import annotations

_WORDS = r"[^\x20\x09-\x0D]+"

MIX = rf"""
with docs as (select doc_id, source, coalesce(len(regexp_extract_all(text, '{_WORDS}')), 0)::bigint as size, text from documents),
sources as (select source, sum(size)::bigint as source_size from docs group by source),
weighted as (select *, [5.0::double, 2.0::double, 1.0::double][((row_number() over (order by source nulls last) - 1) % 3 + 1)::bigint] as weight from sources),
ratios as (select *, 3.0::double * source_size / weight as ratio from weighted),
rates as (select *, (sum(source_size) over () - coalesce(3.0::double * sum(source_size) over w, 0)) / (sum(weight) over () - coalesce(sum(weight) over w, 0)) as rate
  from ratios window w as (order by ratio, source nulls last rows between unbounded preceding and 1 preceding)),
chosen as (select rate from rates where rate <= ratio order by ratio, rate limit 1),
goals as (select source, source_size, coalesce(least(3.0::double * source_size, weight * (select rate from chosen)), 0) as target,
  (('0x' || substr(md5(coalesce(source, chr(0) || 'null') || '|7'), 1, 8))::bigint::double + 0.5) / 4294967296.0::double as u from weighted),
ranked as (select d.doc_id, d.size, g.source_size, g.target, g.u, case when g.source_size > 0 then g.target / g.source_size else 0 end as each,
  (row_number() over (partition by d.source order by d.size, d.doc_id) - 1)::double as k
  from docs d join goals g on d.source is not distinct from g.source)
select doc_id, size, source_size, target, ((floor(u + (k + 1) * each) - floor(u + k * each))::bigint * size)::bigint as taken from ranked
"""

CHAT = r"""
with turns as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '\### Assistant: </turn> ok' union all select -7, 1, 'assistant', '\### Assistant: </turn> ok'),
plain as (select *, '<turn ' || role || '>' || chr(10) || text || '</turn>' || chr(10) as raw,
  replace(replace(replace(role, '\', '\b'), '<', '\l'), '>', '\g') as role_e, replace(replace(replace(text, '\', '\b'), '<', '\l'), '>', '\g') as text_e,
  (contains(text, '</turn>') or contains(text, '<turn ') or regexp_matches(text, '\\[lbg]')
    or contains(role, '>' || chr(10)) or contains(role, '</turn>') or contains(role, '<turn ') or regexp_matches(role, '\\[lbg]')) as clash from turns),
segments as (select *, case when clash then '<turn ' || role_e || '>' || chr(10) || text_e || '</turn>' || chr(10) else raw end as segment from plain)
select conv_id, count(*)::bigint as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn nulls first, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn nulls first, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  sum(length(segment))::bigint as formatted_chars from segments group by conv_id
"""

SEARCH = """
with rows as (select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)::bigint) as q from embeddings
  where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0),
scored as (select a.vec_id as query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda p: coalesce(p[1], 0) * coalesce(p[2], 0)))::bigint as score
  from rows a join rows b on a.vec_id <> b.vec_id where a.vec_id % 50 = 0),
ranked as (select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from scored)
select query_id, rank, vec_id, score from ranked where rank <= 5
"""

_SHINGLES = rf"""
with recursive texts as (select doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORDS}') as w from documents),
sets as (select doc_id, case when text_len = 0 then [] when text_len < 5 then [array_to_string(w, ' ')]
  else list_distinct(list_transform(range(1, text_len - 3), lambda i: array_to_string(w[i:i + 4], ' '))) end as s
  from (select doc_id, coalesce(w, []) as w, coalesce(len(w), 0) as text_len from texts)),
flat as (select doc_id, len(s) as n, unnest(s) as g from sets),
links as (select a.doc_id as a, b.doc_id as b from flat a join flat b on a.g = b.g and a.doc_id < b.doc_id and 4 * a.n >= 3 * b.n and 4 * b.n >= 3 * a.n
  group by a.doc_id, b.doc_id, a.n, b.n having 100 * count(*) >= 75 * (a.n + b.n - count(*))),
edges as (select a, b from links union select b, a from links),
reach as (select distinct a as node, a as other from edges union select r.node, e.b from reach r join edges e on r.other = e.a),
least_of as (select node, min(other) as component from reach group by node)
"""

NGRAM = _SHINGLES + "select s.doc_id, len(s.s)::bigint as n_shingles, coalesce(l.component, s.doc_id) as component_id from sets s left join least_of l on s.doc_id = l.node"

LINKS = (
    _SHINGLES
    + """, texts_of as (select list_sort(s) as k, min(doc_id) as rep from sets where doc_id is not null and len(s) > 0 group by k),
linked as (select a.rep, count(*) as n from texts_of a join edges on edges.a = a.rep join texts_of b on edges.b = b.rep group by a.rep)
select s.doc_id, len(s.s)::bigint as n_shingles, coalesce(l.component, s.doc_id) as component_id, coalesce(linked.n, 0)::bigint as n_links
from sets s left join least_of l on s.doc_id = l.node left join texts_of t on t.k = list_sort(s.s) left join linked on linked.rep = t.rep"""
)

ORACLES = {"op4_ngram_join": NGRAM, "op4_ngram_links": LINKS, "op5_source_mix": MIX, "op6_chat_format": CHAT, "op7_maxscore": SEARCH}
