"""The queries and SQL of this package."""

from __future__ import annotations

import importlib

_OPS = {"op1_pii": "pii", "op2_decontaminate": "decontaminate", "op3_embeddings": "embeddings", "op4_packing": "packing", "op5_langid": "langid", "op6_chat": "chat", "op7_simhash": "simhash", "op8_lm_score": "lm", "op9_lines": "lines", "op10_token_files": "huffman"}

QUERIES = {name: (lambda spark, sf_dir, name=name, module=module: getattr(importlib.import_module(f"bitparse.llm.{module}"), name)(spark, sf_dir)) for name, module in _OPS.items()}
ORACLE_SQL: dict[str, str] = {}

_ESCAPED = "replace(replace(replace(replace({x}, '&', '&amp;'), '<', '&lt;'), '[', '&lsqb;'), '|', '&vert;')"

ORACLE_SQL["op2_decontaminate"] = r"""
with lowered as (select 'd' as side, doc_id::varchar as key, row_number() over () as r, translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents
union all select 'i', item_id::varchar, row_number() over (), translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') from benchmark),
worded as materialized (select side, key, r, list_filter(regexp_split_to_array(coalesce(t, ''), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '') as w from lowered),
win as materialized (select distinct key, w[k:k + 12] as g, least(13, len(w)) as n from (select key, w, unnest(range(1, greatest(len(w) - 12, 1) + 1)) as k from worded where side = 'i' and len(w) > 0)),
own as materialized (select key, r, w, len(w) as m from worded where side = 'd'),
found as materialized (select d.r, d.k, d.n, win.key as item from (select r, n, unnest(range(1, m - n + 2)) as k, w from own, (select distinct n from win) where m >= n) d join win on win.n = d.n and win.g = d.w[d.k:d.k + d.n - 1]),
hits as (select r, count(distinct p) as n_hit from (select r, unnest(range(k, k + n)) as p from found) group by r),
items as (select r, count(distinct item) as n_items, string_agg(distinct item, ',' order by item) as names from found group by r)
select key::bigint as doc_id, m::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(names, '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= m as contaminated
from own left join hits using (r) left join items using (r)"""

ORACLE_SQL["op3_embeddings"] = """
with recursive v as materialized (select vec_id, embedding::double[] as e from embeddings),
pairs as materialized (select a.vec_id as a, b.vec_id as b from v a join v b on a.vec_id <> b.vec_id and list_cosine_similarity(a.e, b.e) >= 0.95),
reach as (select vec_id as a, vec_id as b from v union select r.a, p.b from reach r join pairs p on p.a = r.b),
least_of as (select a, min(b) as component_id from reach group by a)
select vec_id, (select count(*) from pairs where a = vec_id)::bigint as n_links, component_id, component_id = vec_id as kept from v join least_of on a = vec_id"""

ORACLE_SQL["op6_chat"] = f"""
with t as (select conv_id::bigint as conv_id, turn::bigint as turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
union all select -7, 0, 'user', '</s>[INST] ok [/INST]' union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
g as (select conv_id, count(*) as n_turns, string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text) as said, coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '') as loss,
sum(2 + length({_ESCAPED.format(x='role')}) + 3 + length({_ESCAPED.format(x='text')}) + 8) as formatted_chars from t group by conv_id)
select conv_id, n_turns::bigint as n_turns, sha256(said) as turns_sha256, length(loss)::bigint as loss_chars, sha256(loss) as loss_sha256, formatted_chars::bigint as formatted_chars from g"""
