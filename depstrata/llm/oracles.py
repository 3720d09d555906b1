"""DuckDB SQL for the queries that SQL can express."""

from __future__ import annotations

_W = r"[^\x20\x09-\x0D]+"

OP1 = """with v as (select vec_id, embedding::double[] as e from embeddings where embedding is not null and list_bool_and(list_transform(embedding, lambda x: x is not null and isfinite(x))) and list_bool_or(list_transform(embedding, lambda x: x <> 0))),
s as (select q.vec_id as query_id, c.vec_id, list_dot_product(q.e, c.e) as score from v q join v c on q.vec_id % 20 = 0 and q.vec_id <> c.vec_id and len(q.e) = len(c.e)),
r as (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s)
select query_id, cast(rank as int) as rank, vec_id, score from r where rank <= 20"""

OP5 = f"""with d as (select row_number() over () as id, doc_id, source, coalesce(text, '') as text from documents),
w as (select *, regexp_extract_all(text, '{_W}') as ws, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{_W}')) as ls from d),
g as (select id, unnest(range(1, len(ws) - 3)) as i, ws from w where len(ws) >= 5),
k as (select id, i, ws[i:i+4] as x from g), m as (select id, i, count(*) over (partition by id, x) as n from k),
p as (select id, count(distinct i + j) as n_repeat from (select id, i, unnest([0, 1, 2, 3, 4]) as j from m where n > 1) group by id),
l as (select id, source, text, unnest(ls) as line from w),
h as (select id, source, text, lower(regexp_replace(array_to_string(regexp_extract_all(line, '{_W}'), ' '), '[0-9]+', '0', 'g')) as h, len(regexp_extract_all(line, '{_W}')) as n from l),
f as (select source, h from h group by source, h having count(distinct text) > 20 and count(distinct text) > 0.01 * (select count(distinct text) from d where d.source is not distinct from h.source)),
r as (select h.id, sum(h.n) as gone from h join f on h.h = f.h and h.source is not distinct from f.source group by h.id),
b as (select doc_id, len(ws)::bigint as n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::bigint as word_chars, len(regexp_extract_all(text, '[#*$%&|<>]'))::bigint as n_symbols,
 (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines, coalesce(n_repeat, 0)::bigint as n_repeat_words, coalesce(gone, 0)::bigint as n_removed_words from w left join p using (id) left join r using (id))
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed,
 not (n_words < 10 or 100 * n_repeat_words > 20 * n_words) and n_words - n_removed_words >= 10 and n_words - n_removed_words >= 0.3 * n_words as kept, n_removed_words from b"""

ORACLES: dict[str, str] = {"op1_vp_tree_search": OP1, "op5_line_rules": OP5}
