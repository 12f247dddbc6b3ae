"""DuckDB texts for the corpus queries that SQL can express."""

from __future__ import annotations

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BENCH_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _words(table: str, key: str) -> str:
    return f"select {key} as k, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{_BENCH_WORD}') as w from {table}"


OP8 = f"""with dw as materialized ({_words('documents', 'doc_id')}), bw as materialized (select k, w, least(len(w), 10) as n from ({_words('benchmark', 'item_id')}) where len(w) > 0),
sizes as (select distinct n from bw),
bg as materialized (select distinct n, k::VARCHAR as item, array_to_string(w[i:i + n - 1], ' ') as g from (select n, k, w, unnest(range(1, len(w) - n + 2)) as i from bw)),
dg as materialized (select k, n, i, array_to_string(w[i:i + n - 1], ' ') as g from (select k, w, n, unnest(range(1, len(w) - n + 2)) as i from dw, sizes where len(w) >= n)),
hit as materialized (select dg.k, dg.n, dg.i, bg.item from dg join bg on bg.n = dg.n and bg.g = dg.g),
places as (select k, count(distinct p) as n_hit from (select k, unnest(range(i, i + n)) as p from hit) group by 1),
items as (select k, count(*) as n_items, string_agg(item, ',' order by item) as list from (select distinct k, item from hit) group by 1)
select dw.k as doc_id, len(w)::BIGINT as n_words, coalesce(n_hit, 0)::BIGINT as n_hit, coalesce(n_items, 0)::BIGINT as n_items, sha256(coalesce(list, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from dw left join places on places.k = dw.k left join items on items.k = dw.k"""

OP10 = r"""with d as materialized (select doc_id, source, coalesce(text, '') as t, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
g as materialized (select doc_id, i, w[i] || chr(1) || w[i + 1] || chr(1) || w[i + 2] as g from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from d where len(w) > 2)),
r as (select doc_id, count(distinct p) as n from (select doc_id, unnest([i, i + 1, i + 2]) as p from (select doc_id, i, count(*) over (partition by doc_id, g) as c from g) where c > 1) group by 1),
l as materialized (select doc_id, source, t, line, trim(regexp_replace(regexp_replace(lower(line), '[1-9]', '0', 'g'), '[\x20\x09\x0B-\x0D]+', ' ', 'g')) as plain from (select doc_id, source, t, unnest(string_split(t, chr(10))) as line from d) where regexp_matches(line, '[^\x20\x09-\x0D]')),
u as (select doc_id, count(*) - count(distinct line) as n from l group by 1),
f as (select source, plain from l group by source, plain having count(distinct doc_id) > 20),
b as (select l.doc_id, sum(length(replace(l.plain, ' ', ''))) as c from l join f on f.plain = l.plain and f.source is not distinct from l.source group by 1),
x as (select d.doc_id, len(w)::BIGINT as n_words, length(array_to_string(w, ''))::BIGINT as word_chars, (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT as n_symbols, coalesce(u.n, 0)::BIGINT as n_dup_lines, coalesce(r.n, 0)::BIGINT as n_repeat_words, coalesce(b.c, 0)::BIGINT as boilerplate_chars
 from d left join r on r.doc_id = d.doc_id left join u on u.doc_id = d.doc_id left join b on b.doc_id = d.doc_id)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed, boilerplate_chars,
 not (n_words < 50 or 100 * n_repeat_words > 50 * n_words) and not (boilerplate_chars > 0.5::DOUBLE * word_chars) as kept from x"""

SQL = {"op8_decontaminate": OP8, "op10_line_rules": OP10}
