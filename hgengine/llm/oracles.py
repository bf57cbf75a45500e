"""DuckDB SQL for the operators that SQL can express."""

from __future__ import annotations

OP1 = r"""
with d as (select doc_id, source as host, coalesce(text, '') as text from documents),
w as (select doc_id, host, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as words from d),
lines as (
  select doc_id, host, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) as n,
    trim(regexp_replace(regexp_replace(lower(line), '[\x20\x09-\x0D]+', ' ', 'g'), '[0-9]+', '0', 'g')) as plain
  from (select doc_id, host, unnest(string_split(text, chr(10))) as line from d)
  where regexp_matches(line, '[^\x20\x09-\x0D]')),
tri as (
  select doc_id, i, struct_pack(a := words[i], b := words[i + 1], c := words[i + 2]) as t
  from (select doc_id, words, unnest(range(1, len(words) - 1)) as i from w where len(words) >= 3)),
twice as (select doc_id, i, count(*) over (partition by doc_id, t) as n from tri),
rep as (
  select doc_id, count(distinct p) as n_repeat_words
  from (select doc_id, unnest([i, i + 1, i + 2]) as p from twice where n > 1) group by doc_id),
dup as (select doc_id, count(*) - count(distinct line) as n_dup_lines from lines group by doc_id),
hosts as (select host, count(*) as host_docs from d group by host),
freq as (
  select l.host, l.plain from lines l join hosts h on l.host is not distinct from h.host
  group by l.host, l.plain, h.host_docs
  having count(distinct doc_id) > 10 and count(distinct doc_id) > 0.002 * h.host_docs),
gone as (
  select l.doc_id, sum(l.n) as gone from lines l join freq f on l.host is not distinct from f.host and l.plain = f.plain
  group by l.doc_id),
b as (
  select w.doc_id, len(words)::bigint as n_words, length(array_to_string(words, ''))::bigint as word_chars,
    (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
    coalesce(n_dup_lines, 0)::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words, coalesce(gone, 0) as gone
  from w left join dup using (doc_id) left join rep using (doc_id) left join gone using (doc_id)),
f as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from b)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and not (gone > 0 and (n_words - gone < 20 or n_words - gone < 0.3 * n_words)) as kept
from f
"""

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP2 = rf"""
with recursive w as (select doc_id, regexp_extract_all({_LOWER.format("coalesce(text, '')")}, '[^\x20\x09-\x0D]+') as words from documents),
s as (
  select distinct doc_id, array_to_string(words[i:i + least(4, len(words) - 1)], ' ') as g
  from (select doc_id, words, unnest(range(1, greatest(len(words) - 3, 2))) as i from w where len(words) > 0)),
n as (select doc_id, count(*) as n from s group by doc_id),
links as (
  select a.doc_id as a, b.doc_id as b from s a join s b on a.g = b.g and a.doc_id <> b.doc_id
  join n na on na.doc_id = a.doc_id join n nb on nb.doc_id = b.doc_id
  group by a.doc_id, b.doc_id, na.n, nb.n having 100 * count(*) >= 80 * (na.n + nb.n - count(*))),
reach as (select a as root, a as node from links union select r.root, l.b from reach r join links l on l.a = r.node)
select d.doc_id, coalesce(n.n, 0)::bigint as n_shingles, least(d.doc_id, coalesce(m.root, d.doc_id)) as component_id
from documents d left join n using (doc_id) left join (select node, min(root) as root from reach group by node) m on m.node = d.doc_id
"""

_PLAIN = r"regexp_extract_all(" + _LOWER.format("coalesce(text, '')") + r", '[0-9a-z\x{80}-\x{10FFFF}]+')"

OP3 = rf"""
with dw as (select doc_id, {_PLAIN} as words from documents),
iw as (select item_id, {_PLAIN} as words from benchmark where text is not null),
win as (
  select distinct item_id, least(13, len(words)) as size, array_to_string(words[i:i + least(13, len(words)) - 1], ' ') as g
  from (select item_id, words, unnest(range(1, len(words) - least(13, len(words)) + 2)) as i from iw where len(words) > 0)),
sizes as (select distinct size from win),
grams as (
  select doc_id, size, i, array_to_string(words[i:i + size - 1], ' ') as g
  from (select doc_id, size, words, unnest(range(1, len(words) - size + 2)) as i from dw cross join sizes where len(words) >= size)),
found as (select g.doc_id, g.i, g.size, w.item_id from grams g join win w on w.size = g.size and w.g = g.g),
hits as (select doc_id, count(distinct p) as n from (select doc_id, unnest(range(i, i + size)) as p from found) group by doc_id),
items as (select doc_id, count(*) as n, string_agg(item, ',' order by item) as ids from (select distinct doc_id, item_id::varchar as item from found) group by doc_id)
select dw.doc_id, len(words)::bigint as n_words, coalesce(h.n, 0)::bigint as n_hit, coalesce(i.n, 0)::bigint as n_items,
  sha256(coalesce(i.ids, '')) as items_sha256, coalesce(h.n, 0) > 0 and 20 * coalesce(h.n, 0) >= len(words) as contaminated
from dw left join hits h using (doc_id) left join items i using (doc_id)
"""

OP4 = r"""
with d as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size, md5(doc_id::varchar || ':mix') as key from documents),
s as (
  select source, sum(size)::bigint as s, row_number() over (order by source is null, source) as rk from d group by source),
r as (select *, (rk - 1) % 3 + 1 as w, (3 * s)::double / ((rk - 1) % 3 + 1) as ratio from s),
c as (
  select *, ((sum(s) over () - coalesce(sum(3 * s) over (order by ratio, rk rows between unbounded preceding and 1 preceding), 0))::double
    / (sum(w) over () - coalesce(sum(w) over (order by ratio, rk rows between unbounded preceding and 1 preceding), 0))) as level from r),
l as (select *, first(case when ratio >= level then level end order by case when ratio >= level then 0 else 1 end, ratio, rk) over () as lv from c),
t as (select source, s, least((3 * s)::double, lv * w) as target from l),
e as (select *, floor(target)::bigint as budget, case when s > 0 then floor(target)::bigint // s else 0 end as epochs from t),
x as (
  select d.*, e.s, e.target, e.epochs, e.budget - e.epochs * e.s as rest,
    coalesce(sum(size) over (partition by d.source order by key, doc_id rows between unbounded preceding and 1 preceding), 0) as before
  from d join e on d.source is not distinct from e.source)
select doc_id, size, s as source_size, target, (epochs * size + greatest(0, least(size, rest - before)))::bigint as taken from x
"""

OP7 = """
with p as (select page_id, encode(coalesce(html, '')) as h from pages),
q as (select page_id, octet_length(h)::bigint as payload_bytes, sha256(h) as payload_digest, min(page_id) over (partition by sha256(h)) as first from p)
select page_id, payload_bytes, payload_digest, case when payload_bytes >= 100 and first < page_id then 'revisit' else 'response' end as record_type,
  case when payload_bytes >= 100 and first < page_id then first end as refers_to
from q
"""

ORACLES = {"op1_quality_rules": OP1, "op2_ngram_join": OP2, "op3_decontaminate": OP3, "op4_mix_sources": OP4, "op7_warc": OP7}
