"""DuckDB statements for the queries that SQL can express; each takes its own route to the result."""

from __future__ import annotations

SPLIT = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"

OP1 = r"""
with recursive w as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
sh as (select distinct doc_id, array_to_string(ws[i:i + 2], ' ') as g from w, unnest(range(1, greatest(len(ws) - 1, 2))) as r(i) where len(ws) > 0),
n as (select doc_id, count(*) as n from sh group by doc_id),
pairs as (select a.doc_id as a, b.doc_id as b, count(*) as c from sh a join sh b on a.g = b.g and a.doc_id <> b.doc_id group by all),
links as (select a, b from pairs join n x on x.doc_id = a join n y on y.doc_id = b where 100 * c >= 90 * (x.n + y.n - c)),
reach as (select doc_id as a, doc_id as b from w union select reach.a, links.b from reach join links on links.a = reach.b)
select doc_id, cast(coalesce(n.n, 0) as bigint) as n_shingles, component_id from (select a as doc_id, min(b) as component_id from reach group by a) left join n using (doc_id)
"""

OP2 = rf"""
with w as (select doc_id, coalesce(text, '') as body, {SPLIT} as ws from documents),
grams as (select doc_id, i, array_to_string(ws[i:i + 7], ' ') as g from w, unnest(range(1, len(ws) - 6)) as r(i)),
twice as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, g) as n from grams) where n > 1),
rep as (select doc_id, count(distinct p) as n from (select doc_id, unnest(range(i, i + 8)) as p from twice) group by doc_id),
ln as (select doc_id, unnest(string_split(body, chr(10))) as l from w),
lc as (select doc_id, count(*) as n_lines, count(*) - count(distinct l) as n_dup from ln where regexp_matches(l, '[^\x20\x09-\x0D]') group by doc_id),
m as (select w.doc_id, cast(len(ws) as bigint) as n_words, cast(length(array_to_string(ws, '')) as bigint) as word_chars,
  cast(length(regexp_replace(body, '[^#*$%&|<>]', '', 'g')) as bigint) as n_symbols, cast(length(regexp_replace(body, '[^A-Z]', '', 'g')) as bigint) as n_upper,
  cast(coalesce(n_dup, 0) as bigint) as n_dup_lines, cast(coalesce(n_lines, 0) as bigint) as n_lines, cast(coalesce(rep.n, 0) as bigint) as n_repeat_words
  from w left join rep using (doc_id) left join lc using (doc_id)),
f as (select *, cast((n_words < 20)::int + 2 * (100 * n_repeat_words > 30 * n_words)::int + 4 * (100 * n_symbols > 8 * word_chars)::int
  + 8 * (100 * n_dup_lines > 30 * n_lines)::int + 16 * (word_chars > 15 * n_words)::int + 32 * (word_chars < 2 * n_words)::int
  + 64 * (100 * n_upper > 60 * word_chars)::int as bigint) as failures from m)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, failures & 3 <> 0 as base_failed, failures = 0 as kept, failures from f
"""

OP3 = rf"""
with raw as (select doc_id, string_split(coalesce(text, ''), chr(10)) as ls from documents),
ln as (select doc_id, p, l, len(list_filter(regexp_split_to_array(l, '[\x20\x09-\x0D]+'), lambda x: x <> '')) as nw
  from (select doc_id, unnest(range(len(ls))) as p, unnest(ls) as l from raw)),
seq as (select doc_id, list(p order by p) as ps, list(l order by p) as ls, list(nw order by p) as ns from ln where nw > 0 group by doc_id),
run as (select doc_id, s, k, array_to_string(ls[s:s + k - 1], chr(10)) as body, list_sum(ns[s:s + k - 1]) as tw, ns[s] as w1, ns[s + k - 1] as w2
  from seq, unnest(range(1, len(ls) + 1)) as a(s), unnest(range(1, 11)) as b(k) where s + k - 1 <= len(ls)),
mini as (select * from run where tw >= 10 and (tw - w1 < 10 or tw - w2 < 10)),
late as (select * from (select *, row_number() over (partition by k, body order by doc_id, s) as no from mini) where no > 1),
gone as (select distinct doc_id, ps[i] as p from (select doc_id, unnest(range(s, s + k)) as i from late) join seq using (doc_id)),
kept as (select ln.doc_id, string_agg(l, chr(10) order by p) filter (where gone.p is null) as body, count(gone.p) as n_removed,
  coalesce(sum(nw) filter (where gone.p is not null), 0) as removed_words, coalesce(string_agg(gone.p::varchar, ',' order by gone.p), '') as removed_lines
  from ln left join gone using (doc_id, p) group by ln.doc_id)
select doc_id, cast(n_removed as bigint) as n_removed, cast(removed_words as bigint) as removed_words, removed_lines, sha256(coalesce(body, '')) as text_sha256 from kept
"""

OP7 = rf"""
with z as (select doc_id, source, cast(len({SPLIT}) as bigint) as size, md5('mix:' || doc_id::varchar) as k from documents),
t as (select source, sum(size) as source_size, row_number() over (order by source nulls last) as no from z group by source),
w as (select *, [5.0, 2.0, 1.0][(no - 1) % 3 + 1]::double as weight, 3.0 * source_size as cap, (sum(source_size) over ())::double as total from t),
lv as (select a.source, (a.total - coalesce(sum(b.cap), 0)) / ((select sum(weight) from w) - coalesce(sum(b.weight), 0)) as level
  from w a left join w b on b.cap / b.weight < a.cap / a.weight or (b.cap / b.weight = a.cap / a.weight and b.no < a.no) group by a.source, a.total),
fin as (select arg_min(level, (cap / weight, no)) as level from w join lv on lv.source is not distinct from w.source where cap / weight > level),
g as (select w.source, w.no, cast(source_size as bigint) as source_size, coalesce(least(cap, fin.level * weight), cap) as target from w, fin),
c as (select z.*, g.no, source_size, target, least(cast(round(target) as bigint), 3 * source_size) as goal,
  coalesce(sum(size) over (partition by z.source order by k, doc_id rows between unbounded preceding and 1 preceding), 0) as bef
  from z join g on g.source is not distinct from z.source),
d as (select *, case when source_size > 0 then goal // source_size else 0 end as full_rounds from c),
e as (select *, cast(full_rounds * size + greatest(0, least(size, goal - full_rounds * source_size - bef)) as bigint) as taken, bef / goal as y, [0.5, 0.0, -0.5][(no - 1) % 3 + 1]::double as a from d)
select doc_id, size, source_size, round(target, 4) as target, taken,
  round(case when taken = 0 then null when a = 0 then y else (sqrt((1 - a) * (1 - a) + 4 * a * y) - (1 - a)) / (2 * a) end, 6) as position from e
"""

_TOKENS = r"list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"

OP10 = rf"""
with b as (select item_id, {_TOKENS} as ws from benchmark where item_id is not null),
bw as (select distinct item_id, k, array_to_string(ws[i:i + k - 1], ' ') as g
  from (select item_id, ws, least(len(ws), 13) as k from b where len(ws) > 0), unnest(range(1, len(ws) - k + 2)) as r(i)),
d as (select doc_id, {_TOKENS} as ws from documents),
dg as (select doc_id, i, k, array_to_string(ws[i:i + k - 1], ' ') as g
  from d, (select distinct k from bw), unnest(range(1, len(ws) - k + 2)) as r(i)),
hit as (select doc_id, i, k, item_id from dg join bw using (k, g)),
cov as (select doc_id, count(distinct p) as n_hit from (select distinct doc_id, unnest(range(i, i + k)) as p from hit) group by doc_id),
its as (select doc_id, count(*) as n_items, string_agg(s, ',' order by s) as ids from (select distinct doc_id, item_id::varchar as s from hit) group by doc_id)
select d.doc_id, cast(len(ws) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
  sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(ws) as contaminated
from d left join cov using (doc_id) left join its using (doc_id)
"""

_BIT = " + ".join(f"{16 >> k} * substr(bits, (5 * i + {k + 1})::int, 1)::int" for k in range(5))
OP6 = f"""
with p as (select page_id, coalesce(html, '') as html from pages),
f as (select html, min(page_id) as first from p group by html),
h as (select page_id, first, strlen(p.html) as n, array_to_string(list_transform(string_split(sha1(p.html), ''),
  lambda c: substr('0000000100100011010001010110011110001001101010111100110111101111', (4 * (strpos('0123456789abcdef', c) - 1) + 1)::int, 4)), '') as bits from p join f on p.html = f.html)
select page_id, cast(n as bigint) as payload_bytes, array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (1 + {_BIT})::int, 1)), '') as payload_digest,
  case when page_id = first then 'response' else 'revisit' end as record_type, case when page_id <> first then first end as refers_to from h
"""

ORACLES = {"op1_ngram_jaccard": OP1, "op2_quality_rules": OP2, "op3_line_dedup": OP3, "op6_warc": OP6, "op7_source_mix": OP7, "op10_decontamination": OP10}
