"""DuckDB statements of the reducer on exploded tokens: a route of their own to every result."""

from __future__ import annotations

from gistloom.operators.attention import TABLE
from gistloom.operators.scoring import FIXED_CONTRAST

T = r"'[^ \t\n\r\f]+'"
E = "[" + ", ".join(map(str, TABLE)) + "]"
FIXED = "[" + ", ".join(f"'{w}'" for w in FIXED_CONTRAST.split()) + "]"

QUESTIONS = rf"""
hit as (select d.doc_id, b.item_id, d.text, b.text as btext, strpos(d.text, b.text) as p from documents d, benchmark b where contains(d.text, b.text)),
asked as (select distinct doc_id, text from hit),
lns as (select doc_id, unnest(range(len(ls))) as ln, unnest(ls) as l from (select doc_id, string_split(text, chr(10)) as ls from asked)),
lt as (select doc_id, ln, regexp_extract_all(l, {T}) as ts from lns),
lo as (select *, coalesce(sum(len(ts)) over (partition by doc_id order by ln rows between unbounded preceding and 1 preceding), 0) as off from lt),
le as (select *, min(ln) over (partition by doc_id) as a, max(ln) over (partition by doc_id) as z from lo where len(ts) >= 6),
q as (select doc_id, 'p' || item_id || '@' || doc_id as query_id, 'passage' as kind, bt[1:len(bt) // 2] as toks, n0 + len(bt) // 2 as first_pos, n0 + len(bt) as last_pos
    from (select *, regexp_extract_all(btext, {T}) as bt, len(regexp_extract_all(left(text, p - 1), {T})) as n0 from hit) where len(bt) >= 2
  union all select doc_id, 'f' || ln || '@' || doc_id, 'first_line', ts[1:least(len(ts) // 2, 16)], off + len(ts) // 2, off + len(ts) from le where ln = a
  union all select doc_id, 'l' || ln || '@' || doc_id, 'last_line', ts[1:least(len(ts) // 2, 16)], off + len(ts) // 2, off + len(ts) from le where ln = z and z > a),
aq as (select doc_id, query_id, toks from q union all select distinct doc_id, 'fixed@' || doc_id, {FIXED} from q)
"""

SCORES = rf"""
tk as (select doc_id, row_number() over (partition by doc_id order by ln, i) - 1 as pos, ts[i + 1] as tok, i = 0 as fst from (select doc_id, ln, ts, unnest(range(len(ts))) as i from lt)),
dn as (select doc_id, count(*) as n from tk group by doc_id),
ctx as (select doc_id, pos // 256 as c, pos, tok, case when fst or not regexp_matches(tok, '[\p{{L}}\p{{N}}]') or regexp_matches(tok, '[|<>]') then 4 else 1 end as g,
  lower(tok) as low, coalesce(lag(lower(tok)) over (partition by doc_id, pos // 256 order by pos), '^') as prv from tk),
cn as (select doc_id, c, count(*) as n_chunk from ctx group by all),
cv as (select doc_id, c, pos, g, layer, md5(case layer when 0 then low when 1 then prv || ' ' || low else left(low, 4) end) as m from ctx, range(3) as r(layer)),
cw as (select doc_id, c, pos, g, layer, head, ('0x' || substr(m, (8 * head + 1)::int, 8))::bigint as w from cv, range(4) as r(head)),
qt as (select doc_id, query_id, k, lower(toks[k + 1]) as low, case when k = 0 then '^' else lower(toks[k]) end as prv from (select *, unnest(range(len(toks))) as k from aq)),
qv as (select doc_id, query_id, k, layer, md5(case layer when 0 then low when 1 then prv || ' ' || low else left(low, 4) end) as m from qt, range(3) as r(layer)),
qw as (select doc_id, query_id, k, layer, head, ('0x' || substr(m, (8 * head + 1)::int, 8))::bigint as w from qv, range(4) as r(head)),
own as (select a.query_id, a.k, a.layer, a.head, sum({E}[bit_count(xor(a.w, b.w)) + 1]) as e from qw a join qw b on a.query_id = b.query_id and a.layer = b.layer and a.head = b.head and b.k <= a.k group by all),
pr as (select qw.doc_id, qw.query_id, qw.k, layer, head, c, pos, g * {E}[bit_count(xor(qw.w, cw.w)) + 1] as e from qw join cw using (doc_id, layer, head)),
dnm as (select pr.query_id, pr.k, pr.layer, pr.head, c, sum(pr.e) + any_value(own.e) + 16777216 as den from pr join own on pr.query_id = own.query_id and pr.k = own.k and pr.layer = own.layer and pr.head = own.head group by all),
wt as (select doc_id, pr.query_id, pr.k, pr.layer, pr.head, pr.c, pos, (e::hugeint * 1000000000 // den)::bigint as w, den from pr join dnm using (query_id, k, layer, head, c)),
raw as (select doc_id, query_id, c, pos, sum(w)::bigint as s from wt group by all),
sc as (select doc_id, query_id, pos, (s * n_chunk)::bigint as v from raw join cn using (doc_id, c)),
tq as (select query_id, len(toks) as m from aq)
"""

PAIRS = """
bag as (select doc_id, query_id, b, count(*)::double as n from (select doc_id, query_id, ('0x' || substr(md5(lower(t)), 1, 8))::bigint % 64 as b from (select doc_id, query_id, unnest(toks) as t from q)) group by all),
nrm as (select doc_id, query_id, sqrt(sum(n * n)) as z from bag group by all),
cosq as (select x.doc_id, x.query_id, y.query_id as contrast_id, round(coalesce((select sum(a.n * b.n) from bag a join bag b on a.b = b.b where a.query_id = x.query_id and b.query_id = y.query_id), 0) / (x.z * y.z), 9) as similarity
  from nrm x join nrm y on x.doc_id = y.doc_id and x.query_id <> y.query_id),
far as (select doc_id, query_id, arg_min(contrast_id, (similarity, contrast_id)) as contrast_id, min(similarity) as similarity from cosq group by all),
pick as (select q.doc_id, q.query_id, coalesce(contrast_id, 'fixed@' || q.doc_id) as contrast_id, case when contrast_id is null then 'fixed' else 'farthest' end as contrast_kind from q left join far using (doc_id, query_id))
"""


def _diff(kind: str, norm: bool, name: str) -> str:
    if kind == "raw":
        return f"select '{name}' as meth, sc.doc_id, query_id, pos, v from sc join q using (doc_id, query_id)"
    pick = "pick" if kind == "auto" else "(select doc_id, query_id, 'fixed@' || doc_id as contrast_id from q)"
    a, b = ("y.m", "x.m") if norm else ("1", "1")
    return f"""select '{name}' as meth, s.doc_id, s.query_id, s.pos, (s.v * {a} - u.v * {b})::bigint as v from {pick} p join sc s on s.query_id = p.query_id
  join sc u on u.query_id = p.contrast_id and u.doc_id = s.doc_id and u.pos = s.pos join tq x on x.query_id = p.query_id join tq y on y.query_id = p.contrast_id"""


def diff(*kinds: str, norm: bool = True) -> str:
    """CTE d(meth, doc_id, query_id, pos, v) of raw, fixed and auto contrasts."""
    return "d as (" + " union all ".join(_diff(k, norm, k) for k in kinds or ("auto",)) + ")"


KEY = "meth, doc_id, query_id"


def windows(budgets=("0.1",), single: bool = False, isolated: bool = False, table: str = "d") -> str:
    """CTEs sm (smoothed), len (L and B), ws (window scores with ranks), cov (rank that covers a token first)."""
    size = "1" if isolated else ("need" if single else "least(need, ceil(0.02::decimal(9,6) * n))::int")
    smooth = "v" if isolated else f"sum(v) over (partition by {KEY} order by pos rows between 2 preceding and 2 following)"
    grid = ", ".join(f"{b}::decimal(9,6)" for b in budgets)
    return f"""
sm as (select {KEY}, pos, ({smooth})::hugeint as v from {table}),
len as (select doc_id, b, n, need, {size} as l from (select doc_id, b, n, ceil(b * n)::int as need from dn, (select unnest([{grid}]) as b))),
cum as (select {KEY}, pos, sum(v) over (partition by {KEY} order by pos) as p, v from sm),
ws as (select *, row_number() over (partition by {KEY}, b order by score desc, start) as rnk from
  (select a.meth, a.doc_id, a.query_id, b, a.pos as start, l, need, n, z.p - a.p + a.v as score from cum a join len on a.doc_id = len.doc_id join cum z on a.doc_id = z.doc_id and a.query_id = z.query_id and a.meth = z.meth and z.pos = a.pos + l - 1)),
cov as (select {KEY}, b, pos, min(rnk) as r, any_value(need) as need from (select {KEY}, b, unnest(range(start, start + l)) as pos, rnk, need from ws) group by all)
"""


TRIM = f"kept as (select {KEY}, b, pos from (select *, row_number() over (partition by {KEY}, b order by r, pos) as o from cov) where o <= need)"
STOP = f"""cnt as (select {KEY}, b, r, sum(count(*)) over (partition by {KEY}, b order by r) as tot from cov group by {KEY}, b, r),
kept as (select {KEY}, b, pos from cov join cnt using ({KEY}, b, r) where tot <= need)"""
SKIP = f"""ord as (select {KEY}, b, list(start order by rnk) as os, any_value(l)::int as l, any_value(need)::int as need, any_value(n)::int as n from ws group by all),
walk as (select {KEY}, b, 0 as i, list_transform(range(n), lambda x: false) as cv, need as lft from ord
  union all select {KEY}, b, w.i + 1,
    case when f <= w.lft then list_transform(range(n), lambda x: cv[x + 1] or (x >= st and x < st + l)) else cv end, case when f <= w.lft then w.lft - f else w.lft end
  from (select walk.*, os[walk.i + 1] as st, l, n, l - len(list_filter(cv[os[walk.i + 1] + 1:os[walk.i + 1] + l], lambda x: x)) as f from walk join ord using ({KEY}, b) where walk.i < len(os) and walk.lft > 0) w),
fin as (select {KEY}, b, arg_max(cv, i) as cv from walk group by all),
kept as (select {KEY}, b, pos from (select {KEY}, b, unnest(range(len(cv))) as pos, unnest(cv) as x from fin) where x)"""
SPANS = f"""isl as (select {KEY}, b, pos, pos - row_number() over (partition by {KEY}, b order by pos) as grp from kept),
spn as (select {KEY}, b, min(pos)::int as first_pos, (max(pos) + 1)::int as last_pos from isl group by {KEY}, b, grp)"""
RECALL = f"""rec as (select {KEY}, b, n_used, coalesce(n_in, 0) as n_in, last_pos - first_pos as n_gold from
  (select {KEY}, b, count(*) as n_used, count(*) filter (where pos >= first_pos and pos < last_pos) as n_in, any_value(first_pos) as first_pos, any_value(last_pos) as last_pos from kept join q using (doc_id, query_id) group by all))"""


def core(*parts: str, tail: str) -> str:
    return "with recursive " + ",\n".join([QUESTIONS, *parts]) + "\n" + tail
