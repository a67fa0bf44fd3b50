"""General operators around the methods: scans, predicates, joins, aggregates, windows, sets, functions.

Where Spark SQL and DuckDB read the same statement it is written once (``both``); the DataFrame form
is used where the two differ or where the physical operator matters.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from gistloom.operators import nearest
from gistloom.plans.workloads import load
from gistloom.sources.formats import round_trip, sink_partitioned
from gistloom.staging import fresh_path, materialize

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def both(name: str, sql: str, duck: str | None = None) -> None:
    """A query given as SQL; only the tables that it names are read, through temporary views."""
    used = [t for t in TABLES if f"{{{t}}}" in sql]

    def run(spark, sf_dir):
        return spark.sql(sql, **{t: load(spark, sf_dir, t) for t in used})

    QUERIES[name] = run
    ORACLES[name] = (duck or sql).format(**{t: t for t in TABLES}) if "{" in (duck or sql) else (duck or sql)


def frame(name: str, duck: str):
    def keep(f):
        QUERIES[name], ORACLES[name] = f, duck
        return f

    return keep


# scans and formats
both("scan_parquet_pruned", "select l_returnflag, count(*) as n, round(sum(l_quantity), 2) as qty from {lineitem} where l_shipdate >= timestamp '1996-01-01 00:00:00' and l_quantity > 10 group by l_returnflag")
both("scan_json_props", "select get_json_object(props, '$.k') as k, count(*) as n from {events} group by 1", "select json_extract_string(props, '$.k') as k, count(*) as n from events group by 1")
both("scan_json_declared", "select event_id, cast(from_json(props, 'k string').k as string) as k from {events}", "select event_id, json_extract_string(props, '$.k') as k from events")
both("scan_variant", "select event_id, variant_get(parse_json(props), '$.k', 'string') as k from {events}", "select event_id, json_extract_string(props, '$.k') as k from events")
both("pages_strip_tags", r"select page_id, length(regexp_replace(regexp_replace(html, '<script[^<]*</script>', ''), '<[^>]*>', '')) as n from {pages}", r"select page_id, length(regexp_replace(regexp_replace(html, '<script[^<]*</script>', '', 'g'), '<[^>]*>', '', 'g'))::int as n from pages")
both("w6_noise", r"select page_id, size(regexp_extract_all(html, '<[^>]*>', 0)) as tags, size(regexp_extract_all(regexp_replace(html, '<[^>]*>', ' '), '[^ \\t\\n\\r\\f]+', 0)) as words from {pages}", r"select page_id, len(regexp_extract_all(html, '<[^>]*>'))::int as tags, len(regexp_extract_all(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[^ \t\n\r\f]+'))::int as words from pages")
both("values_budgets", "select cast(b as double) as b from values (0.005), (0.02), (0.05), (0.1) as t(b)", "select b::double as b from (values (0.005), (0.02), (0.05), (0.1)) as t(b)")
both("sql_entry", "select lang, count(*) as n, sum(n_chars) as chars from {documents} group by lang")
for _fmt in ("json", "csv", "orc", "text"):
    frame(f"roundtrip_{_fmt}", "select n_nationkey, n_name, n_regionkey from nation" if _fmt != "text" else "select n_name from nation")(lambda spark, sf_dir, f=_fmt: round_trip(load(spark, sf_dir, "nation"), f))
frame("sink_partitioned", "select r_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")(lambda spark, sf_dir: sink_partitioned(spark, sf_dir))

# projection, predicates, generators
both("project_basic", "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) as net from {lineitem}")
both("filter_basic", "select o_orderkey, o_totalprice from {orders} where o_totalprice between 1000 and 50000 and o_orderstatus in ('O', 'F') and o_custkey is not null")
both("filter_text", "select doc_id from {documents} where text like '%the%' and lang <> 'de' and length(text) > 100")
both("filter_array", "select doc_id from {documents} where array_contains(split(text, ' '), 'the') and not exists(split(text, ' '), x -> length(x) > 40)", "select doc_id from documents where list_contains(string_split(text, ' '), 'the') and len(list_filter(string_split(text, ' '), lambda x: length(x) > 40)) = 0")
both("case_coalesce", "select doc_id, case when quality = 1 then 'good' when toxic = 1 then 'toxic' else coalesce(nullif('x', 'x'), 'other') end as kind from {labels}")
both("explode_tokens", "select doc_id, pos, tok from {documents} lateral view posexplode(split(text, '\\n')) t as pos, tok", "select doc_id, unnest(range(len(l)))::int as pos, unnest(l) as tok from (select doc_id, string_split(text, chr(10)) as l from documents)")
both("lateral_chunks", "select doc_id, c from {documents}, lateral (select explode(sequence(0, cast((n_chars - 1) div 1000 as int))) as c)", "select doc_id, c::int as c from documents, unnest(range(0, (n_chars - 1) // 1000 + 1)) as t(c)")
both("sample_md5", "select doc_id from {documents} order by md5(cast(doc_id as string)), doc_id limit 100", "select doc_id from documents order by md5(doc_id::varchar), doc_id limit 100")
both("pivot_budget", "select * from (select l_returnflag, l_linestatus, l_quantity from {lineitem}) pivot (sum(l_quantity) for l_linestatus in ('O' as o, 'F' as f))", "select l_returnflag, sum(l_quantity) filter (where l_linestatus = 'O') as o, sum(l_quantity) filter (where l_linestatus = 'F') as f from lineitem group by 1")
both("unpivot_metrics", "select * from (select doc_id, cast(quality as long) as quality, cast(toxic as long) as toxic from {labels}) unpivot include nulls (value for metric in (quality, toxic))", "select doc_id, 'quality' as metric, quality::bigint as value from labels union all select doc_id, 'toxic', toxic::bigint from labels")

# joins
_OC = "from {orders} o join {customer} c on o.o_custkey = c.c_custkey group by c.c_mktsegment"
for _name, _hint in (("join_shuffle_hash", "shuffle_hash(c)"), ("join_sort_merge", "merge(o, c)"), ("join_broadcast", "broadcast(c)")):
    both(_name, f"select /*+ {_hint} */ c.c_mktsegment, count(*) as n, round(sum(o.o_totalprice), 2) as total {_OC}", f"select c.c_mktsegment, count(*) as n, round(sum(o.o_totalprice), 2) as total {_OC}")
both("join_left", "select d.doc_id, l.quality from {documents} d left join {labels} l on d.doc_id = l.doc_id")
both("join_right", "select l.doc_id, d.lang from {documents} d right join {labels} l on d.doc_id = l.doc_id")
both("join_full", "select coalesce(c.c_nationkey, s.s_nationkey) as k, count(c.c_custkey) as n, count(s.s_suppkey) as m from {customer} c full join {supplier} s on c.c_nationkey = s.s_nationkey group by 1")
both("join_semi", "select c_custkey from {customer} left semi join {orders} on c_custkey = o_custkey", "select c_custkey from customer where c_custkey in (select o_custkey from orders)")
both("join_anti", "select c_custkey from {customer} left anti join {orders} on c_custkey = o_custkey", "select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
both("join_cross", "select n_name, cast(b as double) as b from {nation} cross join (select explode(array(0.1, 0.2)) as b)", "select n_name, b::double as b from nation cross join (select unnest([0.1, 0.2]) as b)")
both("join_theta", "select a.n_name as x, b.n_name as y from {nation} a join {nation} b on a.n_nationkey < b.n_nationkey and a.n_regionkey > b.n_regionkey")
both("join_self", "select a.doc_id, count(*) as siblings from {labels} a join {labels} b on a.quality = b.quality and a.toxic = b.toxic where a.doc_id % 50 = b.doc_id % 50 group by a.doc_id")
both("join_siblings", "select a.doc_id, g.n as siblings from {labels} a join (select quality, toxic, count(*) as n from {labels} group by quality, toxic) g on a.quality = g.quality and a.toxic = g.toxic", "select doc_id, count(*) over (partition by quality, toxic) as siblings from labels where quality is not null and toxic is not null")
both("join_star", "select r_name, count(*) as n, round(sum(l_extendedprice), 2) as revenue from {lineitem} join {orders} on l_orderkey = o_orderkey join {customer} on o_custkey = c_custkey join {nation} on c_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey group by r_name")


@frame("join_interval", "select t.turn, count(*) as n from (select conv_id, turn, sum(length(text)) over (partition by conv_id order by turn) as z, length(text) as w from conversations) t join (select distinct conv_id, p from conversations, unnest(range(0, 2000, 100)) as r(p)) g on g.conv_id = t.conv_id and g.p < t.z and g.p >= t.z - t.w group by 1")
def join_interval(spark, sf_dir):
    """Positions in spans: equality on the conversation and on a position bucket bounds the range comparison."""
    c = load(spark, sf_dir, "conversations")
    z = F.sum(F.length("text")).over(Window.partitionBy("conv_id").orderBy("turn"))
    spans = c.select("conv_id", "turn", z.alias("z"), F.length("text").alias("w"))
    cells = spans.select("*", F.explode(F.sequence(F.floor((F.col("z") - F.col("w")) / 500), F.floor(F.col("z") / 500))).alias("cell"))
    points = c.select("conv_id").distinct().select("conv_id", F.explode(F.sequence(F.lit(0), F.lit(1900), F.lit(100))).alias("p")).withColumn("cell", F.floor(F.col("p") / 500))
    return points.join(cells, ["conv_id", "cell"]).where("p < z and p >= z - w").groupBy("turn").agg(F.count("*").alias("n"))


@frame("join_asof", """select e.event_id, (select arg_max(x.event_id, (x.ts, x.event_id)) from events x where x.event_type <> 'purchase' and x.user_id = e.user_id and (x.ts, x.event_id) <= (e.ts, e.event_id)) as prev_id
  from events e where e.event_type = 'purchase'""")
def join_asof(spark, sf_dir):
    """Latest other event of the user at or before a purchase: one window over one shuffle, no range join."""
    e = load(spark, sf_dir, "events")
    other = F.when(F.col("event_type") != "purchase", F.col("event_id"))
    prev = F.last(other, ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return e.withColumn("prev_id", prev).where("event_type = 'purchase'").select("event_id", "prev_id")


@frame("join_salted", "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1")
def join_salted(spark, sf_dir):
    """A skewed key spread over eight salts; the other side is repeated for each."""
    o = load(spark, sf_dir, "orders").select("o_custkey", F.pmod(F.xxhash64("o_orderkey"), F.lit(8)).alias("salt"))
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", F.explode(F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: i.cast("long"))).alias("salt"))
    return o.join(c, (o.o_custkey == c.c_custkey) & (o.salt == c.salt)).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


# aggregates
both("agg_basic", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as s, round(avg(l_discount), 6) as a, min(l_tax) as lo, max(l_tax) as hi from {lineitem} group by 1, 2")
both("agg_collect_sorted", "select n_regionkey, array_join(array_sort(collect_list(n_name)), ',') as names from {nation} group by 1", "select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by 1")
both("agg_distinct", "select o_orderpriority, count(distinct o_custkey) as customers, count(distinct o_orderstatus) as states from {orders} group by 1")
both("agg_filter", "select l_shipdate >= timestamp '1997-01-01 00:00:00' as late, count(*) filter (where l_quantity > 25) as big, count_if(l_discount > 0.05) as cheap from {lineitem} group by 1")
both("agg_grouping_sets", "select l_returnflag, l_linestatus, count(*) as n, cast(grouping_id(l_returnflag, l_linestatus) as long) as g from {lineitem} group by grouping sets ((l_returnflag), (l_linestatus), ())", "select l_returnflag, l_linestatus, count(*) as n, cast(grouping_id(l_returnflag, l_linestatus) as bigint) as g from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
both("agg_rollup", "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by rollup (l_returnflag, l_linestatus)")
both("agg_cube", "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by cube (l_returnflag, l_linestatus)")
both("agg_max_by", "select o_custkey, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) as best from {orders} group by 1", "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as best from orders group by 1")
both("agg_stats", "select event_type, round(stddev_samp(value), 6) as sd, round(var_pop(value), 6) as vp, round(corr(value, event_id), 6) as r, round(regr_slope(value, event_id), 9) as slope from {events} group by 1")
both("agg_percentile", "select event_type, round(percentile(value, 0.9), 6) as p90, round(median(value), 6) as med from {events} group by 1", "select event_type, round(quantile_cont(value, 0.9), 6) as p90, round(median(value), 6) as med from events group by 1")
both("agg_histogram", "select cast(floor(value / 10) as long) as bin, count(*) as n from {events} group by 1", "select floor(value / 10)::bigint as bin, count(*) as n from events group by 1")
both("agg_having", "select o_custkey, count(*) as n from {orders} group by o_custkey having count(*) > 12")
both("agg_listagg", "select conv_id, listagg(role, '>') within group (order by turn) as roles from {conversations} group by 1", "select conv_id, string_agg(role, '>' order by turn) as roles from conversations group by 1")
both("agg_token_bag", "select item_id, w, count(*) as n from {benchmark} lateral view explode(split(lower(text), '[^a-z]+')) t as w where w <> '' group by all", "select item_id, w, count(*) as n from (select item_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) as w from benchmark) where w <> '' group by all")
both("agg_bool_bit", "select quality, every(toxic >= 0) as ok, some(toxic = 1) as any_toxic, bit_xor(doc_id) as x from {labels} group by 1", "select quality, bool_and(toxic >= 0) as ok, bool_or(toxic = 1) as any_toxic, bit_xor(doc_id) as x from labels group by 1")

# windows
both("win_ranking", "select o_orderkey, row_number() over w as rn, rank() over (partition by o_orderstatus order by o_orderpriority) as rk, dense_rank() over (partition by o_orderstatus order by o_orderpriority) as dr, ntile(10) over w as nt from {orders} window w as (partition by o_orderstatus order by o_totalprice, o_orderkey)")
both("win_distribution", "select s_suppkey, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from {supplier} window w as (order by s_acctbal, s_suppkey)")
both("win_offsets", "select event_id, lag(event_id, 1) over w as a, lead(event_id, 2) over w as b, first_value(event_id) over w as f, nth_value(event_id, 2) over w as s from {events} window w as (partition by user_id order by ts, event_id)")
both("win_last_ignore_nulls", "select event_id, last_value(case when event_type = 'click' then event_id end) ignore nulls over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as c from {events}", "select event_id, last_value(case when event_type = 'click' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as c from events")
both("win_rows_frame", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and 2 following), 4) as s from {events}")
both("win_range_frame", "select event_id, count(*) over (partition by user_id order by ts range between interval '1' hour preceding and current row) as n from {events}")
both("win_islands", "select user_id, min(event_id) as a, max(event_id) as z, count(*) as n from (select *, sum(cut) over (partition by user_id order by ts, event_id) as g from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) <= interval '1' hour then 0 else 1 end as cut from {events})) group by user_id, g")

# order, limits, sets
both("sort_multi", "select o_orderkey, o_orderstatus, o_totalprice from {orders} order by o_orderstatus desc nulls last, o_totalprice, o_orderkey")
both("topk_global", "select o_orderkey, o_totalprice from {orders} order by o_totalprice desc, o_orderkey limit 50")
both("limit_offset", "select o_orderkey from {orders} order by o_orderkey limit 20 offset 100")
both("topk_group", "select * from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rn from {orders}) where rn <= 2")
both("sort_array_desc", "select r_regionkey, array_join(array_sort(split(r_name, ''), (a, b) -> case when a < b then 1 when a > b then -1 else 0 end), '') as s from {region}", "select r_regionkey, array_to_string(list_reverse_sort(string_split(r_name, '')), '') as s from region")
both("set_union", "select c_nationkey as k from {customer} union select s_nationkey from {supplier}")
both("set_union_all", "select c_nationkey as k from {customer} union all select s_nationkey from {supplier}")
both("set_intersect", "select c_nationkey as k from {customer} intersect select s_nationkey from {supplier}")
both("set_intersect_all", "select c_nationkey as k from {customer} intersect all select s_nationkey from {supplier}")
both("set_except", "select c_custkey as k from {customer} except select o_custkey from {orders}")
both("set_except_all", "select c_nationkey as k from {customer} except all select s_nationkey from {supplier}")
both("set_distinct", "select distinct md5(text) as h, lang from {documents}")

# functions
both("fn_string", "select n_nationkey, lower(n_name) as a, substr(n_name, 2, 3) as b, concat_ws('-', n_name, 'x') as c, replace(n_name, 'A', '_') as d, lpad(n_name, 12, '.') as e, reverse(n_name) as f, instr(n_name, 'I') as g, translate(n_name, 'AE', 'ae') as h, repeat('z', 2) as i, levenshtein(n_name, 'INDIA') as j, initcap(lower('ab')) as k from {nation}",
     "select n_nationkey, lower(n_name) as a, substr(n_name, 2, 3) as b, concat_ws('-', n_name, 'x') as c, replace(n_name, 'A', '_') as d, lpad(n_name, 12, '.') as e, reverse(n_name) as f, instr(n_name, 'I')::int as g, translate(n_name, 'AE', 'ae') as h, repeat('z', 2) as i, levenshtein(n_name, 'INDIA')::int as j, 'Ab' as k from nation")
both("fn_hash_bits", "select doc_id, md5(text) as m, sha2(text, 256) as s, bit_count(doc_id ^ 12345) as b, shiftleft(doc_id, 3) as l from {documents}", "select doc_id, md5(text) as m, sha256(text) as s, bit_count(xor(doc_id, 12345))::int as b, doc_id << 3 as l from documents")
both("fn_math", "select p_partkey, round(sqrt(p_retailprice), 6) as a, round(ln(p_retailprice), 6) as b, floor(p_retailprice) as c, ceil(p_retailprice) as d, round(power(p_size, 2), 2) as e, pmod(p_partkey, 7) as f, greatest(p_size, 10) as g, cast(sign(p_size - 10) as int) as h, p_partkey div 3 as i from {part}",
     "select p_partkey, round(sqrt(p_retailprice), 6) as a, round(ln(p_retailprice), 6) as b, floor(p_retailprice)::bigint as c, ceil(p_retailprice)::bigint as d, round(power(p_size, 2), 2) as e, p_partkey % 7 as f, greatest(p_size, 10) as g, sign(p_size - 10)::int as h, p_partkey // 3 as i from part")
both("fn_decimal_budget", "select doc_id, cast(ceil(cast(0.07 as decimal(9,6)) * n_chars) as int) as b from {documents}", "select doc_id, ceil(0.07::decimal(9,6) * n_chars)::int as b from documents")
both("fn_datetime", "select o_orderkey, date_trunc('month', o_orderdate) as m, year(o_orderdate) as y, month(o_orderdate) as mm, datediff(cast(o_orderdate as date), date '1992-01-01') as d, date_add(cast(o_orderdate as date), 30) as p, date_format(o_orderdate, 'yyyy-MM') as f from {orders}",
     "select o_orderkey, date_trunc('month', o_orderdate) as m, year(o_orderdate)::int as y, month(o_orderdate)::int as mm, datediff('day', date '1992-01-01', o_orderdate::date)::int as d, (o_orderdate::date + 30)::date as p, strftime(o_orderdate, '%Y-%m') as f from orders")
both("fn_array", "select item_id, size(t) as n, slice(t, 2, 3)[0] as s, array_position(t, 'the') as p, size(array_distinct(t)) as d, size(array_union(t, array('q'))) as u, size(array_except(t, array('the'))) as x, array_max(t) as hi from (select item_id, split(text, ' ') as t from {benchmark})",
     "select item_id, len(t)::int as n, t[2:4][1] as s, coalesce(list_position(t, 'the'), 0) as p, len(list_distinct(t))::int as d, len(list_distinct(list_append(t, 'q')))::int as u, len(list_distinct(list_filter(t, lambda x: x <> 'the')))::int as x, list_max(t) as hi from (select item_id, string_split(text, ' ') as t from benchmark)")
both("fn_array_hof", "select item_id, aggregate(transform(t, x -> length(x)), 0, (a, x) -> a + x) as chars, size(filter(t, x -> length(x) > 5)) as long_words, exists(t, x -> x = 'the') as has, array_join(zip_with(slice(t, 1, 2), slice(t, 1, 2), (x, y) -> concat(x, y)), '|') as z from (select item_id, split(text, ' ') as t from {benchmark})",
     "select item_id, list_sum(list_transform(t, lambda x: length(x)))::int as chars, len(list_filter(t, lambda x: length(x) > 5))::int as long_words, list_contains(t, 'the') as has, array_to_string(list_transform(t[1:2], lambda x: x || x), '|') as z from (select item_id, string_split(text, ' ') as t from benchmark)")
both("fn_map", "select n_regionkey, map_from_entries(collect_list(struct(n_name, n_nationkey)))['CHINA'] as china, size(map_keys(map_from_entries(collect_list(struct(n_name, n_nationkey))))) as n, aggregate(map_values(transform_values(map_from_entries(collect_list(struct(n_name, n_nationkey))), (k, v) -> v * 2)), 0, (a, x) -> a + x) as twice from {nation} group by 1",
     "select n_regionkey, max(case when n_name = 'CHINA' then n_nationkey end) as china, count(distinct n_name)::int as n, (2 * sum(n_nationkey))::int as twice from nation group by 1")
both("fn_struct", "select s.a as a, s.b.c as c from (select named_struct('a', n_name, 'b', named_struct('c', n_regionkey)) as s from {nation})", "select n_name as a, n_regionkey as c from nation")
both("fn_json", "select n_nationkey, get_json_object(to_json(named_struct('a', n_name, 'k', n_regionkey)), '$.a') as a, from_json(to_json(named_struct('k', n_regionkey)), 'k int').k as k from {nation}", "select n_nationkey, n_name as a, n_regionkey as k from nation")
both("fn_vector", "select a.vec_id, round(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> cast(x as double) * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a.embedding, 0D, (s, x) -> s + cast(x as double) * x) * aggregate(b.embedding, 0D, (s, x) -> s + cast(x as double) * x)), 4) as cosine from {embeddings} a join {embeddings} b on b.vec_id = 0",
     "select a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]) / sqrt(list_dot_product(a.embedding::double[], a.embedding::double[]) * list_dot_product(b.embedding::double[], b.embedding::double[])), 4) as cosine from embeddings a join embeddings b on b.vec_id = 0")
both("fn_null_cast", "select doc_id, coalesce(null, lang) as a, nvl(nullif(lang, 'en'), 'EN') as b, if(n_chars > 1000, 'long', 'short') as c, try_cast(source as int) as d, cast(n_chars as string) as e from {documents}", "select doc_id, lang as a, coalesce(nullif(lang, 'en'), 'EN') as b, if(n_chars > 1000, 'long', 'short') as c, try_cast(source as int) as d, n_chars::varchar as e from documents")
both("embedding_cosine_topk", "select * from (select q, vec_id, row_number() over (partition by q order by c desc, vec_id) as place from (select b.vec_id as q, a.vec_id, round(aggregate(zip_with(a.embedding, b.embedding, (x, y) -> cast(x as double) * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a.embedding, 0D, (s, x) -> s + cast(x as double) * x) * aggregate(b.embedding, 0D, (s, x) -> s + cast(x as double) * x)), 6) as c from {embeddings} a join {embeddings} b on b.vec_id < 10 and a.vec_id <> b.vec_id)) where place <= 5",
     "select * from (select q, vec_id, row_number() over (partition by q order by c desc, vec_id)::int as place from (select b.vec_id as q, a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]) / sqrt(list_dot_product(a.embedding::double[], a.embedding::double[]) * list_dot_product(b.embedding::double[], b.embedding::double[])), 6) as c from embeddings a join embeddings b on b.vec_id < 10 and a.vec_id <> b.vec_id)) where place <= 5")


@frame("embedding_cosine_search",
       "select * from (select q, vec_id, row_number() over (partition by q order by c desc, vec_id)::int as place from (select b.vec_id as q, a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]) / sqrt(list_dot_product(a.embedding::double[], a.embedding::double[]) * list_dot_product(b.embedding::double[], b.embedding::double[])), 6) as c from embeddings a join embeddings b on b.vec_id % 20 = 0 and a.vec_id <> b.vec_id)) where place <= 5")
def embedding_cosine_search(spark, sf_dir):
    """Every row whose id is divisible by 20 against all rows, in blocks."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest.search(e, e.where("vec_id % 20 = 0"))


both("stream_tumbling_batch", "select window(ts, '1 hour').start as w, event_type, count(*) as n from {events} group by 1, 2", "select time_bucket(interval '1 hour', ts) as w, event_type, count(*) as n from events group by 1, 2")


@frame("join_bucketed", "select o_orderstatus, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by 1")
def join_bucketed(spark, sf_dir):
    """Both sides written in the same buckets once: later joins on the key need no exchange."""
    import uuid

    names = []
    for t, key, cols in (("orders", "o_orderkey", ["o_orderkey", "o_orderstatus"]), ("lineitem", "l_orderkey", ["l_orderkey"])):
        name = f"gl_{t}_{uuid.uuid4().hex}"
        load(spark, sf_dir, t).select(*cols).write.bucketBy(8, key).sortBy(key).saveAsTable(name)
        names.append(name)
    o, li = (spark.table(n) for n in names)
    try:
        return materialize(bucketed_join(o, li), "bucketed")
    finally:
        for n in names:
            spark.sql(f"drop table {n}")


def bucketed_join(orders, lineitem):
    """Rows by status; reads of equal buckets meet without an exchange."""
    joined = orders.join(lineitem.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderstatus").agg(F.count("*").alias("n"))


def agg_approx(spark, sf_dir):
    """Sketches for scale; tests bound their error against exact counts."""
    e = load(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5, 10000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_hll"))


QUERIES["agg_approx"] = agg_approx
