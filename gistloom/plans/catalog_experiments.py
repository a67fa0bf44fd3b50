"""Queries of the experiments: all methods over budgets, answers and judges, question kinds, tables, units, cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gistloom.functions.tokens import words
from gistloom.operators import answers, attention, chunking, measures, retrieval, rows, selection, together
from gistloom.plans import catalog_core as CC
from gistloom.plans import core_sql as C
from gistloom.plans import experiments as X
from gistloom.plans import reduce as R
from gistloom.plans import workloads as W
from gistloom.staging import materialize

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


# ---- the statement of every method's kept tokens ----------------------------------------------------

_GRID = "bg as (select unnest([" + ", ".join(f"{b}::decimal(9,6)" for b in X.BUDGETS) + "]) as b)"
_ALIGNED = f"{_GRID},\nal as (select query_id, doc_id, b, max(k) filter (where k = 1 or n_used <= ceil(b * n)) as k from ks join dn using (doc_id), bg group by all)"
_BM25 = """tf as (select doc_id, chunk_no, lower(tok) as t, count(*) as tf from oct group by all), df as (select t, count(*) as df from tf group by t), cl as (select doc_id, chunk_no, count(*) as n from oct group by all),
st as (select count(*)::double as nc, avg(n) as av from cl), qs as (select distinct doc_id, query_id, lower(t) as t from (select doc_id, query_id, unnest(toks) as t from q)),
bm as (select doc_id, query_id, chunk_no, round(sum(ln(1 + (nc - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * n / av))), 6) as score from qs join tf using (doc_id, t) join df using (t) join cl using (doc_id, chunk_no), st group by all),
rg as (select *, row_number() over (partition by doc_id, query_id order by score desc, chunk_no) as place from bm)"""


def _rag_tail(name: str) -> str:
    return f"select distinct '{name}' as meth, al.doc_id, al.query_id, al.b, pos from al join rg on rg.doc_id = al.doc_id and rg.query_id = al.query_id and rg.place <= al.k join oct on oct.doc_id = rg.doc_id and oct.chunk_no = rg.chunk_no"


def kept_sql() -> str:
    kept = "select meth, doc_id, query_id, b, pos from kept"
    parts = [C.core(C.SCORES, C.PAIRS, C.diff(*X.REDUCERS), C.windows(X.BUDGETS), C.TRIM, tail=kept)]
    parts += [CC.rag_sql(k, _rag_tail(f"rag_{k}"), CC._KS, _ALIGNED) for k in X.EMBEDDERS]
    parts.append(C.core(C.SCORES, CC._CH, _BM25, CC._KS, _ALIGNED, tail=_rag_tail("rag_bm25")))
    parts.append(C.core(C.SCORES, _GRID, tail="select 'head' as meth, doc_id, query_id, b, pos from q join dn using (doc_id) join tk using (doc_id), bg where pos < ceil(b * n)"))
    rnd = "d as (select 'random' as meth, doc_id, query_id, pos, ('0x' || substr(md5(query_id || ':' || pos), 1, 7))::bigint as v from q join tk using (doc_id))"
    parts.append(C.core(C.SCORES, rnd, C.windows(X.BUDGETS), C.TRIM, tail=kept))
    return " union all ".join(f"(select * from ({p}))" for p in parts)


_METH = "ms as (select unnest([" + ", ".join(f"'{m}'" for m in X.METHODS) + "]) as meth)"


def grid_sql(tail: str, *more: str) -> str:
    """CTE g(meth, b, query_id, kind, n_used, n_in, n_gold) over all questions, methods and budgets, and ``more``."""
    every = f"""ak as materialized ({kept_sql()}), {_GRID}, {_METH},
g as (select ms.meth, bg.b, q.query_id, q.kind, any_value(q.last_pos - q.first_pos) as n_gold, count(ak.pos) as n_used, count(ak.pos) filter (where ak.pos >= q.first_pos and ak.pos < q.last_pos) as n_in
  from q cross join ms cross join bg left join ak on ak.meth = ms.meth and ak.query_id = q.query_id and ak.b = bg.b group by all)"""
    return C.core(C.SCORES, every, *more, tail=tail)


_SUM = "count(*) as n_queries, round(avg((n_in >= 0.5 * n_gold)::int), 6) as accuracy, round(avg(n_in / n_gold), 6) as recall, round(avg(n_used), 6) as avg_tokens"


def _passages(spark, sf_dir) -> DataFrame:
    """All methods' contexts for the passage questions."""
    c = CC.Core(spark, sf_dir)
    return CC.held(spark, sf_dir, "grid", lambda: X.contexts(c.tok, c.questions, c.scores))


def _budget(df: DataFrame) -> DataFrame:
    return df.withColumn("budget", F.col("b").cast("double")).drop("b")


def _w1(spark, sf_dir) -> DataFrame:
    asked = CC.Core(spark, sf_dir).questions
    return X.judged(_passages(spark, sf_dir), X.one_gold(asked)).join(asked.select("query_id", "kind"), "query_id")


@register("w1_grid", grid_sql("select meth, b::double as budget, " + _SUM + " from g group by meth, b"))
def w1_grid(spark, sf_dir):
    """Reducer variants, three embedders, BM25, positional and random selection at four budgets."""
    return _budget(X.summary(_w1(spark, sf_dir), "meth", "b"))


@register("w1_grid_by_kind", grid_sql("select meth, kind, b::double as budget, " + _SUM + " from g group by meth, kind, b"))
def w1_grid_by_kind(spark, sf_dir):
    return _budget(X.summary(_w1(spark, sf_dir), "meth", "kind", "b"))


@register("w1_grid_rank", grid_sql("select *, rank() over (partition by budget order by accuracy desc) as place from (select meth, b::double as budget, " + _SUM + " from g group by meth, b)"))
def w1_grid_rank(spark, sf_dir):
    ranked = measures.rank_methods(w1_grid(spark, sf_dir), "budget")
    return ranked.withColumn("place", F.col("place").cast("long"))


@register("w1_tokens_at_equal_accuracy", grid_sql("select a.budget, a.accuracy, min(z.avg_tokens / a.avg_tokens) filter (where z.accuracy >= a.accuracy) as ratio from (select * from crv where meth = 'auto') a cross join (select * from crv where meth like 'rag_%') z group by all",
          "crv as (select meth, b::double as budget, round(avg((n_in >= 0.5 * n_gold)::int), 6) as accuracy, round(avg(n_used), 6) as avg_tokens from g group by meth, b)"))
def w1_tokens_at_equal_accuracy(spark, sf_dir):
    """Fewest tokens that a retrieval method needs for the reducer's accuracy, relative to the reducer's; null where none gets there."""
    curve = w1_grid(spark, sf_dir).select("meth", "budget", "accuracy", "avg_tokens")
    mine = curve.where("meth = 'auto'").select("budget", "accuracy", F.col("avg_tokens").alias("mine"))
    other = curve.where("meth like 'rag_%'").select(F.col("accuracy").alias("theirs"), "avg_tokens")
    return mine.join(F.broadcast(other)).groupBy("budget", "accuracy").agg(F.min(F.when(F.col("theirs") >= F.col("accuracy"), F.col("avg_tokens") / F.col("mine"))).alias("ratio"))


# ---- answers and judges -----------------------------------------------------------------------------

_CUES = " ".join(
    f"when len(qs) >= {k} and list_position(list_transform(range(1, len(c) - {k - 2}), lambda i: c[i:i + {k - 1}]), qs[len(qs) - {k - 1}:len(qs)]) > 0"
    f" then c[list_position(list_transform(range(1, len(c) - {k - 2}), lambda i: c[i:i + {k - 1}]), qs[len(qs) - {k - 1}:len(qs)]) + {k}:list_position(list_transform(range(1, len(c) - {k - 2}), lambda i: c[i:i + {k - 1}]), qs[len(qs) - {k - 1}:len(qs)]) + {k + answers.LENGTH - 1}]"
    for k in answers.CUES)
_ANSWERS = f"""cx as (select g.meth, g.b, g.query_id, coalesce(list(tok order by pos) filter (where tok is not null), []) as c from g left join ak on ak.meth = g.meth and ak.query_id = g.query_id and ak.b = g.b left join tk using (doc_id, pos) group by all),
gl as (select q.query_id, q.toks as qs, list(tok order by pos) as gold from q join tk using (doc_id) where pos >= first_pos and pos < least(last_pos, first_pos + {answers.LENGTH}) group by all),
an as (select meth, b, query_id, gold, c, qs, case {_CUES} else [] end as ans from cx join gl using (query_id)),
lw as (select *, list_transform(ans, lambda x: lower(x)) as a, list_transform(gold, lambda x: lower(x)) as z from an),
cm as (select *, coalesce(list_sum(list_transform(list_distinct(a), lambda t: least(len(list_filter(a, lambda x: x = t)), len(list_filter(z, lambda x: x = t))))), 0) as common,
  coalesce(list_sum(list_transform(list_distinct(a), lambda t: len(list_filter(a, lambda x: x = t)) * len(list_filter(z, lambda x: x = t)))), 0)::bigint as dot,
  coalesce(list_sum(list_transform(list_distinct(a), lambda t: len(list_filter(a, lambda x: x = t)) ** 2)), 0)::bigint as na, list_sum(list_transform(list_distinct(z), lambda t: len(list_filter(z, lambda x: x = t)) ** 2))::bigint as nz from lw),
jd as (select *, contains(' ' || array_to_string(a, ' ') || ' ', ' ' || array_to_string(z, ' ') || ' ') or 2.0 * common / (len(a) + len(z)) >= 0.5 as fits,
  case when len(a) = 0 then 0.0 else round(dot / sqrt((na * nz)::double), 6) end as cosine from cm)"""


def _answered(spark, sf_dir) -> DataFrame:
    def build():
        c = CC.Core(spark, sf_dir)
        rows = X.answered(_passages(spark, sf_dir), c.tok, c.questions)
        return rows.select("meth", "query_id", "b", "answer", "gold", answers.open_judge(F.col("answer"), F.col("gold")).alias("fits"), answers.cosine(F.col("answer"), F.col("gold")).alias("cosine"))

    return CC.held(spark, sf_dir, "answered", build)


@register("generate_answers", grid_sql("select meth, query_id, b::double as budget, array_to_string(ans, ' ') as answer from an", _ANSWERS))
def generate_answers(spark, sf_dir):
    """The extractive reader's answer from every method's context."""
    return _budget(_answered(spark, sf_dir).select("meth", "query_id", "b", F.array_join("answer", " ").alias("answer")))


@register("judge_open", grid_sql("select meth, b::double as budget, count(*) as n_queries, round(avg(fits::int), 6) as accuracy, round(avg(cosine), 6) as similarity from jd group by meth, b", _ANSWERS))
def judge_open(spark, sf_dir):
    """Share of answers that contain the reference or share half of its words, and their mean cosine to it."""
    return _budget(_answered(spark, sf_dir).groupBy("meth", "b").agg(F.count("*").alias("n_queries"), F.round(F.avg(F.col("fits").cast("int")), 6).alias("accuracy"), F.round(F.avg("cosine"), 6).alias("similarity")))


_CURVE = "cu as (select meth, b, x, round(avg((cosine * 100 > x)::int), 6) as share from jd, range(0, 101, 5) as r(x) group by meth, b, x)"


@register("answer_curve", grid_sql("select meth, b::double as budget, x::int as x, share from cu", _ANSWERS, _CURVE))
def answer_curve(spark, sf_dir):
    """Share of questions whose answer is more similar to the reference than x, by method and budget."""
    return _budget(measures.survival_curve(_answered(spark, sf_dir), "cosine", "meth", "b"))


@register("answer_dominance", grid_sql("select u.b::double as budget, u.meth as upper, l.meth as lower, round(avg((u.share >= l.share)::int), 6) as not_below from cu u join cu l on u.b = l.b and u.x = l.x and u.meth <> l.meth group by all", _ANSWERS, _CURVE))
def answer_dominance(spark, sf_dir):
    return _budget(measures.dominance(measures.survival_curve(_answered(spark, sf_dir), "cosine", "meth", "b"), "meth", "b"))


_LCS = """wk as (select meth, b, query_id, a, z, 0 as i, list_transform(z, lambda x: 0::bigint) as r from lw
  union all select meth, b, query_id, a, z, i + 1, list_transform(range(1, len(z) + 1), lambda j: list_max(list_transform(range(1, j + 1), lambda k: case when z[k] = a[i + 1] then coalesce(r[k - 1], 0) + 1 else r[k] end))) from wk where i < len(a))"""


@register("rouge_l", grid_sql("select meth, b::double as budget, query_id, round(2.0 * coalesce(list_max(arg_max(r, i)), 0) / (len(any_value(a)) + len(any_value(z))), 6) as f1 from wk group by meth, b, query_id", _ANSWERS, _LCS))
def rouge_l(spark, sf_dir):
    a = _answered(spark, sf_dir)
    return _budget(a.select("meth", "b", "query_id", answers.rouge_l(F.col("answer"), F.col("gold")).alias("f1")))


_CHOICE = f"""pas as (select item_id, regexp_extract_all(text, {C.T}) as ts, row_number() over (order by md5(item_id::varchar), item_id) - 1 as no, count(*) over () as m from benchmark),
hv as (select item_id, no, m, list_transform(ts[len(ts) // 2 + 1:], lambda x: lower(x)) as opt from pas),
pq as (select query_id, split_part(substr(query_id, 2), '@', 1)::bigint as item_id from q where kind = 'passage'),
op as (select pq.query_id, pq.item_id as right_id, o.item_id as option_id, o.opt from pq join hv on hv.item_id = pq.item_id join hv o on (o.no - hv.no + hv.m) % hv.m < 4),
sc2 as (select meth, b, query_id, right_id, option_id, len(list_intersect(list_distinct(opt), list_distinct(list_transform(c, lambda x: lower(x))))) as score from op join cx using (query_id)),
ch as (select meth, b, query_id, any_value(right_id) as right_id, arg_max(option_id, (score, -option_id)) as chosen from sc2 group by meth, b, query_id)"""


def _options(spark, sf_dir) -> DataFrame:
    """right_id, option_id, option: the second half of a passage and of the three passages after it in a ring by md5 order."""
    ring = Window.partitionBy(F.lit(0)).orderBy(F.md5(F.col("item_id").cast("string")), "item_id")
    ts = words(F.col("text"))
    items = W.load(spark, sf_dir, "benchmark").select("item_id", F.slice(ts, F.floor(F.size(ts) / 2).cast("int") + 1, F.size(ts)).alias("option"))
    ids = items.select("item_id", F.row_number().over(ring).alias("no")).withColumn("m", F.max("no").over(Window.partitionBy(F.lit(0))))
    slots = ids.select(F.col("item_id").alias("right_id"), F.explode(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda k: F.pmod(F.col("no") - 1 + k, F.col("m")) + 1)).alias("no")).distinct()
    return slots.join(ids.select("no", F.col("item_id").alias("option_id")), "no").join(items.select(F.col("item_id").alias("option_id"), "option"), "option_id").select("right_id", "option_id", "option")


def _asked_items(spark, sf_dir) -> DataFrame:
    asked = CC.Core(spark, sf_dir).questions.where("kind = 'passage'")
    return asked.select("query_id", F.regexp_extract("query_id", "^p([0-9]+)@", 1).cast("long").alias("right_id"))


def _choices(spark, sf_dir) -> DataFrame:
    """meth, b, query_id, right_id, chosen: the option that the context holds most of."""
    c = CC.Core(spark, sf_dir)
    text = _passages(spark, sf_dir).join(c.tok.select("doc_id", "tokens"), "doc_id").select("meth", "b", "query_id", answers.context_tokens(F.col("tokens"), F.col("spans")).alias("context"))
    scored = text.join(_asked_items(spark, sf_dir), "query_id").join(_options(spark, sf_dir), "right_id").withColumn("score", answers.overlap(F.col("context"), F.col("option")))
    return scored.groupBy("meth", "b", "query_id", "right_id").agg(F.max(F.struct("score", (-F.col("option_id")).alias("minus"))).alias("best")).select("meth", "b", "query_id", "right_id", (-F.col("best.minus")).alias("chosen"))


@register("judge_options", C.core(_CHOICE.rsplit(",\nsc2 as", 1)[0], tail="select query_id, option_id from op"))
def judge_options(spark, sf_dir):
    """The options of every multiple-choice question; each meets four rows, no question meets all passages."""
    return _asked_items(spark, sf_dir).join(_options(spark, sf_dir), "right_id").select("query_id", "option_id")


@register("judge_exact", grid_sql("select query_id, right_id, chosen, chosen = right_id as fits from ch where meth = 'auto' and b = 0.1", _ANSWERS, _CHOICE))
def judge_exact(spark, sf_dir):
    """Multiple choice at a budget of 10%: the chosen option, and whether it is the right one."""
    rows = _choices(spark, sf_dir).where("meth = 'auto' and b = 0.1")
    return rows.select("query_id", "right_id", "chosen", (F.col("chosen") == F.col("right_id")).alias("fits"))


@register("judge_choice", grid_sql("select meth, b::double as budget, count(*) as n_queries, round(avg((chosen = right_id)::int), 6) as accuracy from ch group by meth, b", _ANSWERS, _CHOICE))
def judge_choice(spark, sf_dir):
    """Multiple choice: the option chosen is the right one."""
    return _budget(_choices(spark, sf_dir).groupBy("meth", "b").agg(F.count("*").alias("n_queries"), F.round(F.avg((F.col("chosen") == F.col("right_id")).cast("int")), 6).alias("accuracy")))


# ---- units, kernels, stride -------------------------------------------------------------------------

def _units_sql(name: str) -> str:
    base = CC.ORACLES[name].rsplit("select doc_id, query_id, unit_no", 1)[0]
    return base.rstrip() + """,
us as (select doc_id, query_id, unit_no, min(pos) as first_pos, max(pos) + 1 as last_pos, sum(v)::bigint as score from d join un using (doc_id, pos) group by all),
rs as (select *, sum(last_pos - first_pos) over (partition by doc_id, query_id order by score / (last_pos - first_pos) desc, unit_no rows unbounded preceding) as total from us)
select doc_id, query_id, unit_no::int as unit_no, first_pos::int as first_pos, last_pos::int as last_pos from rs join dn using (doc_id) where total <= ceil(0.1::decimal(9,6) * n)"""


for _rule in ("line", "sentence"):
    register(f"select_units_{_rule}", _units_sql(f"unit_{_rule}"))(
        lambda spark, sf_dir, rule=_rule: X.select_units(CC.QUERIES[f"unit_{rule}"](spark, sf_dir).join(CC.Core(spark, sf_dir).tok.select("doc_id", "n_tokens"), "doc_id")).select("doc_id", "query_id", "unit_no", "first_pos", "last_pos"))


def _kernel_sql(smooth: str) -> str:
    plain = f"sum(v) over (partition by {C.KEY} order by pos rows between 2 preceding and 2 following)"
    return C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows().replace(plain, smooth), C.TRIM, C.SPANS, tail="select doc_id, query_id, first_pos, last_pos from spn")


_LAGS = " + ".join(f"{3 - abs(k)} * coalesce({'lag' if k < 0 else 'lead'}(v, {abs(k)}) over (partition by {C.KEY} order by pos), 0)" if k else "3 * v" for k in range(-2, 3))
for _kernel, _sql in (("triangle", _LAGS), ("none", "v")):
    register(f"select_kernel_{_kernel}", _kernel_sql(_sql))(
        lambda spark, sf_dir, k=_kernel: CC.per_span(selection.select_windows(CC.Core(spark, sf_dir).diff(), overflow="trim", kernel=k)))

_STRIDED = C.windows().replace("where true", "").replace("z.pos = a.pos + l - 1))", "z.pos = a.pos + l - 1 where a.pos % 3 = 0))")


@register("select_stride", C.core(C.SCORES, C.PAIRS, C.diff("auto"), _STRIDED, C.STOP, C.SPANS, tail="select doc_id, query_id, first_pos, last_pos from spn"))
def select_stride(spark, sf_dir):
    """Only every third window is a candidate."""
    return CC.per_span(selection.select_windows(CC.Core(spark, sf_dir).diff(), overflow="stop", stride=3))


# ---- question kinds on long documents, state and ZIP style questions, tiny budgets --------------------

def _science(spark, sf_dir) -> DataFrame:
    """Long documents, each with all its questions; a token and what parts it from the next take two characters."""
    return together.ask(W.load(spark, sf_dir, "documents"), X.science_of, 2 * X.LONG_TOKENS - 1)


@register("w2_kinds")
def w2_kinds(spark, sf_dir):
    """Questions and evidence spans of each kind."""
    asked = CC.held(spark, sf_dir, "science-asked", lambda: X.science_questions(W.load(spark, sf_dir, "documents")))
    return asked.groupBy("kind").agg(F.count("*").alias("n_queries"), F.sum(F.size("golds")).alias("n_spans"))


@register("w2_grid")
def w2_grid(spark, sf_dir):
    """All methods by kind of question, dispersed and counting ones among them."""
    rows = X.judged_pages(_science(spark, sf_dir)).withColumn("kind", F.regexp_replace("kind", "[0-9]", ""))
    return _budget(X.summary(rows, "meth", "kind", "b"))


@register("w8_science")
def w8_science(spark, sf_dir):
    """The contrast ablation on the science set: survival curves of evidence recall for raw, fixed and farthest."""
    rows = X.judged_pages(_science(spark, sf_dir), methods=X.REDUCERS).withColumn("recall", F.col("n_in") / F.col("n_gold"))
    return _budget(measures.survival_curve(rows, "recall", "meth", "b"))


def _notice(spark, sf_dir, budgets) -> DataFrame:
    pages = together.ask(W.load(spark, sf_dir, "documents"), lambda doc_id, text: W.field_of(doc_id, text, "notice"), 2 * W.FIELDS["notice"][1] - 1)
    return X.judged_pages(pages, budgets)


@register("w3_grid")
def w3_grid(spark, sf_dir):
    return _budget(X.summary(_notice(spark, sf_dir, X.BUDGETS), "meth", "b"))


@register("w10_grid")
def w10_grid(spark, sf_dir):
    """Budgets below one chunk: what retrieval spends at least stands beside the reducer."""
    return _budget(X.summary(_notice(spark, sf_dir, ("0.005", "0.01")), "meth", "b"))


# ---- tables -----------------------------------------------------------------------------------------

_ENTITIES = {
    "orders": ("lineitem", "l_orderkey", "l_partkey", ("l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus")),
    "supplier": ("supplier", "s_nationkey", "s_suppkey", ("s_name",)),
    "part": ("part", "p_brand", "p_partkey", ("p_name", "p_type", "p_size")),
}


def _entity(spark, sf_dir, name) -> tuple[DataFrame, DataFrame]:
    table, group, key, columns = _ENTITIES[name]
    rows = W.load(spark, sf_dir, table)
    tables = X.entity_tables(rows, group, key, columns)
    return tables, X.entity_questions(tables, key, columns)


def _entity_sql(name: str) -> str:
    """Accuracy of a reader that gets all rows: a plain join on the key."""
    table, group, key, columns = _ENTITIES[name]
    cells = " union all ".join(f"select {key} as k, {c}::varchar as gold from {table}" for c in columns)
    return f"select count(*) as n_queries from ({cells})"


def _entity_query(name: str):
    def run(spark, sf_dir):
        key = _ENTITIES[name][2]
        tables, asked = _entity(spark, sf_dir, name)
        ranked = materialize(rows.rank_rows(X.packed_tables(tables, asked), 4), "ranked")
        return X.table_accuracy(tables, asked, X.best_places(ranked), key, 4)

    return run


for _name in ("supplier", "part"):
    QUERIES[f"w4_{_name}"] = _entity_query(_name)
    register(f"w4_{_name}_questions", _entity_sql(_name))(lambda spark, sf_dir, n=_name: _entity(spark, sf_dir, n)[1].agg(F.count("*").alias("n_queries")))


# ---- cost -------------------------------------------------------------------------------------------

@register("runtime_ledger", C.core(C.SCORES, CC._CH, "cc as (select doc_id, count(distinct pos // 256) as chunks from tk group by 1), nq as (select doc_id, count(*) as k from q group by 1)",
          tail="""select 'embed_' || e as step, count(*) as n_units, sum(z - a)::bigint as n_tokens from och, (values ('unigram'), ('trigram'), ('tfidf')) as x(e) group by e
 union all select 'attend', sum(chunks * k)::bigint, sum(n * k)::bigint from dn join cc using (doc_id) join nq using (doc_id)
 union all select 'encode', sum(chunks)::bigint, sum(n)::bigint from dn join cc using (doc_id)"""))
def runtime_ledger(spark, sf_dir):
    """What each step has to read: chunks embedded for each embedder, chunks encoded once, and pairs of chunk and question attended."""
    c = CC.Core(spark, sf_dir)
    over = retrieval.chunk_overlap(c.tok).agg(F.count("*").alias("n_units"), F.sum(F.col("last_pos") - F.col("first_pos")).cast("long").alias("n_tokens"))
    embed = over.select(F.explode(F.array(*[F.lit(f"embed_{k}") for k in X.EMBEDDERS])).alias("step"), "n_units", "n_tokens")
    own = chunking.chunk(c.tok).groupBy("doc_id").agg(F.count("*").alias("chunks"), F.sum("n_chunk").alias("n")).join(c.questions.groupBy("doc_id").agg(F.count("*").alias("k")), "doc_id")
    attend = own.agg(F.sum(F.col("chunks") * F.col("k")).alias("n_units"), F.sum(F.col("n") * F.col("k")).alias("n_tokens")).select(F.lit("attend").alias("step"), "*")
    encode = own.agg(F.sum("chunks").alias("n_units"), F.sum("n").alias("n_tokens")).select(F.lit("encode").alias("step"), "*")
    return embed.unionByName(attend).unionByName(encode)


def timed_attention(spark, sf_dir, reuse: bool) -> int:
    """One pass of attention over the passage questions with or without remembered chunks; the number of vectors."""
    c = CC.Core(spark, sf_dir)
    vectors = attention.PopcountProvider().attend(chunking.chunk(c.tok), c.questions, reuse=reuse)
    return vectors.agg(F.sum(F.size("s")).alias("n")).first().n


# ---- the reducer on streams, in user functions, over checked tables -----------------------------------

SPAN_ROWS = "doc_id long, query_id string, first_pos int, last_pos int"


def _turn_spans(docs: DataFrame, asked: DataFrame) -> DataFrame:
    tok = W.asked_documents(docs, asked)
    diff = R.contrasted(R.vectors(tok, asked), asked, "fixed")
    return CC.per_span(selection.select_windows(diff, overflow="trim"))


_TURNS = f"""asked as (select conv_id as doc_id, string_agg(text, chr(10) order by turn, text) as text from conversations where role <> 'user' group by 1),
lns as (select doc_id, unnest(range(len(ls))) as ln, unnest(ls) as l from (select doc_id, string_split(text, chr(10)) as ls from asked)),
lt as (select doc_id, ln, regexp_extract_all(l, {C.T}) as ts from lns),
q as (select conv_id as doc_id, 'u' || turn || '@' || conv_id as query_id, regexp_extract_all(text, {C.T}) as toks from conversations where role = 'user'),
aq as (select doc_id, query_id, toks from q union all select distinct doc_id, 'fixed@' || doc_id, {C.FIXED} from q)"""


@register("stream_reduce_questions", "with recursive " + ",\n".join([_TURNS, C.SCORES, C.diff("fixed"), C.windows(), C.TRIM, C.SPANS]) + "\nselect doc_id, query_id, first_pos, last_pos from spn")
def stream_reduce_questions(spark, sf_dir):
    """User turns arrive as a stream; every micro-batch is reduced over the static conversations."""
    from gistloom.streaming import questions as S

    docs = W.conversation_documents(W.load(spark, sf_dir, "conversations"))
    turns = S.source(spark, sf_dir, "conversations")
    return S.questions_in_batches(turns, lambda rows: _turn_spans(docs, R.materialize(W.conversation_questions(rows), "turns")), SPAN_ROWS)


def _greedy_rows(doc_id, query_id, pos, v):
    import numpy as np
    import pyarrow as pa

    order = np.argsort(pos)
    found = selection.spans_of(selection.choose(selection.smooth(np.asarray(v)[order]), "0.1"))
    return pa.table({"doc_id": pa.array([doc_id] * len(found), pa.int64()), "query_id": pa.array([query_id] * len(found), pa.string()), "first_pos": pa.array([a for a, _ in found], pa.int32()), "last_pos": pa.array([z for _, z in found], pa.int32())})


@register("udf_grouped", CC.ORACLES["select_skip"])
def udf_grouped(spark, sf_dir):
    """Greedy selection as a grouped function over rows of tokens."""
    def run(table):
        return _greedy_rows(table["doc_id"][0].as_py(), table["query_id"][0].as_py(), table["pos"].to_numpy(), table["v"].to_numpy())

    rows = CC.per_token(CC.Core(spark, sf_dir).diff())
    return rows.groupBy("doc_id", "query_id").applyInArrow(run, SPAN_ROWS)


@register("udf_cogrouped", C.core(C.SCORES, tail="select doc_id, query_id, c::int as chunk_no, sum(s)::bigint as total from raw join q using (doc_id, query_id) group by all"))
def udf_cogrouped(spark, sf_dir):
    """Chunks and questions of a document meet in a cogrouped function that attends."""
    import numpy as np
    import pyarrow as pa

    def run(chunks, asked):
        if not len(asked):
            return pa.table({"doc_id": pa.array([], pa.int64()), "query_id": pa.array([], pa.string()), "chunk_no": pa.array([], pa.int32()), "total": pa.array([], pa.int64())})
        pack = attention._Pack(asked["query_id"].to_pylist(), asked["tokens"].to_pylist())
        out = []
        for r in chunks.to_pylist():
            s = pack.scores(attention.keys_of(r["tokens"]), np.array(r["structural"], bool), attention.ALL_LAYERS, attention.ALL_HEADS)
            out += [(r["doc_id"], q, r["chunk_no"], int(x)) for q, x in zip(pack.ids, s.sum(1), strict=True)]
        kinds = (pa.int64(), pa.string(), pa.int32(), pa.int64())
        return pa.table([pa.array([o[k] for o in out], kind) for k, kind in enumerate(kinds)], names=["doc_id", "query_id", "chunk_no", "total"])

    c = CC.Core(spark, sf_dir)
    asked = c.questions.select(F.col("doc_id").alias("asked_id"), "query_id", "tokens")
    return c.chunks.groupBy("doc_id").cogroup(asked.groupBy("asked_id")).applyInArrow(run, "doc_id long, query_id string, chunk_no int, total long")


@register("udtf_reduce_context", CC.ORACLES["select_skip"])
def udtf_reduce_context(spark, sf_dir):
    """Table function with a partitioned table argument: rows of tokens in, spans under a budget out."""
    from pyspark.sql.functions import udtf
    from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType
    from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

    spans = StructType([StructField("doc_id", LongType()), StructField("query_id", StringType()), StructField("first_pos", IntegerType()), StructField("last_pos", IntegerType())])

    @udtf
    class ReduceContext:
        def __init__(self):
            self.rows, self.budget = [], None

        @staticmethod
        def analyze(tokens: AnalyzeArgument, budget: AnalyzeArgument) -> AnalyzeResult:
            if not tokens.isTable or {"doc_id", "query_id", "pos", "v"} - set(tokens.dataType.names):
                raise ValueError("the first argument is a table with doc_id, query_id, pos and v")
            if budget.value is None:
                raise ValueError("the budget is a constant")
            return AnalyzeResult(spans)

        def eval(self, tokens, budget: str):
            self.rows.append((tokens["doc_id"], tokens["query_id"], tokens["pos"], tokens["v"]))
            self.budget = budget

        def terminate(self):
            if self.rows:
                import numpy as np

                ordered = sorted(self.rows, key=lambda r: r[2])
                v = np.array([r[3] for r in ordered], np.int64)
                for a, z in selection.spans_of(selection.choose(selection.smooth(v), self.budget)):
                    yield ordered[0][0], ordered[0][1], a, z

    spark.udtf.register("gl_reduce_context", ReduceContext)
    rows = CC.per_token(CC.Core(spark, sf_dir).diff())
    return spark.sql("select * from gl_reduce_context(table({rows}) partition by (doc_id, query_id), '0.1')", rows=rows)


@register("load_checked", "select count(*) as n, count(distinct lang) as langs from documents")
def load_checked(spark, sf_dir):
    from gistloom.sources.checked import load_checked as checked

    docs = checked(spark, f"{sf_dir}/documents.parquet", "doc_id bigint, text string, lang string")
    return docs.agg(F.count("*").alias("n"), F.count_distinct("lang").alias("langs"))


# ---- structural noise in web pages --------------------------------------------------------------------

def _page_text(html):
    """Tags as tokens of their own, every paragraph a line."""
    spaced = F.regexp_replace(html, "<[^>]*>", " $0 ")
    return F.regexp_replace(F.regexp_replace(spaced, "<p>", "\n<p>"), "</p>", "</p>\n")


def _pages(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """Pages as documents, and their titles as questions with the paragraphs as evidence."""
    pages = W.load(spark, sf_dir, "pages").where("html is not null")
    docs = pages.select(F.col("page_id").alias("doc_id"), _page_text(F.col("html")).alias("text"))
    title = words(F.regexp_extract("html", "<title>([^<]*)</title>", 1))
    asked = pages.select(F.col("page_id").alias("doc_id"), F.concat(F.lit("title@"), F.col("page_id").cast("string")).alias("query_id"), title.alias("tokens")).where(F.size("tokens") > 0)
    lines = W.lines_of(docs, least=1).where(F.col("ts")[0] == "<p>")
    span = F.struct(F.col("off").cast("int").alias("first_pos"), (F.col("off") + F.size("ts")).cast("int").alias("last_pos"))
    golds = lines.groupBy("doc_id").agg(F.array_sort(F.collect_list(span)).alias("golds"))
    return docs, asked.join(golds, "doc_id")


_PAGES = rf"""asked as (select page_id as doc_id, regexp_replace(regexp_replace(regexp_replace(html, '<[^>]*>', ' \0 ', 'g'), '<p>', chr(10) || '<p>', 'g'), '</p>', '</p>' || chr(10), 'g') as text, html from pages where html is not null),
lns as (select doc_id, unnest(range(len(ls))) as ln, unnest(ls) as l from (select doc_id, string_split(text, chr(10)) as ls from asked)),
lt as (select doc_id, ln, regexp_extract_all(l, {C.T}) as ts from lns),
gp as (select doc_id, row_number() over (partition by doc_id order by ln, i) - 1 as pos, ts[1] = '<p>' as gold from (select doc_id, ln, ts, unnest(range(len(ts))) as i from lt)),
q as (select doc_id, 'title@' || doc_id as query_id, regexp_extract_all(regexp_extract(html, '<title>([^<]*)</title>', 1), {C.T}) as toks from asked
  where len(regexp_extract_all(regexp_extract(html, '<title>([^<]*)</title>', 1), {C.T})) > 0 and doc_id in (select doc_id from gp where gold)),
aq as (select doc_id, query_id, toks from q union all select distinct doc_id, 'fixed@' || doc_id, {C.FIXED} from q)"""


@register("w6_questions", "with recursive " + _PAGES + "\nselect query_id, len(toks)::int as n, (select count(*) from gp where gp.doc_id = q.doc_id and gold) as n_gold from q")
def w6_questions(spark, sf_dir):
    size = F.aggregate("golds", F.lit(0).cast("long"), lambda s, g: s + g["last_pos"] - g["first_pos"])
    return _pages(spark, sf_dir)[1].select("query_id", F.size("tokens").alias("n"), size.alias("n_gold"))


@register("w6_noise_share", "with recursive " + ",\n".join([_PAGES, C.SCORES, C.diff("raw", "fixed"), C.windows(("0.1", "0.2")), C.TRIM])
          + "\nselect meth, b::double as budget, count(distinct query_id) as n_queries, round(1 - sum(gold::int) / count(*), 6) as noise from kept join gp using (doc_id, pos) group by meth, b")
def w6_noise_share(spark, sf_dir):
    """Share of the kept tokens that are tags, navigation, script or advertisement, without and with the contrast."""
    docs, asked = _pages(spark, sf_dir)
    asked = CC.held(spark, sf_dir, "pages-asked", lambda: asked)
    tok = CC.held(spark, sf_dir, "pages-tok", lambda: W.asked_documents(docs, asked))
    scores = CC.held(spark, sf_dir, "pages-scores", lambda: R.vectors(tok, asked))
    found = X.judged(X.contexts(tok, asked, scores, ("0.1", "0.2"), ("raw", "fixed")), asked)
    return _budget(found.groupBy("meth", "b").agg(F.count_distinct("query_id").alias("n_queries"), F.round(1 - F.sum("n_in") / F.sum("n_used"), 6).alias("noise")))
