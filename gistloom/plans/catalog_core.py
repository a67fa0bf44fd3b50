"""Queries of the reducer, its baselines, measures and workloads, each with its DuckDB statement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gistloom.functions.tokens import tokenize, words
from gistloom.operators import attention, chunking, measures, retrieval, rows, scoring, selection
from gistloom.plans import core_sql as C
from gistloom.plans import experiments as X
from gistloom.plans import reduce as R
from gistloom.plans import workloads as W

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
_HELD: dict = {}
T = C.T


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def held(spark: SparkSession, sf_dir: str, name: str, build) -> DataFrame:
    """Shared prefixes of the queries, persisted for the session that asked first, until ``let_go``."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _HELD:
        _HELD[key] = build().persist()
    return _HELD[key]


def let_go() -> None:
    """Free what ``held`` keeps; the next query builds it anew."""
    while _HELD:
        _HELD.popitem()[1].unpersist()


class Core:
    """Documents that contain a benchmark passage, three kinds of questions on them, and their scores."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf = spark, sf_dir
        self.docs = W.load(spark, sf_dir, "documents")

    def _held(self, name, build):
        return held(self.spark, self.sf, name, build)

    @property
    def questions(self) -> DataFrame:
        return self._held("questions", lambda: W.passage_questions(self.docs, W.load(self.spark, self.sf, "benchmark")))

    @property
    def tok(self) -> DataFrame:
        return self._held("tok", lambda: W.asked_documents(self.docs, self.questions))

    @property
    def chunks(self) -> DataFrame:
        return chunking.chunk(self.tok)

    @property
    def raw(self) -> DataFrame:
        return self._held("raw", lambda: attention.PopcountProvider().attend(self.chunks, R.all_queries(self.questions)))

    @property
    def scores(self) -> DataFrame:
        return self._held("scores", lambda: scoring.reconstruct(scoring.scale_by_chunk(self.raw)))

    def diff(self, contrast: str = "auto") -> DataFrame:
        return self._held(f"diff-{contrast}", lambda: R.contrasted(self.scores, self.questions, contrast))


def per_token(df: DataFrame, value: str = "v") -> DataFrame:
    keep = [c for c in df.columns if c not in (value, "contrast_id", "contrast_kind")]
    return df.select(*keep, F.posexplode(value).alias("pos", "v"))


def per_span(df: DataFrame) -> DataFrame:
    return df.select("doc_id", "query_id", F.explode("spans").alias("s")).select("doc_id", "query_id", "s.first_pos", "s.last_pos")


def spans_sql(rule: str, budgets=("0.1",), kind: str = "auto", **shape) -> str:
    return C.core(C.SCORES, C.PAIRS, C.diff(kind), C.windows(budgets, **shape), rule, C.SPANS, tail="select doc_id, query_id, first_pos, last_pos from spn")


# ---- tokens, chunks, attention ----------------------------------------------------------------------

@register("tokenize_documents", f"select doc_id, len(ts)::int as n_tokens, md5(array_to_string(ts, ' ')) as tokens_md5 from (select doc_id, regexp_extract_all(text, {T}) as ts from documents)")
def tokenize_documents(spark, sf_dir):
    t = tokenize(W.load(spark, sf_dir, "documents"))
    return t.select("doc_id", "n_tokens", F.md5(F.array_join("tokens", " ")).alias("tokens_md5"))


for _kind, _sql in (("wordpunct", "len(regexp_extract_all(text, '[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]'))"), ("trigram", "greatest(length(text) - 2, 0)"),
                    ("piece", f"list_sum(list_transform(regexp_extract_all(text, {T}), lambda t: ceil(length(t) / 4.0)::int))")):
    register(f"tokenize_{_kind}", f"select doc_id, ({_sql})::int as n_tokens from documents")(
        lambda spark, sf_dir, k=_kind: tokenize(W.load(spark, sf_dir, "documents"), kind=k).select("doc_id", "n_tokens"))

_CHUNKS = f"""with t as (select doc_id, regexp_extract_all(text, {T}) as ts from documents),
c as (select doc_id, s // 256 as chunk_no, s as start_pos, ts[s + 1:s + 256] as ts from t, unnest(range(0, len(ts), 256)) as r(s))"""


@register("chunk_documents", _CHUNKS + " select doc_id, chunk_no::int as chunk_no, start_pos::int as start_pos, len(ts)::int as n_chunk, md5(array_to_string(ts, ' ')) as chunk_hash from c")
def chunk_documents(spark, sf_dir):
    return chunking.chunk(tokenize(W.load(spark, sf_dir, "documents"))).select("doc_id", "chunk_no", "start_pos", "n_chunk", "chunk_hash")


@register("chunk_short_docs", f"select doc_id, len(ts)::int as n_chunk from (select doc_id, regexp_extract_all(text, {T}) as ts from documents) where len(ts) between 1 and 255")
def chunk_short_docs(spark, sf_dir):
    return chunking.chunk(tokenize(W.load(spark, sf_dir, "documents"))).where("start_pos = 0 and n_chunk < 256").select("doc_id", "n_chunk")


@register("prompt_layout", C.core(tail=f"""select query_id, s // 256 as chunk_no, md5(array_to_string(ts[s + 1:s + 256], ' ') || chr(10) || 'Question:' || chr(10) || array_to_string(toks, ' ') || chr(10) || 'Answer:') as prompt_md5
  from (select q.query_id, q.toks, regexp_extract_all(a.text, {T}) as ts from q join asked a using (doc_id)), unnest(range(0, len(ts), 256)) as r(s)"""))
def prompt_layout(spark, sf_dir):
    c = Core(spark, sf_dir)
    return attention.pair(c.chunks, c.questions).select("query_id", F.col("chunk_no").cast("long").alias("chunk_no"), F.md5(chunking.layout()).alias("prompt_md5"))


@register("attention_weights", C.core(C.SCORES, tail="select query_id, k::int as q_pos, layer::int as layer, head::int as head, sum(w)::bigint as mass, max(w)::bigint as top from wt join q using (doc_id, query_id) group by all"))
def attention_weights(spark, sf_dir):
    c = Core(spark, sf_dir)
    w = attention.PopcountProvider().exploded(c.chunks, c.questions)
    return w.groupBy("query_id", "q_pos", "layer", "head").agg(F.sum("w").alias("mass"), F.max("w").alias("top"))


@register("mass_conservation", C.core(C.SCORES, tail="""select query_id, bool_and(tot <= 1000000000 and tot > 1000000000 - 400) as conserved, max(1000000000 - tot)::bigint > 0 as floored from
  (select pr.query_id, pr.k, pr.layer, pr.head, pr.c, sum(e::hugeint * 1000000000 // den) + any_value(oe.s) + 16777216::hugeint * 1000000000 // any_value(den) as tot from pr join dnm using (query_id, k, layer, head, c) join q using (doc_id, query_id)
   join (select a.query_id, a.k, a.layer, a.head, d.c, sum(""" + C.E + """[bit_count(xor(a.w, b.w)) + 1]::hugeint * 1000000000 // d.den) as s from qw a join qw b on a.query_id = b.query_id and a.layer = b.layer and a.head = b.head and b.k <= a.k
     join dnm d on d.query_id = a.query_id and d.k = a.k and d.layer = a.layer and d.head = a.head group by all) oe on oe.query_id = pr.query_id and oe.k = pr.k and oe.layer = pr.layer and oe.head = pr.head and oe.c = pr.c group by all) group by query_id"""))
def mass_conservation(spark, sf_dir):
    c = Core(spark, sf_dir)
    w = attention.PopcountProvider().exploded(c.chunks, c.questions).withColumn("c", F.floor(F.col("pos") / 256))
    total = w.groupBy("query_id", "q_pos", "layer", "head", "c").agg((F.sum("w") + F.max("rest")).alias("tot"))
    short = F.lit(10**9) - F.col("tot")
    return total.groupBy("query_id").agg(F.bool_and((short >= 0) & (short < 400)).alias("conserved"), (F.max(short) > 0).alias("floored"))


def _vector_sql(select: str, *more: str) -> str:
    return C.core(C.SCORES, *more, tail=select)


@register("raw_scores", _vector_sql("select doc_id, query_id, pos::int as pos, s as v from raw join q using (doc_id, query_id)"))
def raw_scores(spark, sf_dir):
    c = Core(spark, sf_dir)
    rows = c.raw.join(c.questions.select("query_id"), "query_id", "left_semi").select("doc_id", "query_id", "chunk_no", F.posexplode("s").alias("at", "v"))
    return rows.select("doc_id", "query_id", (F.col("chunk_no") * 256 + F.col("at")).cast("int").alias("pos"), "v")


@register("raw_scores_one_layer", _vector_sql("select doc_id, query_id, pos::int as pos, sum(w)::bigint as v from wt join q using (doc_id, query_id) where layer = 1 and head in (0, 2) group by all"))
def raw_scores_one_layer(spark, sf_dir):
    c = Core(spark, sf_dir)
    s = attention.PopcountProvider().attend(c.chunks, c.questions, layers=(1,), heads=(0, 2))
    return s.select("doc_id", "query_id", "chunk_no", F.posexplode("s").alias("at", "v")).select("doc_id", "query_id", (F.col("chunk_no") * 256 + F.col("at")).cast("int").alias("pos"), "v")


@register("chunk_scaled_scores", _vector_sql("select doc_id, query_id, (pos // 256)::int as chunk_no, sum(v)::bigint as total, max(v)::bigint as top from sc join q using (doc_id, query_id) group by all"))
def chunk_scaled_scores(spark, sf_dir):
    c = Core(spark, sf_dir)
    s = scoring.scale_by_chunk(c.raw).join(c.questions.select("query_id"), "query_id", "left_semi")
    return s.select("doc_id", "query_id", "chunk_no", F.aggregate("s", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.array_max("s").alias("top"))


@register("chunk_unscaled_tail", _vector_sql("""select doc_id, query_id, round(max(case when c = z then m end) / nullif(avg(case when c < z then m end), 0), 6) as raw_ratio, round(max(case when c = z then m * n_chunk end) / nullif(avg(case when c < z then m * n_chunk end), 0), 6) as scaled_ratio
  from (select doc_id, query_id, raw.c, max(raw.c) over (partition by doc_id, query_id) as z, avg(s) as m from raw join q using (doc_id, query_id) group by doc_id, query_id, raw.c) join cn using (doc_id, c) where z > 0 group by all"""))
def chunk_unscaled_tail(spark, sf_dir):
    """Mean score of a short last chunk against the full ones, without and with the length scaling."""
    c = Core(spark, sf_dir)
    mean = F.aggregate("s", F.lit(0).cast("long"), lambda a, x: a + x) / F.size("s")
    m = c.raw.join(c.questions.select("query_id"), "query_id", "left_semi").select("doc_id", "query_id", "chunk_no", "n_chunk", mean.alias("m"))
    m = m.withColumn("z", F.max("chunk_no").over(Window.partitionBy("doc_id", "query_id"))).where("z > 0")
    ratio = lambda x: F.round(F.max(F.when(F.col("chunk_no") == F.col("z"), x)) / F.avg(F.when(F.col("chunk_no") < F.col("z"), x)), 6)
    return m.groupBy("doc_id", "query_id").agg(ratio(F.col("m")).alias("raw_ratio"), ratio(F.col("m") * F.col("n_chunk")).alias("scaled_ratio"))


@register("document_scores", _vector_sql("select doc_id, query_id, pos::int as pos, v from sc join q using (doc_id, query_id)"))
def document_scores(spark, sf_dir):
    c = Core(spark, sf_dir)
    return per_token(c.scores.join(c.questions.select("query_id"), "query_id", "left_semi").select("doc_id", "query_id", "v"))


_CONV = f"""with d as (select conv_id as doc_id, string_agg(text, chr(10) order by turn) as text from conversations where role <> 'user' group by conv_id),
uq as (select conv_id as doc_id, count(*) as n_queries from conversations where role = 'user' group by conv_id),
t as (select doc_id, regexp_extract_all(text, {T}) as ts from d),
c as (select doc_id, md5(array_to_string(ts[s + 1:s + 256], ' ')) as h, len(ts[s + 1:s + 256]) as n from t, unnest(range(0, len(ts), 256)) as r(s))"""


def _conversation_chunks(spark, sf_dir):
    turns = W.load(spark, sf_dir, "conversations")
    return chunking.chunk(tokenize(W.conversation_documents(turns))), W.conversation_questions(turns)


@register("kv_cache_entries", _CONV + " select doc_id, h as chunk_hash, any_value(n)::int as n_keys from c group by all")
def kv_cache_entries(spark, sf_dir):
    chunks, _ = _conversation_chunks(spark, sf_dir)
    return attention.PopcountProvider().encode(chunks).select("doc_id", "chunk_hash", (F.size("keys") / 12).cast("int").alias("n_keys"))


@register("kv_cache_scope", _CHUNKS + " select count(*) as chunks, count(distinct (doc_id, md5(array_to_string(ts, ' ')))) as scoped, count(distinct md5(array_to_string(ts, ' '))) as unscoped from c")
def kv_cache_scope(spark, sf_dir):
    c = chunking.chunk(tokenize(W.load(spark, sf_dir, "documents")))
    return c.agg(F.count("*").alias("chunks"), F.count_distinct("doc_id", "chunk_hash").alias("scoped"), F.count_distinct("chunk_hash").alias("unscoped"))


@register("kv_cache_ledger", _CONV + " select doc_id, count(*) as n_chunks, any_value(n_queries) as n_queries, count(*) * any_value(n_queries) as lookups, count(distinct h) as misses, count(*) * any_value(n_queries) - count(distinct h) as hits from c join uq using (doc_id) group by doc_id")
def kv_cache_ledger(spark, sf_dir):
    return attention.cache_ledger(*_conversation_chunks(spark, sf_dir))


@register("w5_cache", _CONV + " select sum(l)::bigint as lookups, sum(m)::bigint as misses, sum(l - m)::bigint as hits, round(sum(l - m) / sum(n_queries), 6) as hits_per_query from (select any_value(n_queries) as n_queries, count(*) * any_value(n_queries) as l, count(distinct h) as m from c join uq using (doc_id) group by doc_id)")
def w5_cache(spark, sf_dir):
    led = attention.cache_ledger(*_conversation_chunks(spark, sf_dir))
    return led.agg(F.sum("lookups").alias("lookups"), F.sum("misses").alias("misses"), F.sum("hits").alias("hits"), F.round(F.sum("hits") / F.sum("n_queries"), 6).alias("hits_per_query"))


@register("prefill_cost", _CONV + " select doc_id, sum(n)::bigint as tokens_once, (sum(n) * any_value(n_queries))::bigint as tokens_every_time from c join uq using (doc_id) group by doc_id")
def prefill_cost(spark, sf_dir):
    chunks, asked = _conversation_chunks(spark, sf_dir)
    n = asked.groupBy("doc_id").agg(F.count("*").alias("k"))
    return chunks.join(n, "doc_id").groupBy("doc_id").agg(F.sum("n_chunk").alias("tokens_once"), (F.sum("n_chunk") * F.max("k")).alias("tokens_every_time"))


# ---- normalisation and contrast ---------------------------------------------------------------------

@register("query_normalized", _vector_sql("select query_id, round(sum(v) / (256.0 * any_value(m)) / 1e9, 6) as mass from sc join tq using (query_id) join q using (doc_id, query_id) group by all"))
def query_normalized(spark, sf_dir):
    c = Core(spark, sf_dir)
    n = c.questions.select("query_id", F.size("tokens").alias("m"))
    total = F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x)
    return c.scores.join(n, "query_id").select("query_id", F.round(total / (256.0 * F.col("m")) / 1e9, 6).alias("mass"))


@register("query_unnormalized", _vector_sql("select query_id, len(any_value(q.toks))::int as n_query, sum(v)::bigint as mass from sc join q using (doc_id, query_id) group by all"))
def query_unnormalized(spark, sf_dir):
    c = Core(spark, sf_dir)
    n = c.questions.select("query_id", F.size("tokens").alias("n_query"))
    return c.scores.join(n, "query_id").select("query_id", "n_query", F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x).alias("mass"))


_D = "select doc_id, query_id, pos::int as pos, v from d"


@register("differential_scores", C.core(C.SCORES, C.PAIRS, C.diff("auto"), tail=_D))
def differential_scores(spark, sf_dir):
    return per_token(Core(spark, sf_dir).diff())


@register("differential_unnormalized", C.core(C.SCORES, C.PAIRS, C.diff("auto", norm=False), tail=_D))
def differential_unnormalized(spark, sf_dir):
    c = Core(spark, sf_dir)
    return per_token(R.contrasted(c.scores, c.questions, "auto", query_norm="none"))


@register("farthest_query", C.core(C.PAIRS, tail="select doc_id, query_id, contrast_id, similarity from far"))
def farthest_query(spark, sf_dir):
    return scoring.farthest(Core(spark, sf_dir).questions)


@register("mirror_pairs", C.core(C.PAIRS, tail="select a.doc_id, a.query_id, a.contrast_id from far a join far b on b.query_id = a.contrast_id and b.contrast_id = a.query_id where a.query_id < a.contrast_id"))
def mirror_pairs(spark, sf_dir):
    far = scoring.farthest(Core(spark, sf_dir).questions).select("doc_id", "query_id", "contrast_id")
    back = far.select(F.col("query_id").alias("contrast_id"), F.col("contrast_id").alias("query_id"))
    return far.join(back, ["query_id", "contrast_id"]).where("query_id < contrast_id").select("doc_id", "query_id", "contrast_id")


@register("contrast_fallback", C.core(C.PAIRS, tail="select doc_id, query_id, contrast_id, contrast_kind from pick"))
def contrast_fallback(spark, sf_dir):
    return scoring.contrast_pairs(Core(spark, sf_dir).questions, "auto")


# ---- selection --------------------------------------------------------------------------------------

def _spans(contrast="auto", budgets=("0.1",), **options):
    return lambda spark, sf_dir: per_span(selection.select_windows(Core(spark, sf_dir).diff(contrast), budgets, **options))


register("select_raw", spans_sql(C.TRIM, kind="raw"))(_spans("raw", overflow="trim"))
register("select_fixed_contrast", spans_sql(C.TRIM, kind="fixed"))(_spans("fixed", overflow="trim"))
register("select_trim", spans_sql(C.TRIM))(_spans(overflow="trim"))
register("select_stop", spans_sql(C.STOP))(_spans(overflow="stop"))
register("select_skip", spans_sql(C.SKIP))(_spans(overflow="skip"))
register("merged_spans", spans_sql(C.SKIP, ("0.2",)))(_spans(budgets=("0.2",)))
register("select_single_window", spans_sql(C.TRIM, ("0.01",)))(_spans(budgets=("0.01",)))
register("select_full_budget", spans_sql(C.TRIM, ("1",)))(_spans(budgets=("1",)))
register("select_isolated_tokens", spans_sql(C.TRIM, isolated=True))(_spans(overflow="trim", isolated=True))
register("select_single_long_span", spans_sql(C.TRIM, single=True))(_spans(overflow="trim", single=True))


@register("smoothed_scores", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), tail="select query_id, sum(v)::bigint as total, max(v)::bigint as top, min(v)::bigint as low from sm group by all"))
def smoothed_scores(spark, sf_dir):
    v = per_token(Core(spark, sf_dir).diff())
    near = Window.partitionBy("query_id").orderBy("pos").rowsBetween(-2, 2)
    s = v.withColumn("v", F.sum("v").over(near))
    return s.groupBy("query_id").agg(F.sum("v").alias("total"), F.max("v").alias("top"), F.min("v").alias("low"))


@register("window_length", f"""select doc_id, b::double as budget, least(ceil(b * n), ceil(0.02::decimal(9,6) * n))::int as window_len, ceil(b * n)::int as budget_tokens
  from (select doc_id, len(regexp_extract_all(text, {T})) as n from documents), (select unnest([0.005, 0.02, 0.07, 0.1, 1]::decimal(9,6)[]) as b)""")
def window_length(spark, sf_dir):
    n = tokenize(W.load(spark, sf_dir, "documents")).select("doc_id", "n_tokens")
    b = F.explode(F.array(*[F.lit(x).cast("decimal(9,6)") for x in ("0.005", "0.02", "0.07", "0.1", "1")])).alias("b")
    return n.select("doc_id", "n_tokens", b).select("doc_id", F.col("b").cast("double").alias("budget"), selection.window_len(F.col("n_tokens"), F.col("b")).alias("window_len"), selection.budget_tokens(F.col("n_tokens"), F.col("b")).alias("budget_tokens"))


@register("window_scores", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), tail="select doc_id, query_id, start::int as start, score::bigint as score, rnk::int as place from ws where rnk <= 20"))
def window_scores(spark, sf_dir):
    """Ranked windows by window functions only: prefix sums, then the first twenty of each query (a report)."""
    c = Core(spark, sf_dir)
    by = Window.partitionBy("doc_id", "query_id").orderBy("pos")
    v = per_token(c.diff()).withColumn("v", F.sum("v").over(by.rowsBetween(-2, 2)))
    v = v.join(c.tok.select("doc_id", selection.window_len(F.col("n_tokens"), F.lit("0.1")).alias("l")), "doc_id").withColumn("p", F.sum("v").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    ends = v.select("doc_id", "query_id", F.col("pos").alias("end"), F.col("p").alias("pe"))
    w = v.withColumn("end", F.col("pos") + F.col("l") - 1).join(ends, ["doc_id", "query_id", "end"]).select("doc_id", "query_id", F.col("pos").alias("start"), (F.col("pe") - F.col("p") + F.col("v")).alias("score"))
    place = F.row_number().over(Window.partitionBy("doc_id", "query_id").orderBy(F.desc("score"), "start"))
    return w.withColumn("place", place).where("place <= 20")


_PROMPT = "pt as (select query_id, doc_id, b, first_pos, string_agg(tok, ' ' order by pos) as piece from spn join tk using (doc_id) where pos >= first_pos and pos < last_pos group by all)"
_PROMPT_TAIL = "select query_id, string_agg(piece, ' [...] ' order by first_pos) as prompt from pt group by query_id"


def _prompt_sql(tail: str, rule: str = C.SKIP) -> str:
    return C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), rule, C.SPANS, _PROMPT, f"prm as ({_PROMPT_TAIL})", tail=tail)


@register("reduced_prompt", _prompt_sql("select query_id, prompt from prm"))
def reduced_prompt(spark, sf_dir):
    c = Core(spark, sf_dir)
    return selection.assemble(c.tok, selection.select_windows(c.diff())).select("query_id", "prompt")


@register("reduce_flagship", _prompt_sql("select prm.query_id, prompt, (len(regexp_extract_all(replace(prompt, ' [...] ', ' '), " + T + ")))::int as used from prm"))
def reduce_flagship(spark, sf_dir):
    docs, passages = W.load(spark, sf_dir, "documents"), W.load(spark, sf_dir, "benchmark")
    return R.reduce(docs, W.passage_questions(docs, passages)).select("query_id", "prompt", "used")


@register("multi_query_reduce", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), C.TRIM, tail="select doc_id, count(distinct query_id) as n_queries, count(*) as kept_tokens, count(distinct pos) as distinct_tokens from kept group by doc_id"))
def multi_query_reduce(spark, sf_dir):
    s = selection.select_windows(Core(spark, sf_dir).diff(), overflow="trim")
    pos = s.select("doc_id", "query_id", F.explode("spans").alias("x")).select("doc_id", "query_id", F.explode(F.sequence("x.first_pos", F.col("x.last_pos") - 1)).alias("pos"))
    return pos.groupBy("doc_id").agg(F.count_distinct("query_id").alias("n_queries"), F.count("*").alias("kept_tokens"), F.count_distinct("pos").alias("distinct_tokens"))


# ---- units and tables -------------------------------------------------------------------------------

def _unit_query(rule: str):
    def run(spark, sf_dir):
        c = Core(spark, sf_dir)
        if rule == "line":
            starts = c.docs.join(c.tok.select("doc_id"), "doc_id", "left_semi").select("doc_id", F.posexplode(F.filter(F.transform(F.split("text", "\n"), lambda x: F.size(words(x))), lambda n: n > 0)).alias("unit_no", "n"))
            first = F.coalesce(F.sum("n").over(Window.partitionBy("doc_id").orderBy("unit_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
            units = starts.select("doc_id", "unit_no", first.cast("int").alias("first_pos"), F.col("n").cast("int").alias("n"))
        else:
            t = c.tok.select("doc_id", F.posexplode("tokens").alias("pos", "tok"))
            order = Window.partitionBy("doc_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
            numbered = t.withColumn("unit_no", F.coalesce(F.sum(F.col("tok").rlike("[.!?]$").cast("int")).over(order), F.lit(0)).cast("int"))
            units = numbered.groupBy("doc_id", "unit_no").agg(F.min("pos").alias("first_pos"), F.count("*").cast("int").alias("n"))
        slices = c.diff().join(units, "doc_id").select("doc_id", "query_id", "unit_no", "first_pos", "n", F.aggregate(F.slice("v", F.col("first_pos") + 1, F.col("n")), F.lit(0).cast("long"), lambda a, x: a + x).alias("score"))
        return slices.select("doc_id", "query_id", "unit_no", "first_pos", (F.col("first_pos") + F.col("n")).alias("last_pos"), "score")

    return run


_UNIT_TAIL = "select doc_id, query_id, unit_no::int as unit_no, min(pos)::int as first_pos, (max(pos) + 1)::int as last_pos, sum(v)::bigint as score from d join un using (doc_id, pos) group by all"
register("unit_line", C.core(C.SCORES, C.PAIRS, C.diff("auto"), "un as (select doc_id, pos, dense_rank() over (partition by doc_id order by ln) - 1 as unit_no from (select doc_id, ln, row_number() over (partition by doc_id order by ln, i) - 1 as pos from (select doc_id, ln, unnest(range(len(ts))) as i from lt)))", tail=_UNIT_TAIL))(_unit_query("line"))
register("unit_sentence", C.core(C.SCORES, C.PAIRS, C.diff("auto"), "un as (select doc_id, pos, coalesce(sum(regexp_matches(tok, '[.!?]$')::int) over (partition by doc_id order by pos rows between unbounded preceding and 1 preceding), 0) as unit_no from tk)", tail=_UNIT_TAIL))(_unit_query("sentence"))

_COLS = ["l_partkey", *W.COLUMNS]
_CELL = " || ' , ' || ".join(f"""'"{c}": ' || {"l_quantity::int" if c == "l_quantity" else c}""" for c in _COLS)
_TABLES = f"""tb as (select l_orderkey as table_id, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) as row_no, *
  from lineitem where l_orderkey in (select l_orderkey from lineitem group by 1 having count(*) >= 6 order by 1 limit 116)),
tl as (select table_id, row_no, '{{ ' || {_CELL} || ' }}' as line from tb),
tquest as (select table_id, row_no as gold_row, no, column_name, gold_value, l_partkey from (select *, count(*) over (partition by table_id, l_partkey) as c1 from tb), lateral (values {", ".join(f"({k}, '{c}', {'l_quantity::int' if c == 'l_quantity' else c}::varchar)" for k, c in enumerate(W.COLUMNS))}) as x(no, column_name, gold_value) where c1 = 1 order by no, table_id, gold_row limit 515)
"""
_TABLE_Q = """asked as (select table_id as doc_id, string_agg(line, chr(10) order by row_no) as text from tl group by 1),
lns as (select doc_id, unnest(range(len(ls))) as ln, unnest(ls) as l from (select doc_id, string_split(text, chr(10)) as ls from asked)),
lt as (select doc_id, ln, regexp_extract_all(l, """ + T + """) as ts from lns),
q as (select table_id as doc_id, 't-' || table_id || '-' || gold_row || '-' || no as query_id, ['"' || column_name || '":', '"l_partkey":', l_partkey::varchar] as toks, gold_row from tquest),
aq as (select doc_id, query_id, toks from q)
"""
_TABLE_TAIL = "rs as (select doc_id, query_id, ln + 1 as row_no, sum(v) as score from sc join (select doc_id, ln, row_number() over (partition by doc_id order by ln, i) - 1 as pos from (select doc_id, ln, unnest(range(len(ts))) as i from lt)) using (doc_id, pos) group by all),\nrk as (select *, row_number() over (partition by doc_id, query_id order by score desc, row_no) as place from rs)"


def table_sql(tail: str) -> str:
    return "with recursive " + ",\n".join([_TABLES, _TABLE_Q, C.SCORES, _TABLE_TAIL]) + "\n" + tail


def whole_table_sql(tail: str) -> str:
    return table_sql(tail).replace(" order by 1 limit 116)", ")").replace(" order by no, table_id, gold_row limit 515)", ")")


REPLICA = (116, 515)  # tables and questions that the statements of the W4 queries fix; the _all queries take every one
WHOLE = (None, None)


def _tables(spark, sf_dir, size=REPLICA) -> tuple[DataFrame, DataFrame]:
    tables = W.order_tables(W.load(spark, sf_dir, "lineitem"), size[0])
    return tables, W.table_questions(tables, size[1])


def _row_places(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    def build():
        tables, asked = _tables(spark, sf_dir)
        docs = W.table_documents(tables)
        tok = tokenize(docs)
        scores = R.vectors(tok, asked, fixed=False)
        lines = docs.select("doc_id", F.posexplode(F.transform(F.split("text", "\n"), lambda x: F.size(words(x)))).alias("at", "n"))
        first = F.coalesce(F.sum("n").over(Window.partitionBy("doc_id").orderBy("at").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        rows = lines.select("doc_id", (F.col("at") + 1).alias("row_no"), first.cast("int").alias("first"), F.col("n").cast("int").alias("n"))
        scored = scores.join(rows, "doc_id").select("doc_id", "query_id", "row_no", F.aggregate(F.slice("v", F.col("first") + 1, F.col("n")), F.lit(0).cast("long"), lambda a, x: a + x).alias("score"))
        return scored.withColumn("place", F.row_number().over(Window.partitionBy("doc_id", "query_id").orderBy(F.desc("score"), "row_no")))

    asked = _tables(spark, sf_dir)[1]
    return held(spark, sf_dir, "row-places", build), asked


@register("w4_questions", table_sql("select q.query_id, q.gold_row::int as gold_row from q"))
def w4_questions(spark, sf_dir):
    return _tables(spark, sf_dir)[1].select("query_id", F.col("gold_row").cast("int").alias("gold_row"))


@register("w4_questions_all", whole_table_sql("select q.query_id, q.gold_row::int as gold_row from q"))
def w4_questions_all(spark, sf_dir):
    return _tables(spark, sf_dir, WHOLE)[1].select("query_id", F.col("gold_row").cast("int").alias("gold_row"))


@register("unit_row", table_sql("select query_id, row_no::int as row_no, score::bigint as score from rk"))
def unit_row(spark, sf_dir):
    return _row_places(spark, sf_dir)[0].select("query_id", F.col("row_no").cast("int").alias("row_no"), "score")


@register("table_topk_rows", table_sql("select query_id, row_no::int as row_no, place::int as place from rk where place <= 4"))
def table_topk_rows(spark, sf_dir):
    return _row_places(spark, sf_dir)[0].where("place <= 4").select("query_id", F.col("row_no").cast("int").alias("row_no"), "place")


@register("table_k_sweep", table_sql("select k::int as k, round(avg((place <= k)::int), 6) as accuracy from rk join q using (doc_id, query_id), range(1, 9) as r(k) where row_no = gold_row group by k"))
def table_k_sweep(spark, sf_dir):
    places, asked = _row_places(spark, sf_dir)
    gold = places.join(asked.select("query_id", F.col("gold_row").alias("row_no")), ["query_id", "row_no"])
    return _k_sweep(gold.select("place"))


def _k_sweep(gold: DataFrame) -> DataFrame:
    counted = gold.select("place", F.explode(F.sequence(F.lit(1), F.lit(8))).alias("k"))
    return counted.groupBy("k").agg(F.round(F.avg((F.col("place") <= F.col("k")).cast("int")), 6).alias("accuracy"))


@register("table_k_sweep_all", whole_table_sql("select k::int as k, round(avg((place <= k)::int), 6) as accuracy from rk join q using (doc_id, query_id), range(1, 9) as r(k) where row_no = gold_row group by k"))
def table_k_sweep_all(spark, sf_dir):
    """Every table is one row with its questions; places come out of the task that attends."""
    asked = X.tokenized_tables(W.asked_tables(W.load(spark, sf_dir, "lineitem")))
    return _k_sweep(rows.rank_rows(asked).select(F.col("gold_place").alias("place")))


@register("w4_accuracy", table_sql("""select 'top4' as method, round((select avg((place <= 4)::int) from rk join q using (doc_id, query_id) where row_no = gold_row), 6) as accuracy,
  round((select sum((place <= 4)::int) / count(*) from rk), 6) as row_usage
union all select 'head4', round((select avg((gold_row <= 4)::int) from q), 6), round((select sum((row_no <= 4)::int) / count(*) from rk), 6)
union all select 'full_table', round((select avg((regexp_extract(line, '"' || column_name || '": ([^ ]+)', 1) = gold_value)::int) from tquest join tl on tl.table_id = tquest.table_id and contains(line, '"l_partkey": ' || l_partkey || ' ,')), 6),
  round((select sum(given) / sum(n) from (select doc_id, query_id, count(*) as given from rk group by 1, 2) join (select table_id as doc_id, count(*) as n from tl group by 1) using (doc_id)), 6)"""))
def w4_accuracy(spark, sf_dir):
    """Cells read out of the four best rows, the first four, and all rows."""
    places, asked = _row_places(spark, sf_dir)
    tables = _tables(spark, sf_dir)[0].select(F.col("table_id").alias("doc_id"), "row_no", W.row_text().alias("line"))
    told = X.table_accuracy(tables, asked.withColumn("key", F.col("tokens")[2]), places, "l_partkey", 4)
    name = F.when(F.col("meth") == "top_rows", "top4").when(F.col("meth") == "head_rows", "head4").otherwise(F.col("meth"))
    return told.select(name.alias("method"), "accuracy", "row_usage")


@register("row_usage", table_sql("select doc_id, (count(*) filter (where place <= 4) / count(*))::double as usage from rk group by doc_id"))
def row_usage(spark, sf_dir):
    return _row_places(spark, sf_dir)[0].groupBy("doc_id").agg((F.sum((F.col("place") <= 4).cast("int")) / F.count("*")).alias("usage"))


@register("full_table", "with recursive " + _TABLES + " select table_id as doc_id, md5(string_agg(line, chr(10) order by row_no)) as text_md5 from tl group by 1")
def full_table(spark, sf_dir):
    return W.table_documents(_tables(spark, sf_dir)[0]).select("doc_id", F.md5("text").alias("text_md5"))


# ---- accuracy and cost by budget and method ---------------------------------------------------------

SOME = ("0.05", "0.1", "0.2", "0.4")
METHODS = ("raw", "fixed", "auto")


def _found(spark, sf_dir, contrasts=("auto",), budgets=SOME, overflow="trim") -> DataFrame:
    def build():
        c = Core(spark, sf_dir)
        out = None
        for kind in contrasts:
            s = selection.select_windows(c.diff(kind), budgets, overflow).withColumn("meth", F.lit(kind))
            out = s if out is None else out.unionByName(s)
        gold = c.questions
        spans = out.withColumn("n_spans", F.size("spans"))
        return measures.evidence(spans, gold).join(gold.select("query_id", "kind"), "query_id")

    return held(spark, sf_dir, f"found-{contrasts}-{budgets}-{overflow}", build)


def found_sql(tail: str, kinds=("auto",), budgets=SOME, *more: str) -> str:
    return C.core(C.SCORES, C.PAIRS, C.diff(*kinds), C.windows(budgets), C.TRIM, C.RECALL, *more, tail=tail)


_REC = "count(*) as n_queries, round(avg(n_in / n_gold), 6) as recall, round(avg(n_in / n_used), 6) as precision"


@register("evidence_recall", found_sql("select query_id, b::double as budget, n_used, n_in, n_gold::bigint as n_gold from rec"))
def evidence_recall(spark, sf_dir):
    return _found(spark, sf_dir).select("query_id", F.col("b").cast("double").alias("budget"), "n_used", "n_in", "n_gold")


@register("budget_sweep", found_sql("select b::double as budget, " + _REC + " from rec group by b", budgets=R.BUDGETS))
def budget_sweep(spark, sf_dir):
    return measures.recall(_found(spark, sf_dir, budgets=R.BUDGETS), "b").withColumn("budget", F.col("b").cast("double")).drop("b")


@register("evidence_precision", found_sql("select kind, b::double as budget, " + _REC + " from rec join q using (doc_id, query_id) group by kind, b"))
def evidence_precision(spark, sf_dir):
    return measures.recall(_found(spark, sf_dir), "kind", "b").withColumn("budget", F.col("b").cast("double")).drop("b")


_ACC = "count(*) as n_queries, round(avg((n_in >= 0.5 * n_gold)::int), 6) as accuracy"


@register("judge_accuracy", found_sql("select meth, kind, b::double as budget, " + _ACC + " from rec join q using (doc_id, query_id) group by meth, kind, b", METHODS))
def judge_accuracy(spark, sf_dir):
    return measures.correct_share(_found(spark, sf_dir, METHODS), "meth", "kind", "b").withColumn("budget", F.col("b").cast("double")).drop("b")


@register("w8_ablation", found_sql("select meth, b::double as budget, " + _REC + " from rec group by meth, b", METHODS))
def w8_ablation(spark, sf_dir):
    return measures.recall(_found(spark, sf_dir, METHODS), "meth", "b").withColumn("budget", F.col("b").cast("double")).drop("b")


@register("method_rank", found_sql("select *, rank() over (partition by budget order by accuracy desc) as place from (select meth, b::double as budget, " + _ACC + " from rec group by meth, b)", METHODS))
def method_rank(spark, sf_dir):
    acc = measures.correct_share(_found(spark, sf_dir, METHODS), "meth", "b").withColumn("budget", F.col("b").cast("double")).drop("b")
    return measures.rank_methods(acc, "budget").withColumn("place", F.col("place").cast("long"))


@register("token_usage", found_sql("select b::double as budget, round(avg(n_used), 6) as avg_tokens, round(sum(n_used) / sum(n), 6) as share, round(1 - sum(n_used) / sum(n), 6) as reduction from rec join dn using (doc_id) group by b"))
def token_usage(spark, sf_dir):
    return measures.token_usage(_found(spark, sf_dir), "b").withColumn("budget", F.col("b").cast("double")).drop("b")


@register("token_reduction", found_sql("select doc_id, round(1 - sum(n_used) / sum(n), 6) as reduction from rec join dn using (doc_id) where b = 0.1 group by doc_id"))
def token_reduction(spark, sf_dir):
    return measures.token_usage(_found(spark, sf_dir).where("b = 0.1"), "doc_id").select("doc_id", "reduction")


@register("budget_adherence", found_sql("select b::double as budget, min(o)::bigint as min_over, max(o)::bigint as max_over, round(avg(o), 6) as avg_over from (select b, n_used - ceil(b * n) as o from rec join dn using (doc_id)) group by b"))
def budget_adherence(spark, sf_dir):
    out = measures.budget_adherence(_found(spark, sf_dir), "b")
    return out.select(F.col("b").cast("double").alias("budget"), F.col("min_over").cast("long").alias("min_over"), F.col("max_over").cast("long").alias("max_over"), F.col("avg_over").cast("double").alias("avg_over"))


@register("marginal_gain", found_sql("select *, round(recall - lag(recall) over (order by budget), 6) as gain from (select b::double as budget, " + _REC + " from rec group by b)", budgets=R.BUDGETS))
def marginal_gain(spark, sf_dir):
    curve = measures.recall(_found(spark, sf_dir, budgets=R.BUDGETS), "b")
    return measures.marginal_gain(curve.withColumn("_all", F.lit(0)), "recall", "_all").withColumn("budget", F.col("b").cast("double")).drop("b", "_all")


@register("span_stats", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(SOME), C.TRIM, C.SPANS, tail="select budget, round(avg(n), 6) as avg_spans, round(sum(t) / sum(n), 6) as avg_length from (select b::double as budget, query_id, count(*) as n, sum(last_pos - first_pos) as t from spn group by all) group by budget"))
def span_stats(spark, sf_dir):
    s = selection.select_windows(Core(spark, sf_dir).diff(), SOME, "trim")
    return measures.span_stats(s, "b").withColumn("budget", F.col("b").cast("double")).drop("b")


@register("similarity_curve", found_sql("select meth, x::int as x, round(avg((n_in / n_gold * 100 > x)::int), 6) as share from rec, range(0, 101, 5) as r(x) where b = 0.1 group by meth, x", METHODS))
def similarity_curve(spark, sf_dir):
    f = _found(spark, sf_dir, METHODS).where("b = 0.1").withColumn("sim", F.col("n_in") / F.col("n_gold"))
    return measures.survival_curve(f, "sim", "meth")


@register("curve_dominance", found_sql("select a.meth as upper, z.meth as lower, round(avg((a.share >= z.share)::int), 6) as not_below from cur a join cur z on a.x = z.x and a.meth <> z.meth group by all", METHODS, SOME, "cur as (select meth, x, round(avg((n_in / n_gold * 100 > x)::int), 6) as share from rec, range(0, 101, 5) as r(x) where b = 0.1 group by meth, x)"))
def curve_dominance(spark, sf_dir):
    return measures.dominance(similarity_curve(spark, sf_dir), "meth")


@register("structural_share", C.core(C.SCORES, C.PAIRS, C.diff(*METHODS), C.windows(), C.TRIM, tail="select meth, round(avg((g = 4)::int), 6) as structural_share from kept join ctx using (doc_id, pos) group by meth"))
def structural_share(spark, sf_dir):
    c = Core(spark, sf_dir)
    out = None
    for kind in METHODS:
        s = selection.select_windows(c.diff(kind), overflow="trim").select(F.lit(kind).alias("meth"), "doc_id", F.explode("spans").alias("x"))
        out = s if out is None else out.union(s)
    flags = out.join(c.tok, "doc_id").select("meth", F.explode(F.slice("structural", F.col("x.first_pos") + 1, F.col("x.last_pos") - F.col("x.first_pos"))).alias("s"))
    return flags.groupBy("meth").agg(F.round(F.avg(F.col("s").cast("int")), 6).alias("structural_share"))


_SENSITIVE = r"[\w.+-]+@[\w-]+\.|[0-9]{13,16}|[0-9a-f]{24,}"


@register("exposure_ratio", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), C.TRIM, tail=f"select doc_id, query_id, count(*) filter (where kept.pos is not null) as forwarded, count(*) as present from (select q.doc_id, q.query_id, pos from q join tk using (doc_id) where regexp_matches(tok, '{_SENSITIVE}')) s left join kept using (doc_id, query_id, pos) group by all"))
def exposure_ratio(spark, sf_dir):
    c = Core(spark, sf_dir)
    s = selection.select_windows(c.diff(), overflow="trim")
    t = s.join(c.tok, "doc_id").select("doc_id", "query_id", "spans", F.posexplode("tokens").alias("pos", "tok")).where(F.col("tok").rlike(_SENSITIVE))
    inside = F.exists("spans", lambda x: (F.col("pos") >= x["first_pos"]) & (F.col("pos") < x["last_pos"]))
    return t.groupBy("doc_id", "query_id").agg(F.count_if(inside).alias("forwarded"), F.count("*").alias("present"))


@register("extractive_answer", _prompt_sql("select query_id, len(list_distinct(list_filter(regexp_extract_all(prompt, " + T + "), lambda x: list_contains(toks, x))))::int as matched from prm join q using (query_id)"))
def extractive_answer(spark, sf_dir):
    """Stand-in answer model: how many of the question's own words the context repeats."""
    c = Core(spark, sf_dir)
    p = selection.assemble(c.tok, selection.select_windows(c.diff()))
    return p.join(c.questions.select("query_id", F.col("tokens").alias("t")), "query_id").select("query_id", F.size(F.array_intersect(words(F.col("prompt")), F.col("t"))).alias("matched"))


@register("judge_audit_sample", C.core(tail="select query_id from q order by md5(query_id) limit 200"))
def judge_audit_sample(spark, sf_dir):
    return Core(spark, sf_dir).questions.select("query_id").orderBy(F.md5("query_id")).limit(200)


_GOLD = "gt as (select q.query_id, list(tok order by pos) as gold from q join tk using (doc_id) where pos >= first_pos and pos < last_pos group by all),\nan as (select query_id, list(tok order by pos) as ans from kept join tk using (doc_id, pos) group by all)"


def _answers(spark, sf_dir) -> DataFrame:
    c = Core(spark, sf_dir)
    s = selection.select_windows(c.diff(), overflow="trim").join(c.questions.select("query_id", "first_pos", "last_pos"), "query_id").join(c.tok.select("doc_id", "tokens"), "doc_id")
    ans = F.flatten(F.transform("spans", lambda x: F.slice("tokens", x["first_pos"] + 1, x["last_pos"] - x["first_pos"])))
    return s.select("query_id", ans.alias("ans"), F.slice("tokens", F.col("first_pos") + 1, F.col("last_pos") - F.col("first_pos")).alias("gold"))


def _rouge_sql(n: int) -> str:
    g = lambda c: f"select query_id, lower(array_to_string({c}[i:i + {n - 1}], ' ')) as g, count(*) as k from x, unnest(range(1, len({c}) - {n - 2})) as r(i) group by all"
    return C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), C.TRIM, _GOLD, "x as (select * from gt join an using (query_id))", f"ga as ({g('ans')})", f"gg as ({g('gold')})",
                  tail="select query_id, round(coalesce(2.0 * c / nullif(coalesce(na, 0) + coalesce(ng, 0), 0), 0), 6) as f1 from x left join (select query_id, sum(least(ga.k, gg.k)) as c from ga join gg using (query_id, g) group by 1) using (query_id) left join (select query_id, sum(k) as na from ga group by 1) using (query_id) left join (select query_id, sum(k) as ng from gg group by 1) using (query_id)")


for _n in (1, 2):
    register(f"rouge_{_n}", _rouge_sql(_n))(lambda spark, sf_dir, n=_n: _answers(spark, sf_dir).select("query_id", F.round(measures.rouge(F.col("ans"), F.col("gold"), n), 6).alias("f1")))


@register("answer_cosine", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(), C.TRIM, _GOLD,
          "ab as (select query_id, b, count(*)::double as n from (select query_id, ('0x' || substr(md5(lower(t)), 1, 8))::bigint % 64 as b from (select query_id, unnest(ans) as t from an)) group by all)",
          "gb as (select query_id, b, count(*)::double as n from (select query_id, ('0x' || substr(md5(lower(t)), 1, 8))::bigint % 64 as b from (select query_id, unnest(gold) as t from gt)) group by all)",
          tail="select query_id, round(coalesce(d, 0) / (sqrt(za) * sqrt(zg)), 6) as cosine from (select query_id, sum(n * n) as za from ab group by 1) join (select query_id, sum(n * n) as zg from gb group by 1) using (query_id) left join (select query_id, sum(ab.n * gb.n) as d from ab join gb using (query_id, b) group by 1) using (query_id)"))
def answer_cosine(spark, sf_dir):
    a = _answers(spark, sf_dir).select("query_id", scoring.hashed_bag(F.col("ans")).alias("a"), scoring.hashed_bag(F.col("gold")).alias("g"))
    return a.select("query_id", F.round(scoring.cosine_of_bags(F.col("a"), F.col("g")), 6).alias("cosine"))


@register("competing_candidates", C.core(C.SCORES, C.PAIRS, C.diff("auto"), C.windows(SOME), C.TRIM, tail="""select query_id, b::double as budget, count(distinct riv.ln) as rivals from (select q.query_id, q.doc_id, lo.ln, lo.off from q join lo me on me.doc_id = q.doc_id and me.off <= q.first_pos and q.first_pos < me.off + len(me.ts) join lo on lo.doc_id = q.doc_id and len(lo.ts) > 0 and lo.ts[1] = me.ts[1] and lo.ln <> me.ln) riv
  join kept using (doc_id, query_id) where kept.pos = riv.off group by all"""))
def competing_candidates(spark, sf_dir):
    """Lines that open with the same token as the asked one and are in the context: the failure mode grows with the budget."""
    c = Core(spark, sf_dir)
    lines = W.lines_of(c.docs.join(c.tok.select("doc_id"), "doc_id", "left_semi"), least=1)
    mine = lines.select("doc_id", F.col("ln").alias("my_ln"), F.col("ts")[0].alias("head"), F.col("off").alias("a"), (F.col("off") + F.size("ts")).alias("z"))
    asked = c.questions.join(mine, "doc_id").where("a <= first_pos and first_pos < z").select("doc_id", "query_id", "my_ln", "head")
    rivals = asked.join(lines.select("doc_id", "ln", "off", F.col("ts")[0].alias("head")), ["doc_id", "head"]).where("ln <> my_ln").select("query_id", "ln", "off")
    s = selection.select_windows(c.diff(), SOME, "trim")
    hit = s.join(rivals, "query_id").where(F.exists("spans", lambda x: (F.col("off") >= x["first_pos"]) & (F.col("off") < x["last_pos"])))
    return hit.groupBy("query_id", F.col("b").cast("double").alias("budget")).agg(F.count_distinct("ln").alias("rivals"))


# ---- baselines --------------------------------------------------------------------------------------

_CH = """och as (select doc_id, n, (s // 96) as chunk_no, s as a, least(s + 128, n) as z from dn, unnest(range(0, greatest(n - 33, 0)::bigint + 1, 96)) as r(s)),
oct as (select doc_id, chunk_no, pos, tok from och join tk using (doc_id) where pos >= a and pos < z)"""


def _features_sql(kind: str) -> str:
    dims = {"unigram": 64, "trigram": 256, "tfidf": 1024}[kind]
    h = lambda x: f"('0x' || substr(md5({x}), 1, 8))::bigint % {dims}"
    if kind == "trigram":
        cf = f"cf0 as (select doc_id, chunk_no, lower(string_agg(tok, ' ' order by pos)) as t from oct group by all), cf as (select doc_id, chunk_no, {h('substr(t, i::int, 3)')} as bk, count(*)::double as w from cf0, unnest(range(1, length(t) - 1)) as r(i) group by all)"
        qf = f"qf0 as (select doc_id, query_id, lower(array_to_string(toks, ' ')) as t from q), qf as (select doc_id, query_id, {h('substr(t, i::int, 3)')} as bk, count(*)::double as w from qf0, unnest(range(1, length(t) - 1)) as r(i) group by all)"
    else:
        cf = f"cf as (select doc_id, chunk_no, {h('lower(tok)')} as bk, count(*)::double as w from oct group by all)"
        qf = f"qf as (select doc_id, query_id, {h('lower(t)')} as bk, count(*)::double as w from (select doc_id, query_id, unnest(toks) as t from q) group by all)"
    if kind == "tfidf":
        idf = "idf as (select bk, round(ln((select count(*) from och) / count(*)) + 1, 6) as idf from cf group by bk)"
        return f"{cf},\n{qf},\n{idf},\ncfw as (select doc_id, chunk_no, bk, w * idf as w from cf join idf using (bk)),\nqfw as (select doc_id, query_id, bk, w * idf as w from qf join idf using (bk))"
    return f"{cf},\n{qf},\ncfw as (select * from cf),\nqfw as (select * from qf)"


def rag_sql(kind: str, tail: str, *more: str) -> str:
    sim = """rg as (select *, row_number() over (partition by doc_id, query_id order by similarity desc, chunk_no) as place from (select a.doc_id, a.query_id, c.chunk_no, round(coalesce(d.dot, 0) / (a.z * c.z), 6) as similarity
  from (select doc_id, query_id, sqrt(sum(w * w)) as z from qfw group by all) a join (select doc_id, chunk_no, sqrt(sum(w * w)) as z from cfw group by all) c using (doc_id)
  left join (select q1.doc_id, q1.query_id, c1.chunk_no, sum(q1.w * c1.w) as dot from qfw q1 join cfw c1 using (doc_id, bk) group by all) d on d.doc_id = a.doc_id and d.query_id = a.query_id and d.chunk_no = c.chunk_no))"""
    return C.core(C.SCORES, _CH, _features_sql(kind), sim, *more, tail=tail)


def _hits(spark, sf_dir, kind="unigram"):
    c = Core(spark, sf_dir)
    chunks = retrieval.chunk_overlap(c.tok)
    return held(spark, sf_dir, f"hits-{kind}", lambda: retrieval.retrieve(chunks, c.questions, kind)), chunks


for _k in ("unigram", "trigram", "tfidf"):
    register(f"embed_{_k}", rag_sql(_k, "select query_id, chunk_no::int as chunk_no, similarity from rg"))(
        lambda spark, sf_dir, k=_k: _hits(spark, sf_dir, k)[0].select("query_id", "chunk_no", "similarity"))

_KS = """ks as (select doc_id, query_id, k, count(distinct pos) as n_used from rg join range(1, 9) as r(k) on place <= k join oct using (doc_id, chunk_no) group by all)"""


@register("rag_topk", rag_sql("unigram", "select query_id, chunk_no::int as chunk_no, place::int as place from rg where place <= 4"))
def rag_topk(spark, sf_dir):
    return _hits(spark, sf_dir)[0].where("place <= 4").select("query_id", "chunk_no", "place")


@register("rag_context", rag_sql("unigram", "select query_id, count(distinct pos) as n_used, min(pos)::int as first_pos, (max(pos) + 1)::int as last_pos from rg join oct using (doc_id, chunk_no) where place <= 4 group by query_id"))
def rag_context(spark, sf_dir):
    hits, chunks = _hits(spark, sf_dir)
    s = retrieval.stitch(hits.where("place <= 4"), chunks)
    return s.select("query_id", selection.used_tokens(F.col("spans")).cast("long").alias("n_used"), F.col("spans")[0]["first_pos"].alias("first_pos"), F.element_at("spans", -1)["last_pos"].alias("last_pos"))


@register("rag_k_sweep", rag_sql("unigram", "select query_id, k::int as k, n_used from ks", _KS))
def rag_k_sweep(spark, sf_dir):
    return retrieval.k_sweep(*_hits(spark, sf_dir)).select("query_id", "k", "n_used")


_AL = "al as (select query_id, doc_id, max(k) filter (where k = 1 or n_used <= ceil(0.4::decimal(9,6) * n)) as k from ks join dn using (doc_id) group by all)"


@register("rag_token_aligned", rag_sql("unigram", "select query_id, al.k::int as k, n_used from al join ks using (query_id, doc_id, k)", _KS, _AL))
def rag_token_aligned(spark, sf_dir):
    return retrieval.align_k(retrieval.k_sweep(*_hits(spark, sf_dir)), F.lit("0.4")).select("query_id", "k", "n_used")


@register("rag_min_cost", rag_sql("unigram", "select query_id, n_used, round(n_used / n, 6) as share from ks join dn using (doc_id) where k = 1", _KS))
def rag_min_cost(spark, sf_dir):
    """What one chunk costs: budgets below it are out of reach for retrieval."""
    s = retrieval.k_sweep(*_hits(spark, sf_dir), ks=(1,))
    return s.select("query_id", "n_used", F.round(F.col("n_used") / F.col("n_tokens"), 6).alias("share"))


_W1 = f"""rkept as (select 'rag' as meth, rg.doc_id, rg.query_id, pos from al join rg on rg.query_id = al.query_id and rg.place <= al.k join oct on oct.doc_id = rg.doc_id and oct.chunk_no = rg.chunk_no group by all),
both_kept as (select meth, doc_id, query_id, pos from kept union all select * from rkept),
r2 as (select meth, kind, query_id, count(*) as n_used, count(*) filter (where pos >= first_pos and pos < last_pos) as n_in, any_value(last_pos - first_pos) as n_gold from both_kept join q using (doc_id, query_id) group by all)"""


@register("w1_accuracy", rag_sql("unigram", "select meth, kind, count(*) as n_queries, round(avg((n_in >= 0.5 * n_gold)::int), 6) as accuracy, round(avg(n_used), 6) as avg_tokens from r2 group by meth, kind", _KS, _AL, C.PAIRS, C.diff("auto"), C.windows(("0.4",)), C.TRIM, _W1))
def w1_accuracy(spark, sf_dir):
    """Reducer against retrieval at 40% of the tokens, by kind of question."""
    c = Core(spark, sf_dir)
    mine = selection.select_windows(c.diff(), ("0.4",), "trim").select(F.lit("auto").alias("meth"), "query_id", "n_tokens", "spans")
    rag = retrieval.align_k(retrieval.k_sweep(*_hits(spark, sf_dir)), F.lit("0.4")).select(F.lit("rag").alias("meth"), "query_id", "n_tokens", "spans")
    found = measures.evidence(mine.unionByName(rag), c.questions).join(c.questions.select("query_id", "kind"), "query_id")
    ok = (F.col("n_in") >= 0.5 * F.col("n_gold")).cast("int")
    return found.groupBy("meth", "kind").agg(F.count("*").alias("n_queries"), F.round(F.avg(ok), 6).alias("accuracy"), F.round(F.avg("n_used"), 6).alias("avg_tokens"))


@register("embed_work", C.core(C.SCORES, _CH, tail="select count(*) as n_chunks, sum(z - a)::bigint as n_tokens from och"))
def embed_work(spark, sf_dir):
    return _hits(spark, sf_dir)[1].agg(F.count("*").alias("n_chunks"), F.sum(F.col("last_pos") - F.col("first_pos")).alias("n_tokens"))


@register("rag_bm25", C.core(C.SCORES, _CH, """tf as (select doc_id, chunk_no, lower(tok) as t, count(*) as tf from oct group by all), df as (select t, count(*) as df from tf group by t), cl as (select doc_id, chunk_no, count(*) as n from oct group by all),
st as (select count(*)::double as nc, avg(n) as av from cl), qs as (select distinct doc_id, query_id, lower(t) as t from (select doc_id, query_id, unnest(toks) as t from q))""",
          tail="select query_id, chunk_no::int as chunk_no, round(sum(ln(1 + (nc - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * n / av))), 6) as score from qs join tf using (doc_id, t) join df using (t) join cl using (doc_id, chunk_no), st group by all"))
def rag_bm25(spark, sf_dir):
    c = Core(spark, sf_dir)
    return retrieval.bm25(retrieval.chunk_overlap(c.tok), c.questions).select("query_id", "chunk_no", "score")


@register("rag_maxsim", C.core(C.SCORES, _CH, tail="select query_id, chunk_no::int as chunk_no, sum(s)::bigint as score from (select q1.query_id, q1.k, o.chunk_no, max(32 - 2 * bit_count(xor(q1.w, o.w))) as s from (select doc_id, query_id, k, w from qw join q using (doc_id, query_id) where layer = 0 and head = 0) q1 join (select distinct doc_id, chunk_no, ('0x' || substr(md5(lower(tok)), 1, 8))::bigint as w from oct) o using (doc_id) group by all) group by all"))
def rag_maxsim(spark, sf_dir):
    c = Core(spark, sf_dir)
    return retrieval.maxsim(retrieval.chunk_overlap(c.tok), c.questions).select("query_id", "chunk_no", "score")


def _region_sql(cond: str) -> str:
    return C.core(C.SCORES, tail=f"select query_id, count(*) as n_used, count(*) filter (where pos >= first_pos and pos < last_pos) as n_in from q join dn using (doc_id) join tk using (doc_id), (select 0.1::decimal(9,6) as b) where {cond} group by query_id")


_B = "ceil(b * n)"
for _w, _c in (("head", f"pos < {_B}"), ("tail", f"pos >= n - {_B}"), ("both", f"(pos < ceil({_B} / 2.0) or pos >= n - ({_B} - ceil({_B} / 2.0)))")):
    register(f"select_{_w}", _region_sql(_c))(lambda spark, sf_dir, w=_w: measures.evidence(retrieval.fixed_region(Core(spark, sf_dir).tok, Core(spark, sf_dir).questions, "0.1", w), Core(spark, sf_dir).questions).select("query_id", "n_used", "n_in"))


@register("full_context", C.core(C.SCORES, tail="select query_id, n::int as used, round(0.0, 6)::double as reduction from q join dn using (doc_id)"))
def full_context(spark, sf_dir):
    c = Core(spark, sf_dir)
    return c.questions.join(c.tok, "doc_id").select("query_id", F.col("n_tokens").alias("used"), F.lit(0.0).alias("reduction"))


@register("select_random", C.core(C.SCORES, "d as (select 'rnd' as meth, doc_id, query_id, pos, ('0x' || substr(md5(query_id || ':' || pos), 1, 7))::bigint as v from q join tk using (doc_id))", C.windows(), C.TRIM, C.SPANS, tail="select doc_id, query_id, first_pos, last_pos from spn"))
def select_random(spark, sf_dir):
    c = Core(spark, sf_dir)
    return per_span(selection.select_windows(retrieval.random_scores(c.tok, c.questions), overflow="trim"))


_HEAT = "hm as (select kind, (p * 20 // n)::int as bin, count(*) as mass from (select kind, n, unnest(range(first_pos::bigint, last_pos::bigint)) as p from q join dn using (doc_id) where doc_id % 2 = 0) group by all)"


@register("positional_heatmap", C.core(C.SCORES, _HEAT, tail="select kind, bin, mass from hm"))
def positional_heatmap(spark, sf_dir):
    c = Core(spark, sf_dir)
    return retrieval.fit_heatmap(c.questions, c.tok)


@register("positional_select", C.core(C.SCORES, _HEAT, "d as (select 'heat' as meth, doc_id, query_id, pos, coalesce(mass, 0) as v from (select q.*, n, pos, (pos * 20 // n)::int as bin from q join dn using (doc_id) join tk using (doc_id) where doc_id % 2 = 1) x left join hm using (kind, bin))", C.windows(), C.TRIM, C.SPANS,
          tail="select doc_id, query_id, first_pos, last_pos from spn"))
def positional_select(spark, sf_dir):
    c = Core(spark, sf_dir)
    kinds = retrieval.fit_heatmap(c.questions, c.tok).persist()
    v = retrieval.apply_heatmap(kinds, c.questions, c.tok)
    missing = c.questions.where("doc_id % 2 = 1").join(kinds.select("kind").distinct(), "kind", "left_anti").join(c.tok.select("doc_id", "n_tokens"), "doc_id")
    zero = missing.select("doc_id", "query_id", F.array_repeat(F.lit(0).cast("long"), F.col("n_tokens")).alias("v"))
    return per_span(selection.select_windows(v.unionByName(zero), overflow="trim"))


# ---- workloads --------------------------------------------------------------------------------------

@register("w1_questions", C.core(tail="select query_id, kind, len(toks)::int as n, first_pos::int as first_pos, last_pos::int as last_pos from q"))
def w1_questions(spark, sf_dir):
    return Core(spark, sf_dir).questions.select("query_id", "kind", F.size("tokens").alias("n"), F.col("first_pos").cast("int").alias("first_pos"), F.col("last_pos").cast("int").alias("last_pos"))


_FIELD = {"science": (9, 1000, 1000000000, 12, "s"), "notice": (6, 200, 500, 6, "n")}


def field_sql(kind: str) -> str:
    count, low, high, least, mark = _FIELD[kind]
    return f"""asked as (select doc_id, text from documents where len(regexp_extract_all(text, {T})) between {low} and {high}),
lns as (select doc_id, unnest(range(len(ls))) as ln, unnest(ls) as l from (select doc_id, string_split(text, chr(10)) as ls from asked)),
lt as (select doc_id, ln, regexp_extract_all(l, {T}) as ts from lns),
lo as (select *, coalesce(sum(len(ts)) over (partition by doc_id order by ln rows between unbounded preceding and 1 preceding), 0) as off from lt),
fl as (select *, count(*) over (partition by doc_id) as n, row_number() over (partition by doc_id order by md5(doc_id || '-' || ln)) as r from lo where len(ts) >= 6),
q as (select doc_id, '{mark}' || ln || '@' || doc_id as query_id, '{kind}' as kind, ts[1:least(len(ts) // 2, 16)] as toks, off + len(ts) // 2 as first_pos, off + len(ts) as last_pos from fl where n >= {least} and r <= {count})"""


for _name, _kind2 in (("w2_questions", "science"), ("w3_questions", "notice")):
    register(_name, "with " + field_sql(_kind2) + " select query_id, len(toks)::int as n, first_pos::int as first_pos, last_pos::int as last_pos from q")(
        lambda spark, sf_dir, k=_kind2: W.field_questions(W.load(spark, sf_dir, "documents"), k).select("query_id", F.size("tokens").alias("n"), F.col("first_pos").cast("int").alias("first_pos"), F.col("last_pos").cast("int").alias("last_pos")))


def _field_found(spark, sf_dir, kind, budgets):
    def build():
        docs = W.load(spark, sf_dir, "documents")
        asked = W.field_questions(docs, kind)
        tok = W.asked_documents(docs, asked)
        v = R.contrasted(R.vectors(tok, asked), asked)
        return measures.evidence(selection.select_windows(v, budgets, "skip"), asked)

    return held(spark, sf_dir, f"field-{kind}-{budgets}", build)


def _curve(name: str, kind: str, budgets) -> None:
    def run(spark, sf_dir):
        f = _field_found(spark, sf_dir, kind, budgets)
        out = measures.recall(f, "b").join(measures.budget_adherence(f, "b").select("b", "max_over"), "b")
        return out.select(F.col("b").cast("double").alias("budget"), "n_queries", "recall", "precision", F.col("max_over").cast("long").alias("max_over"))

    QUERIES[name] = run  # the exploded statement would need all questions of all long documents; tests use brute force


_curve("w2_curves", "science", SOME)
_curve("w3_curves", "notice", SOME)
_curve("w10_tiny_budget", "notice", ("0.005", "0.01"))


def w3_failure_mode(spark, sf_dir):
    """Rival lines (same first token as the asked line) inside the context, by budget."""
    docs = W.load(spark, sf_dir, "documents")
    asked = W.field_questions(docs, "notice")
    tok = W.asked_documents(docs, asked)
    s = held(spark, sf_dir, "notice-spans", lambda: selection.select_windows(R.contrasted(R.vectors(tok, asked), asked), SOME, "skip"))
    lines = W.lines_of(docs.join(asked.select("doc_id").distinct(), "doc_id", "left_semi"), least=1)
    mine = lines.select("doc_id", F.col("ln").alias("my_ln"), F.col("ts")[0].alias("head"), F.col("off").alias("a"), (F.col("off") + F.size("ts")).alias("z"))
    key = asked.join(mine, "doc_id").where("a <= first_pos and first_pos < z").select("doc_id", "query_id", "my_ln", "head")
    rivals = key.join(lines.select("doc_id", "ln", "off", F.col("ts")[0].alias("head")), ["doc_id", "head"]).where("ln <> my_ln").groupBy("query_id").agg(F.collect_list("off").alias("offs"))
    n = F.size(F.filter("offs", lambda o: F.exists("spans", lambda x: (o >= x["first_pos"]) & (o < x["last_pos"]))))
    return s.join(rivals, "query_id").groupBy(F.col("b").cast("double").alias("budget")).agg(F.count("*").alias("n_queries"), F.round(F.avg(n), 6).alias("avg_rivals"))


QUERIES["w3_failure_mode"] = w3_failure_mode


def w1_hard_accuracy(spark, sf_dir):
    """Every fourth token of a passage's first half as the question: weakly similar to the evidence."""
    docs, passages = W.load(spark, sf_dir, "documents"), W.load(spark, sf_dir, "benchmark")
    asked = W.hard_questions(docs, passages)
    tok = W.asked_documents(docs, asked)
    mine = selection.select_windows(R.contrasted(R.vectors(tok, asked), asked), ("0.4",)).select(F.lit("auto").alias("meth"), "query_id", "n_tokens", "spans")
    chunks = retrieval.chunk_overlap(tok)
    rag = retrieval.align_k(retrieval.k_sweep(retrieval.retrieve(chunks, asked), chunks), F.lit("0.4")).select(F.lit("rag").alias("meth"), "query_id", "n_tokens", "spans")
    return measures.correct_share(measures.evidence(mine.unionByName(rag), asked), "meth")


QUERIES["w1_hard_accuracy"] = w1_hard_accuracy


def w9_scorer_size(spark, sf_dir):
    """Fewer layers and heads stand in for a smaller scorer: 1, 4 and 12 of them."""
    c = Core(spark, sf_dir)
    out = None
    for size, layers, heads in ((1, (0,), (0,)), (4, (0,), attention.ALL_HEADS), (12, attention.ALL_LAYERS, attention.ALL_HEADS)):
        v = R.contrasted(R.vectors(c.tok, c.questions, layers=layers, heads=heads), c.questions)
        f = measures.evidence(selection.select_windows(v, ("0.05", "0.1"), "trim"), c.questions)
        part = measures.recall(f, "b").select(F.lit(size).alias("size"), F.col("b").cast("double").alias("budget"), "n_queries", "recall")
        out = part if out is None else out.unionByName(part)
    return out


def _w9_sql() -> str:
    parts = []
    for size, cond in ((1, "layer = 0 and head = 0"), (4, "layer = 0"), (12, "true")):
        base = C.SCORES.replace("raw as (select doc_id, query_id, c, pos, sum(w)::bigint as s from wt group by all)", f"raw as (select doc_id, query_id, c, pos, sum(w)::bigint as s from wt where {cond} group by all)")
        parts.append(f"select {size} as size, budget, n_queries, recall from (" + C.core(base, C.PAIRS, C.diff("auto"), C.windows(("0.05", "0.1")), C.TRIM, C.RECALL, tail="select b::double as budget, " + _REC + " from rec group by b") + ")")
    return " union all ".join(parts)


register("w9_scorer_size", _w9_sql())(w9_scorer_size)

for _name, _by, _join in (("w12_by_language", "lang", "documents"), ("w12_by_quality", "quality", "labels")):
    register(_name, found_sql(f"select {_by}, b::double as budget, {_REC} from rec join {_join} using (doc_id) group by {_by}, b"))(
        lambda spark, sf_dir, by=_by, t=_join: measures.recall(_found(spark, sf_dir).join(W.load(spark, sf_dir, t).select("doc_id", by), "doc_id"), by, "b").withColumn("budget", F.col("b").cast("double")).drop("b"))
