"""Streaming queries and user-defined function surfaces."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from gistloom.plans.workloads import load
from gistloom.shipping import ship
from gistloom.sources.chunks import ChunkSource, PromptSink
from gistloom.staging import fresh_path
from gistloom.streaming import questions as S

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

QUERIES["stream_tumbling"] = lambda spark, d: S.drain(S.tumbling(S.source(spark, d)), "complete")
ORACLES["stream_tumbling"] = "select time_bucket(interval '1 hour', ts) as start, event_type, count(*) as n, round(sum(value), 4) as v from events group by 1, 2"
QUERIES["stream_sliding"] = lambda spark, d: S.drain(S.sliding(S.source(spark, d)), "complete")
ORACLES["stream_sliding"] = "select start, count(*) as n from (select unnest([time_bucket(interval '1 hour', ts), time_bucket(interval '1 hour', ts) - interval '1 hour']) as start from events) group by 1"
QUERIES["stream_watermark"] = lambda spark, d: S.drain(S.tumbling(S.source(spark, d)), "append")
QUERIES["stream_session"] = lambda spark, d: S.drain(S.sessions(S.source(spark, d)), "append")
QUERIES["stream_dedup"] = lambda spark, d: S.drain(S.deduplicated(S.source(spark, d)))
QUERIES["stream_reduce"] = lambda spark, d: S.drain(S.with_static(S.source(spark, d), load(spark, d, "customer").select("c_custkey", "c_mktsegment")))
ORACLES["stream_reduce"] = "select event_id, c_mktsegment from events left join customer on user_id = c_custkey"
QUERIES["stream_stream_join"] = lambda spark, d: S.drain(S.with_stream(S.source(spark, d), S.source(spark, d)))
ORACLES["stream_stream_join"] = "select x.event_id as a, y.event_id as b from events x join events y on x.user_id = y.user_id and y.ts > x.ts and y.ts <= x.ts + interval '1 hour'"


def stream_cache_state(spark, sf_dir):
    ship(spark)
    return S.drain(S.cache_state(S.source(spark, sf_dir)), "update", ("user_id",))


QUERIES["stream_cache_state"] = stream_cache_state
ORACLES["stream_cache_state"] = """select user_id, cast(count(*) filter (where same) as bigint) as hits, cast(count(*) filter (where not same) as bigint) as misses from
 (select user_id, coalesce(event_type = lag(event_type) over (partition by user_id order by ts, event_id), false) as same from events) group by user_id"""


def stream_foreach_batch(spark, sf_dir):
    """The batch code on every micro-batch, rows appended to a table of files."""
    out = fresh_path(spark, "batches")
    S.each_batch(S.source(spark, sf_dir), lambda df, no: df.groupBy("event_type").agg(F.count("*").alias("n")).write.mode("append").parquet(out), fresh_path(spark, "batch-log"))
    return spark.read.parquet(out).groupBy("event_type").agg(F.sum("n").alias("n"))


QUERIES["stream_foreach_batch"] = stream_foreach_batch
ORACLES["stream_foreach_batch"] = "select event_type, count(*)::bigint as n from events group by 1"


def udf_sql(spark, sf_dir):
    spark.sql("create or replace temporary function gl_budget(n int, b decimal(9,6)) returns int return cast(ceil(b * n) as int)")
    return spark.sql("select doc_id, gl_budget(cast(n_chars as int), cast(0.1 as decimal(9,6))) as b from {d}", d=load(spark, sf_dir, "documents"))


QUERIES["udf_sql"] = udf_sql
ORACLES["udf_sql"] = "select doc_id, ceil(0.1::decimal(9,6) * n_chars)::int as b from documents"


def udf_arrow(spark, sf_dir):
    @pandas_udf("long")
    def digits(s: pd.Series) -> pd.Series:
        return s.str.count("[0-9]")

    return load(spark, sf_dir, "documents").select("doc_id", digits("text").alias("digits"))


QUERIES["udf_arrow"] = udf_arrow
ORACLES["udf_arrow"] = "select doc_id, length(regexp_replace(text, '[^0-9]', '', 'g')) as digits from documents"


def udaf_curve(spark, sf_dir):
    @pandas_udf("double")
    def above(v: pd.Series) -> float:
        return float((v > 50).mean())

    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.round(above("value"), 6).alias("share"))


QUERIES["udaf_curve"] = udaf_curve
ORACLES["udaf_curve"] = "select event_type, round(avg((value > 50)::int), 6) as share from events group by 1"


def udtf_chunks(spark, sf_dir):
    """Table function: the chunks of a text, callable from SQL."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="chunk_no: int, n: int")
    class Chunks:
        def eval(self, text: str, size: int):
            t = (text or "").split(" ")
            for k, i in enumerate(range(0, len(t), size)):
                yield k, len(t[i : i + size])

    spark.udtf.register("gl_chunks", Chunks)
    return spark.sql("select d.doc_id, c.chunk_no, c.n from {d} as d, lateral gl_chunks(d.text, 64) as c", d=load(spark, sf_dir, "benchmark").withColumnRenamed("item_id", "doc_id"))


QUERIES["udtf_reduce"] = udtf_chunks
ORACLES["udtf_reduce"] = "select item_id as doc_id, (s // 64)::int as chunk_no, len(t[s + 1:s + 64])::int as n from (select item_id, string_split(text, ' ') as t from benchmark), unnest(range(0, len(t), 64)) as r(s)"


def source_chunks(spark, sf_dir):
    """Prompts written by the sink as JSON lines and read back by the chunk source."""
    ship(spark)
    spark.dataSource.register(ChunkSource)
    spark.dataSource.register(PromptSink)
    path = fresh_path(spark, "prompts")
    load(spark, sf_dir, "benchmark").select(F.col("item_id").cast("string").alias("query_id"), F.col("text").alias("prompt")).write.format("gl_prompts").option("path", path).mode("append").save()
    return spark.read.format("gl_chunks").option("path", path).option("size", "16").load()


QUERIES["source_chunks"] = source_chunks
ORACLES["source_chunks"] = "select item_id::varchar as query_id, (s // 16)::int as chunk_no, len(t[s + 1:s + 16])::int as n from (select item_id, regexp_extract_all(text, '[^ \\t\\n\\r\\f]+') as t from benchmark), unnest(range(0, len(t), 16)) as r(s)"
