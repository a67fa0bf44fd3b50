"""Streams of questions: late data, windows, duplicates, state per document, joins, micro-batches.

All functions take a streaming DataFrame of events (event_id, ts, user_id, event_type, value) and
return a streaming DataFrame; ``drain`` runs one over the files that are there and gives the rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from gistloom.staging import fresh_path, is_folder

LATE = "10 minutes"


def source(spark: SparkSession, sf_dir: str, table: str = "events") -> DataFrame:
    """The table as a file stream with a declared schema; events carry a timestamp for watermarks.

    A table is one file, or a folder of files as Spark writes it; the filter on names would find none of the latter's.
    """
    path = f"{sf_dir}/{table}.parquet"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if is_folder(spark, path):
        stream = reader.parquet(path)
    else:
        folder, _, name = path.rpartition("/")
        stream = reader.option("pathGlobFilter", name).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in schema.names else stream


def drain(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """All rows that the stream has now, by files in the shared folder; no row passes the driver.

    ``append`` goes through the Parquet sink.  In the other modes every micro-batch writes its own
    folder, so a repeated batch replaces itself; ``complete`` is the last folder, and of ``update``
    the last row of each of ``keys`` counts.
    """
    spark, out = stream.sparkSession, fresh_path(stream.sparkSession, "stream")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream-log")).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    batches: list[int] = []

    def write(rows: DataFrame, no: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/{no}")
        batches.append(no)

    writer.foreachBatch(write).start().awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    read = lambda no: spark.read.schema(stream.schema).parquet(f"{out}/{no}")
    if mode == "complete":
        return read(max(batches))
    rows = reduce(DataFrame.unionByName, [read(no).withColumn("_gl_batch", F.lit(no)) for no in sorted(set(batches))])
    last = Window.partitionBy(*keys).orderBy(F.desc("_gl_batch"))
    return rows.withColumn("_gl_no", F.row_number().over(last)).where("_gl_no = 1").drop("_gl_no", "_gl_batch")


def questions_in_batches(turns: DataFrame, work: Callable[[DataFrame], DataFrame], schema) -> DataFrame:
    """Rows that ``work`` makes of the questions of each micro-batch; a repeated batch replaces its rows."""
    spark, out = turns.sparkSession, fresh_path(turns.sparkSession, "reduced")
    batches: set[int] = set()

    def write(rows: DataFrame, no: int) -> None:
        work(rows).write.mode("overwrite").parquet(f"{out}/batch={no}")
        batches.add(no)

    each_batch(turns, write, fresh_path(spark, "reduced-log"))
    return spark.read.schema(schema).parquet(f"{out}/*") if batches else spark.createDataFrame([], schema)


def rate(spark: SparkSession, rows: int = 50, batches: int = 1) -> DataFrame:
    """A generated stream with ``rows`` rows a micro-batch, for load tests without files."""
    return spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", 2).load()


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", LATE).groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "v")


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", LATE).groupBy(F.window("ts", size, step)).agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """One question of a kind per user within the watermark."""
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type", "ts")


def with_static(events: DataFrame, static: DataFrame) -> DataFrame:
    return events.join(static, events.user_id == static.c_custkey, "left").select("event_id", "c_mktsegment")


def with_stream(left: DataFrame, right: DataFrame) -> DataFrame:
    """Questions and the same user's next event within an hour; both sides watermarked."""
    a = left.withWatermark("ts", LATE).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = right.withWatermark("ts", LATE).select(F.col("event_id").alias("b"), F.col("user_id").alias("w"), F.col("ts").alias("s"))
    return a.join(b, F.expr("u = w and s > t and s <= t + interval 1 hour")).select("a", "b")


def cache_state(events: DataFrame, ttl: str | None = None) -> DataFrame:
    """Key cache as state: one slot a user that is cleared when the kind of question changes.

    With ``ttl`` (such as "1 hour") a user's state goes when the watermark has passed that long after
    their last question; without it states stay.
    """
    seconds = None if ttl is None else int(pd.Timedelta(ttl).total_seconds())

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        held, hits, misses, until = state.get if state.exists else ("", 0, 0, 0)
        if seconds is not None and until <= state.getCurrentWatermarkMs():  # expired, but new rows came first
            held, hits, misses = "", 0, 0
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for kind in rows.event_type:
            if kind == held:
                hits += 1
            else:
                held, misses = kind, misses + 1
        if seconds is not None:
            until = int(rows["_gl_ms"].max()) + 1000 * seconds
            state.setTimeoutTimestamp(max(until, state.getCurrentWatermarkMs() + 1))
        state.update((held, hits, misses, until))
        yield pd.DataFrame({"user_id": [key[0]], "hits": [hits], "misses": [misses]})

    timeout = GroupStateTimeout.NoTimeout if ttl is None else GroupStateTimeout.EventTimeTimeout
    kept = events if ttl is None else events.withWatermark("ts", LATE).withColumn("_gl_ms", F.unix_millis("ts"))
    return kept.groupBy("user_id").applyInPandasWithState(step, "user_id long, hits long, misses long", "held string, hits long, misses long, until long", "update", timeout)


def each_batch(stream: DataFrame, work: Callable[[DataFrame, int], None], folder: str) -> None:
    """Run the batch reducer (or any work) on every micro-batch; a restart resumes from ``folder``."""
    stream.writeStream.foreachBatch(work).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()
