"""Benchmark decontamination by n-gram windows.

The benchmark's normalised windows form a hash set.  It is broadcast while its counted rows and bytes
stay under ``broadcast_windows`` and ``BROADCAST_BYTES``; beyond that the same join shuffles.  One pass over the training texts
hashes every token window and probes the set; documents with a probe are read again and their
windows compared word by word, so hash collisions cannot decide anything.

Defined cases: a null text or one without words has no words, no hits and is not contaminated; an
item of fewer than 13 words is one window, an item without words none; repeated benchmark rows
count once; repeated document rows are judged alike and all returned; a null item_id is ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gistloom.llm.quality_rules import let
from gistloom.llm.shared import ascii_lower, aside, materialize

N = 13
BROADCAST_WINDOWS = 1_000_000
BROADCAST_BYTES = 100_000_000  # of the windows' words
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def bound_tokens(column: Column, body) -> Column:
    """``body`` of the words: runs of a-z, 0-9 and characters beyond ASCII, A-Z lower-cased.

    Only the first and the last part of the split can be empty.
    """
    return let(F.split(ascii_lower(column), SEPARATORS), lambda p: let(
        F.slice(p, F.when(p[0] == "", 2).otherwise(1), F.greatest(F.size(p) - F.when(p[0] == "", 1).otherwise(0) - F.when((F.size(p) > 1) & (F.element_at(p, -1) == ""), 1).otherwise(0), F.lit(0))), body))


def _grams(words: Column, length: int) -> Column:
    starts = F.when(F.size(words) >= length, F.sequence(F.lit(1), F.size(words) - (length - 1))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: F.xxhash64(F.slice(words, i, F.lit(length))))


def benchmark_windows(benchmark: DataFrame, n: int = N) -> DataFrame:
    """item_id, length, gram: distinct windows of the items."""
    def windows(w: Column) -> Column:
        size = F.size(w)
        length = F.least(size, F.lit(n))
        starts = F.when(size > 0, F.sequence(F.lit(1), size - length + 1)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.struct(length.alias("length"), F.slice(w, i, length).alias("words")))

    return (
        benchmark.where(F.col("item_id").isNotNull()).select("item_id", F.explode(bound_tokens(F.col("text"), windows)).alias("g"))
        .select("item_id", F.col("g.length").alias("length"), F.array_join("g.words", " ").alias("gram"), F.xxhash64("g.words").alias("hash")).distinct()
    )


def _union_length(spans: Column) -> Column:
    """Words under the (pos, length) spans, sorted by pos; pos counts from 1."""
    def step(s: Column, x: Column) -> Column:
        end = F.greatest(s["end"], x["pos"] + x["length"] - 1)
        return F.struct(end.alias("end"), (s["sum"] + end - F.greatest(s["end"], F.least(x["pos"] - 1, end))).alias("sum"))

    return F.aggregate(F.array_sort(spans), F.struct(F.lit(0).alias("end"), F.lit(0).alias("sum")), step, lambda s: s["sum"])


def find_contamination(docs: DataFrame, benchmark: DataFrame, n: int = N, broadcast_windows: int = BROADCAST_WINDOWS) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated and spans of every document row."""
    windows = materialize(benchmark_windows(benchmark, n), "windows")
    lengths = sorted(r[0] for r in windows.groupBy("length").count().select("length").collect())  # n values at most
    size = windows.agg(F.count("*").alias("rows"), F.coalesce(F.sum(F.octet_length("gram")), F.lit(0)).alias("bytes")).first()
    bounded = size.rows <= broadcast_windows and size.bytes <= BROADCAST_BYTES
    small = F.broadcast if bounded else (lambda df: df)
    probe = small(windows.select(F.col("hash").alias("_gl_h"), F.col("length").alias("_gl_len")).distinct())

    mark = F.xxhash64("doc_id", "text")
    base = docs.select("doc_id", "text", mark.alias("_gl_t"))
    # value 0 of the first list says how many words the text has; what follows are window hashes
    lists = bound_tokens(F.col("text"), lambda w: F.array(F.array(F.size(w).cast("long")), *[_grams(w, k) for k in lengths]))
    rows = (
        base.select("doc_id", "_gl_t", F.posexplode(lists).alias("_gl_k", "_gl_list"))
        .select("doc_id", "_gl_t", "_gl_k", F.posexplode("_gl_list").alias("_gl_pos", "_gl_value"))
    )
    size_of = F.element_at(F.array(F.lit(0), *[F.lit(k) for k in lengths]), F.col("_gl_k") + 1)
    rows = rows.withColumn("_gl_size", size_of)
    hit = F.col("_gl_h").isNotNull()
    is_count = F.col("_gl_k") == 0
    kept = rows.join(probe, (F.col("_gl_value") == F.col("_gl_h")) & (F.col("_gl_size") == F.col("_gl_len")), "left").where(hit | is_count)
    found = materialize(
        kept.groupBy("doc_id", "_gl_t").agg(
            F.max(F.when(is_count, F.col("_gl_value"))).alias("n_words"),
            F.sum(F.when(is_count, 1).otherwise(0)).alias("_gl_copies"),
            F.collect_set(F.when(hit, F.struct((F.col("_gl_pos") + 1).alias("pos"), F.col("_gl_size").alias("length")))).alias("_gl_hits"),
        ),
        "probes",
    )
    touched = found.where(F.size("_gl_hits") > 0).select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), "_gl_hits")
    same = F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.col("_gl_t") == F.col("_gl_m"))
    grams = bound_tokens(F.col("text"), lambda w: F.transform("_gl_hits", lambda h: F.struct(h["pos"].alias("pos"), h["length"].alias("length"), F.array_join(F.slice(w, h["pos"], h["length"]), " ").alias("gram"))))
    opened = base.join(touched, same).select("doc_id", "_gl_t", F.explode(grams).alias("_gl_g"))
    book = small(windows.select("item_id", F.col("length").alias("_gl_len"), F.col("gram").alias("_gl_gram")))
    checked = opened.join(book, (F.col("_gl_g.gram") == F.col("_gl_gram")) & (F.col("_gl_g.length") == F.col("_gl_len")))
    verified = checked.groupBy("doc_id", "_gl_t").agg(
        F.collect_set(F.struct(F.col("_gl_g.pos").alias("pos"), F.col("_gl_g.length").alias("length"))).alias("spans"),
        F.array_sort(F.collect_set(F.col("item_id").cast("string"))).alias("_gl_items"),
    ).select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), "spans", "_gl_items")
    none = F.array().cast("array<string>")
    items = F.coalesce("_gl_items", none)
    n_hit = F.coalesce(_union_length(F.col("spans")), F.lit(0)).cast("long")
    out = found.join(verified, same, "left").withColumn("n_hit", n_hit)
    return out.select(
        "doc_id", "n_words", "n_hit", F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"), F.array_sort("spans").alias("spans"), F.col("_gl_t"),
        F.explode(F.sequence(F.lit(1), F.col("_gl_copies").cast("int"))).alias("_gl_copy"),
    ).drop("_gl_copy")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Documents without the contaminated ones; all others stay as they are."""
    docs, back = aside(docs, "doc_id", "text")
    bad = find_contamination(docs, benchmark, **options).where("contaminated").select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m")).distinct()
    return back(docs.join(bad, F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.xxhash64("doc_id", "text") == F.col("_gl_m")), "left_anti"))
