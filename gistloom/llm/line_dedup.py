"""Line deduplication by a suffix array over line-ID sequences.

Documents are sequences of line IDs (lines without a word are left out and never removed).  Prefix
doubling gives every suffix the rank of its first 1, 2, 4, ... lines among all suffixes; suffixes
whose rank is unique are settled and leave the next round.  A longest-common-prefix interval of
depth d is the set of suffixes that agree on d lines, named by two overlapping ranks.  A run of
lines with at least ``min_words`` words that has an earlier equal copy (earlier document by doc_id,
or earlier in the same one) is deleted; the earliest copy stays.

Every such run is the union of minimal runs, which reach ``min_words`` words and lose that with
their first or last line.  They have ``min_words`` lines at most, so log2(min_words) rounds settle
every depth that matters.  Ranks are monotone IDs over a range-sorted table of *distinct* pairs, so
a line that a third of all documents share is one row there; only joins meet hot keys, and those
are split by adaptive execution.

Defined cases: null texts have no lines and stay null; rows equal in doc_id and text are one
document and treated alike; ties of doc_id are ordered by a hash of the text; an empty table gives
an empty result.  ``remove_repeats`` drops a document only if deletion leaves it without words.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gistloom.llm.quality_rules import let
from gistloom.llm.shared import aside, count_words, materialize, text_of

MIN_WORDS = 10
KEY = ["doc_id", "_gl_t"]


def line_table(docs: DataFrame) -> DataFrame:
    """doc_id, _gl_t, pos (line of the text), ord (among lines with words), h1, h2, nw."""
    lines = (
        docs.select("doc_id", F.xxhash64("doc_id", "text").alias("_gl_t"), F.posexplode(F.split(text_of(F.col("text")), "\n")).alias("pos", "line"))
        .select(*KEY, "pos", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(7), "line").alias("h2"), count_words(F.col("line")).alias("nw"))
        .where("nw > 0")
        .repartition(*KEY)
        .distinct()
    )
    return lines.withColumn("ord", F.row_number().over(Window.partitionBy(*KEY).orderBy("pos")))


def _ranked(pairs: DataFrame, a: str, b: str, name: str) -> DataFrame:
    """(a, b, rank) of the pairs that occur twice or more; rank follows the order of (a, b)."""
    parts = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    again = pairs.groupBy(a, b).agg(F.count("*").alias("n")).where("n > 1").select(a, b)
    ordered = again.repartitionByRange(parts, a, b).sortWithinPartitions(a, b)
    return materialize(ordered.withColumn("rank", F.monotonically_increasing_id()), name)


def suffix_ranks(lines: DataFrame, depth: int) -> list[DataFrame]:
    """Level k: (doc_id, _gl_t, ord, rank) of suffixes whose first 2^k lines occur elsewhere too."""
    ranks = _ranked(lines, "h1", "h2", "rank0")
    level = materialize(lines.join(ranks, ["h1", "h2"]).select(*KEY, "ord", "rank"), "level0")
    levels, reach = [level], 1
    while reach * 2 <= depth:
        nxt = level.select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), (F.col("ord") - reach).alias("_gl_o"), F.col("rank").alias("b"))
        pairs = level.withColumnRenamed("rank", "a").join(
            nxt, F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.col("_gl_t") == F.col("_gl_m")) & (F.col("ord") == F.col("_gl_o"))
        ).select(*KEY, "ord", "a", "b")
        ranks = _ranked(pairs, "a", "b", f"rank{len(levels)}")
        level = materialize(pairs.join(ranks, ["a", "b"]).select(*KEY, "ord", "rank"), f"level{len(levels)}")
        levels.append(level)
        reach *= 2
    return levels


def _minimal_runs(held: DataFrame, min_words: int) -> DataFrame:
    """(doc_id, _gl_t, first, n): runs of repeated lines that reach min_words, and lose that with an end line."""
    by = Window.partitionBy(*KEY).orderBy("ord")
    reach = min_words - 1
    ahead = F.collect_list(F.struct("ord", "nw")).over(by.rangeBetween(0, reach))
    back = F.reverse(F.collect_list(F.struct("ord", "nw")).over(by.rangeBetween(-reach, 0)))

    def length(run):
        step = lambda s, x: F.when(
            (s["words"] >= min_words) | (F.abs(x["ord"] - F.col("ord")) != s["n"]), s
        ).otherwise(F.struct((s["n"] + 1).alias("n"), (s["words"] + x["nw"]).alias("words")))
        start = F.struct(F.lit(0).alias("n"), F.lit(0).cast("long").alias("words"))
        return F.aggregate(run, start, step, lambda s: F.when(s["words"] >= min_words, s["n"]))

    seen = held.select(*KEY, "ord", length(ahead).alias("f"), length(back).alias("r"))
    ends = F.array(F.struct(F.col("ord").alias("first"), F.col("f").alias("n")), F.struct((F.col("ord") - F.col("r") + 1).alias("first"), F.col("r").alias("n")))
    return seen.select(*KEY, F.explode(F.array_distinct(F.filter(ends, lambda e: e["n"].isNotNull()))).alias("e")).select(*KEY, "e.first", "e.n").distinct()


def later_copies(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc_id, _gl_t, removed): sorted positions of the lines to delete; documents without any are left out."""
    lines = materialize(line_table(docs), "lines")
    levels = suffix_ranks(lines, min_words)
    held = lines.select(*KEY, "ord", "nw").join(
        levels[0].select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), F.col("ord").alias("_gl_o")),
        F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.col("_gl_t") == F.col("_gl_m")) & (F.col("ord") == F.col("_gl_o")),
    ).select(*KEY, "ord", "nw")
    runs = _minimal_runs(held, min_words).withColumn("k", F.floor(F.log2(F.col("n").cast("double") + 1e-9)).cast("int"))
    book = None
    for k, level in enumerate(levels):
        tagged = level.withColumn("k", F.lit(k))
        book = tagged if book is None else book.unionByName(tagged)
    book = book.select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), F.col("ord").alias("_gl_o"), F.col("k").alias("_gl_k"), "rank")

    def named(df: DataFrame, at, name: str) -> DataFrame:
        same = F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.col("_gl_t") == F.col("_gl_m")) & (at == F.col("_gl_o")) & (F.col("k") == F.col("_gl_k"))
        return df.join(book, same).drop("_gl_d", "_gl_m", "_gl_o", "_gl_k").withColumnRenamed("rank", name)

    last = F.col("first") + F.col("n") - F.pow(F.lit(2), F.col("k")).cast("int")
    runs = named(named(runs, F.col("first"), "a"), last, "b")
    runs = materialize(runs.select(*KEY, "first", "n", "a", "b"), "runs")
    # pre-aggregated before its shuffle and written, so that the join may split the runs of one interval over tasks
    intervals = runs.groupBy("n", "a", "b").agg(F.min(F.struct(*KEY, "first")).alias("origin"), F.count("*").alias("size")).where("size > 1").drop("size")
    intervals = materialize(intervals, "intervals")
    later = runs.join(intervals, ["n", "a", "b"]).where(~F.struct(*KEY, "first").eqNullSafe(F.col("origin")))
    gone = later.select(*KEY, F.explode(F.sequence(F.col("first"), F.col("first") + F.col("n") - 1)).alias("ord")).distinct()
    gone = gone.select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), F.col("ord").alias("_gl_o"))
    placed = lines.join(gone, F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.col("_gl_t") == F.col("_gl_m")) & (F.col("ord") == F.col("_gl_o")))
    return placed.groupBy(*KEY).agg(F.array_sort(F.collect_list("pos")).alias("removed"), F.sum("nw").alias("removed_words"))


def with_removals(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Documents with removed (positions or null), removed_words and the new text as _gl_text."""
    gone = materialize(later_copies(docs, min_words), "gone").select(F.col("doc_id").alias("_gl_d"), F.col("_gl_t").alias("_gl_m"), F.col("removed").alias("_gl_removed"), F.col("removed_words").alias("_gl_words"))
    joined = docs.join(gone, F.col("doc_id").eqNullSafe(F.col("_gl_d")) & (F.xxhash64("doc_id", "text") == F.col("_gl_m")), "left").drop("_gl_d", "_gl_m")
    rest = let(F.split(F.col("text"), "\n"), lambda x: F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(x) - 1), F.col("_gl_removed")), lambda i: F.get(x, i)), "\n"))
    return joined.withColumn("_gl_text", F.when(F.col("_gl_removed").isNull(), F.col("text")).otherwise(rest))


def remove_repeats(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """Documents with later copies deleted; n_chars follows the text where the table has it."""
    plain, back = aside(docs, "doc_id", "text", "n_chars")
    done = with_removals(plain, min_words).where(F.col("_gl_removed").isNull() | (count_words(F.col("_gl_text")) > 0))
    new = {"text": F.col("_gl_text")}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("_gl_removed").isNull(), F.col("n_chars")).otherwise(F.char_length("_gl_text").cast("long"))
    return back(done.withColumns(new).select(*plain.columns))
