"""Source mixing by a time-varying curriculum.

Each source has a weight that may change over training time t in [0, 1]; its integral is the
source's share of all words.  A source's documents form a stream in a fixed pseudo-random order,
repeated as often as its target asks for.  The words a copy begins at are turned into a training
position by inverting the integrated schedule, and the mix is range-sorted by that position.

Defined cases: a missing text has no words, takes none and has no position; an empty table gives
an empty mix; rows that are equal in every column are interchangeable; all words zero gives zero
targets.  Prefix sums run over two levels of hash buckets, so no source meets in one task.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gistloom.llm.shared import aside, count_words, materialize

WEIGHTS = (5, 2, 1)  # dealt to the sources in code point order, null last
REPEATS = 3
BUCKET_ROWS = 500


def source_targets(totals: DataFrame, weights=WEIGHTS, repeats: int = REPEATS, budget: Column | None = None) -> DataFrame:
    """(source, source_size) -> + weight, target.  One row a source: the only rows that meet.

    Targets are weight times a common level, cut at ``repeats`` times the source.  Sorted by the
    level at which they are cut, the cut sources are a prefix, so one running sum finds the level.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    deal = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.col("_gl_no") - 1, F.lit(len(weights))) + 1).cast("int"))
    everything = Window.partitionBy()
    by_cut = Window.orderBy("_gl_cut", "_gl_no")
    earlier = by_cut.rowsBetween(Window.unboundedPreceding, -1)
    dealt = (
        totals.withColumn("_gl_no", F.row_number().over(order))
        .withColumn("weight", deal)
        .withColumn("_gl_cap", F.col("source_size").cast("double") * repeats)
        .withColumn("_gl_cut", F.col("_gl_cap") / F.col("weight"))
        .withColumn("_gl_all", budget if budget is not None else F.sum("source_size").over(everything).cast("double"))
    )
    level = (F.col("_gl_all") - F.coalesce(F.sum("_gl_cap").over(earlier), F.lit(0.0))) / (
        F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(earlier), F.lit(0.0))
    )
    found = dealt.withColumn("_gl_level", level).withColumn("_gl_free", F.col("_gl_cut") > F.col("_gl_level"))
    final = F.min(F.when(F.col("_gl_free"), F.struct("_gl_cut", "_gl_no", "_gl_level"))).over(everything)["_gl_level"]
    return (
        found.withColumn("_gl_final", final)
        .withColumn("target", F.coalesce(F.least("_gl_cap", F.col("_gl_final") * F.col("weight")), F.col("_gl_cap")))
        .select("source", "source_size", "weight", "target", F.col("_gl_no").alias("source_no"))
    )


def invert_schedule(share: Column, slope: Column) -> Column:
    """t at which the integral of 1 + slope * (2t - 1) over [0, t] reaches ``share``."""
    base = 1 - slope
    curved = (F.sqrt(base * base + 4 * slope * share) - base) / (2 * slope)
    return F.when(F.abs(slope) < 1e-9, share).otherwise(curved)


def schedule_slope(source_no: Column) -> Column:
    """Default curriculum: heavy sources rise, middle ones stay, light ones fall."""
    return F.element_at(F.array(F.lit(0.5), F.lit(0.0), F.lit(-0.5)), (F.pmod(source_no - 1, F.lit(3)) + 1).cast("int"))


def drawn(docs: DataFrame, weights=WEIGHTS, repeats: int = REPEATS, seed: str = "mix") -> DataFrame:
    """doc_id, size, source_size, target, taken, the positions of all copies, first to last, and _gl_mark of the row; in no order."""
    spark = docs.sparkSession
    mark = row_mark(docs).alias("_gl_mark")
    name = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("-"), mark.cast("string")))  # rows without doc_id spread, too
    sizes = materialize(
        docs.select("doc_id", "source", count_words(F.col("text")).alias("size"), F.md5(F.concat_ws(":", F.lit(seed), name)).alias("_gl_key"), mark), "mix-sizes")
    rows = sizes.count()
    bits = min(30, max(2, 2 * math.ceil(math.log2(max(2, rows / BUCKET_ROWS)) / 2)))
    fine = F.shiftright(F.conv(F.substring("_gl_key", 1, 8), 16, 10).cast("long"), 32 - bits)
    sizes = sizes.withColumn("_gl_fine", fine).withColumn("_gl_coarse", F.shiftright("_gl_fine", bits // 2))

    same = lambda a, b: a.eqNullSafe(b)
    cells = sizes.groupBy("source", "_gl_coarse", "_gl_fine").agg(F.sum("size").alias("_gl_sum"))
    coarse = cells.groupBy("source", "_gl_coarse").agg(F.sum("_gl_sum").alias("_gl_sum"))
    targets = source_targets(coarse.groupBy("source").agg(F.sum("_gl_sum").alias("source_size")), weights, repeats)
    before = lambda *by: Window.partitionBy(*by[:-1]).orderBy(by[-1]).rowsBetween(Window.unboundedPreceding, -1)
    zero = F.lit(0).cast("long")
    coarse = coarse.select(
        F.col("source").alias("_gl_s1"), F.col("_gl_coarse").alias("_gl_c1"),
        F.coalesce(F.sum("_gl_sum").over(before("source", "_gl_coarse")), zero).alias("_gl_b1"),
    )
    cells = cells.withColumn("_gl_b2", F.coalesce(F.sum("_gl_sum").over(before("source", "_gl_coarse", "_gl_fine")), zero))
    starts = cells.join(coarse, same(F.col("source"), F.col("_gl_s1")) & (F.col("_gl_coarse") == F.col("_gl_c1"))).select(
        F.col("source").alias("_gl_s2"), F.col("_gl_fine").alias("_gl_f2"), (F.col("_gl_b1") + F.col("_gl_b2")).alias("_gl_start")
    )
    inner = Window.partitionBy("source", "_gl_fine").orderBy("_gl_key", "doc_id", "size", "_gl_mark").rowsBetween(Window.unboundedPreceding, -1)
    placed = (
        sizes.withColumn("_gl_in", F.coalesce(F.sum("size").over(inner), zero))
        .join(starts, same(F.col("source"), F.col("_gl_s2")) & (F.col("_gl_fine") == F.col("_gl_f2")))
        .withColumn("_gl_before", F.col("_gl_start") + F.col("_gl_in"))
        .drop("_gl_s2", "_gl_f2")
    )
    targets = targets.withColumnRenamed("source", "_gl_s3")
    goal, total = F.least(F.round("target").cast("long"), repeats * F.col("source_size")), F.col("source_size")
    rounds = F.when(total > 0, F.floor(goal / total)).otherwise(zero)
    joined = (
        placed.join(targets, same(F.col("source"), F.col("_gl_s3")))
        .withColumn("_gl_goal", goal)
        .withColumn("_gl_full", rounds)
        .withColumn("_gl_rest", F.col("_gl_goal") - F.col("_gl_full") * total)
        .withColumn("taken", F.col("_gl_full") * F.col("size") + F.greatest(zero, F.least(F.col("size"), F.col("_gl_rest") - F.col("_gl_before"))))
    )
    # copy j begins j whole sources after the first one; the last may be taken in part
    begins = F.transform(F.sequence(zero, F.ceil(F.col("taken") / F.col("size")) - 1), lambda j: (F.col("_gl_before") + j * F.col("source_size")) / F.col("_gl_goal"))
    positions = F.transform(begins, lambda share: invert_schedule(share, schedule_slope(F.col("source_no"))))
    return joined.withColumn("positions", F.when(F.col("taken") > 0, positions)).select("doc_id", "size", "source_size", "target", "taken", "positions", "_gl_mark")


def row_mark(docs: DataFrame) -> Column:
    """A hash of all columns that have an order or an equality: rows with one doc_id and mark are the same."""
    return F.xxhash64(*[F.col(f"`{f.name}`") for f in docs.schema if not any(k in f.dataType.simpleString() for k in ("map<", "variant"))])


def mix(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken, position of the first copy, positions of all; sorted ranges of position."""
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return (
        drawn(docs, **options).withColumn("position", F.col("positions")[0])
        .select("doc_id", "size", "source_size", "target", "taken", "position", "positions")
        .repartitionByRange(parts, F.col("position").asc_nulls_last(), "doc_id")
        .sortWithinPartitions(F.col("position").asc_nulls_last(), "doc_id")
    )


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """A row for every copy that the mix draws, in training order.

    mix_copy of mix_copies counts the copies of a document, mix_taken the words of this copy and
    mix_position its place.  A copy that is drawn in part keeps its whole text; ``mix_taken`` says
    how many words of it count.  Every row is drawn for itself; equal rows give equal copies.
    """
    docs, back = aside(docs, "doc_id", "text", "source")
    plan = drawn(docs, **options).where(F.col("taken") > 0)
    plan = plan.select("doc_id", "_gl_mark", "size", "taken", F.size("positions").cast("long").alias("mix_copies"), F.posexplode("positions").alias("_gl_copy", "mix_position"))
    plan = plan.select(
        F.col("doc_id").alias("_gl_id"), F.col("_gl_mark").alias("_gl_row"), F.least("size", F.col("taken") - F.col("_gl_copy") * F.col("size")).alias("mix_taken"),
        "mix_copies", (F.col("_gl_copy") + 1).alias("mix_copy"), "mix_position",
    )
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # equal rows meet once; each of their places in the plan brings one of them back
    rows = docs.withColumn("_gl_mark", row_mark(docs)).dropDuplicates(["doc_id", "_gl_mark"])
    placed = rows.join(plan, F.col("doc_id").eqNullSafe(F.col("_gl_id")) & (F.col("_gl_mark") == F.col("_gl_row"))).drop("_gl_id", "_gl_row", "_gl_mark")
    return back(placed).repartitionByRange(parts, "mix_position", "doc_id", "mix_copy").sortWithinPartitions("mix_position", "doc_id", "mix_copy")
