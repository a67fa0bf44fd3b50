"""Helpers that the training-data operators share.

Missing texts count as empty everywhere.  Columns that an operator adds while it works carry the
prefix ``_gl_``; operators that return the caller's columns work with ``aside``, so that none clashes.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gistloom.shipping import ship
from gistloom.staging import discard, fresh_path, materialize, release, scratch

__all__ = ["aside", "ascii_lower", "count_words", "discard", "fresh_path", "materialize", "release", "scratch", "split_words", "table", "text_of"]

SPACES = " \t\n\x0b\f\r"
SPACE_CLASS = r"[\x20\x09-\x0D]"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(column: Column) -> Column:
    return F.coalesce(column, F.lit(""))


def split_words(column: Column) -> Column:
    """Maximal runs without the six ASCII spaces; no words give an empty array."""
    trimmed = F.btrim(text_of(column), F.lit(SPACES))
    empty = F.array().cast("array<string>")
    return F.when(trimmed == "", empty).otherwise(F.split(trimmed, SPACE_CLASS + "+"))


def count_words(column: Column) -> Column:
    """Number of words; a split at one plain character is far cheaper than at a class, and lines hold blanks mostly."""
    text = text_of(column)
    parts = F.when(text.rlike(r"[\x09-\x0D]"), F.split(text, SPACE_CLASS)).otherwise(F.split(text, " "))
    return F.size(F.array_remove(parts, "")).cast("long")


def aside(docs: DataFrame, *used: str) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """The table with all columns but ``used`` under names that no operator uses, and the way back.

    Columns that the operator adds stand for columns of the same name that the caller had.
    """
    names = {c: c if c in used else f"_own{i}" for i, c in enumerate(docs.columns)}

    def back(df: DataFrame) -> DataFrame:
        kept = [F.col(names[c]).alias(c) for c in docs.columns if names[c] == c or c not in df.columns]
        added = [F.col(c) for c in df.columns if c not in names.values()]
        return df.select(*kept, *added)

    return docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()]), back


def ascii_lower(column: Column) -> Column:
    """A-Z only: other letters keep their case."""
    return F.translate(text_of(column), UPPER, LOWER)
