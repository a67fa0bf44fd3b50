"""Bounded, deterministic samples of labelled documents."""

from __future__ import annotations

import zlib

import numpy as np

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WINDOW_CHARS = 600


def fold(doc_id: Column, folds: int) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds))


def sample(docs: DataFrame, labels: DataFrame, label: str, keep: Column, rows: int, max_chars: int | None = None, value: int | None = None) -> DataFrame:
    """(doc_id, text, y) of at most ``rows`` labelled documents, in the order of a hash of the id.

    With ``max_chars`` every chosen document stays, and a text longer than the common level at which
    all together fit into that many characters is read by windows spread evenly over its whole length.
    Labels that are null or not joined to a document are left out.
    """
    known = known_labels(labels, label, keep, value)
    ids = known.groupBy("doc_id").agg(F.max(label).cast("int").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    body = F.coalesce("text", F.lit(""))
    if max_chars is not None:
        sized = docs.select("doc_id", F.char_length(body).alias("n")).join(F.broadcast(ids), "doc_id").select("n").collect()
        body = spread_windows(body, fair_level([r.n for r in sized], max_chars))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), body.alias("text")).join(F.broadcast(ids), "doc_id")


def known_labels(labels: DataFrame, label: str, keep: Column, value: int | None = None) -> DataFrame:
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & keep)
    return known if value is None else known.where(F.col(label) == value)


def fair_level(sizes: list[int], most: int) -> int:
    """Largest level (1 at least) such that the sizes, each cut at it, add up to ``most`` or less."""
    ordered = np.sort(np.array(sizes, np.int64))
    rest = most
    for i, n in enumerate(ordered):
        if n * (len(ordered) - i) > rest:
            return max(1, int(rest // (len(ordered) - i)))
        rest -= n
    return max(1, int(ordered[-1])) if len(ordered) else 1


def spread_windows(text: Column, level: int) -> Column:
    """Texts of up to ``level`` characters as they are; of longer ones windows from the first to the last character."""
    count = max(2, level // WINDOW_CHARS)
    width = max(1, level // count - 1)
    gaps = F.char_length(text) - width
    start = lambda i: (F.lit(1) + F.floor(gaps * i / (count - 1))).cast("int")
    cut = F.transform(F.sequence(F.lit(0), F.lit(count - 1)), lambda i: F.substring(text, start(i), F.lit(width)))
    return F.when(F.char_length(text) <= level, text).otherwise(F.array_join(cut, " "))


def hash_key(doc_id: int) -> int:
    return zlib.crc32(b"order:%d" % doc_id)
