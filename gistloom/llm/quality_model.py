"""Quality classifier: histogram gradient-boosted trees over statistics of the whole text.

Learns from at most ``max_rows`` labelled documents outside the held-out fold.  Label, language,
source and id are never features.  Defined cases: null or empty texts have all-zero statistics and
get the score of those; without labels of both classes every score is the prior; repeated rows are
scored alike; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.llm import kernels as K
from gistloom.llm import trees
from gistloom.llm.labelled import fold, sample

MAX_ROWS = 20_000
FOLDS, HELD = 5, 0
CLASSES = 12
CLASS_OF = np.zeros(256, np.uint8)
CLASS_OF[65:91] = 1
CLASS_OF[97:123] = 2
CLASS_OF[48:58] = 3
CLASS_OF[[ord(c) for c in "#*$%&<>"]] = 4
CLASS_OF[ord("|")] = 5
CLASS_OF[ord("!")] = 6
CLASS_OF[[ord(c) for c in ".,;:?"]] = 7
CLASS_OF[10] = 8
CLASS_OF[[9, 11, 12, 13, 32]] = 9
CLASS_OF[128:192] = 10
CLASS_OF[192:] = 11


def statistics(column: pa.Array) -> np.ndarray:
    """One row of statistics for each text."""
    out = []
    for row, end, data, offsets in K.pieces(column):
        n = end - row
        size = np.diff(offsets)
        who = np.repeat(np.arange(n), size)
        counts = np.bincount(who * CLASSES + CLASS_OF[data], minlength=n * CLASSES).reshape(n, CLASSES).astype(float)
        starts, ends, firsts = K.word_bounds(data, offsets)
        h = K.word_hashes(K.FOLD[data], starts, ends)
        words = np.diff(firsts)
        length = (ends - starts).astype(float)
        owner = np.repeat(np.arange(n), words)
        total, square = np.bincount(owner, length, n), np.bincount(owner, length**2, n)
        mean = total / np.maximum(words, 1)
        spread = np.sqrt(np.maximum(square / np.maximum(words, 1) - mean**2, 0))
        longest, distinct, lines, other, pairs = np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n)
        after = np.array([10], np.uint8)
        for i in range(n):
            a, b = firsts[i], firsts[i + 1]
            if b > a:
                longest[i] = length[a:b].max()
                distinct[i] = len(np.unique(h[a:b])) / (b - a)
                two = h[a : b - 1] * K.GOLDEN + h[a + 1 : b]
                pairs[i] = len(np.unique(two)) / max(1, len(two))
                body = data[offsets[i] : offsets[i + 1]]
                rows = np.concatenate([body, after]).tobytes().split(b"\n")
                rows = [r for r in rows if r.strip()]
                lines[i], other[i] = len(rows), len(set(rows)) / max(1, len(rows))
        chars = np.maximum(size, 1)[:, None]
        shares = counts / chars
        w = np.maximum(words, 1)
        per_word = np.stack([counts[:, 4] / w, counts[:, 5] / w, counts[:, 6] / w, counts[:, 1] / w, counts[:, 3] / w, counts[:, 7] / w], 1)
        rest = np.stack([np.log1p(size), np.log1p(words), mean, spread, np.log1p(longest), distinct, pairs, lines / w, other], 1)
        out.append(np.concatenate([shares, per_word, rest], 1))
    return np.concatenate(out) if out else np.zeros((0, 27))


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, **options) -> trees.Forest:
    rows = sample(docs, labels, "quality", fold(F.col("doc_id"), FOLDS) != HELD, max_rows)

    def run(batches):
        for b in batches:
            x = statistics(b.column(0))
            yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.list_(pa.float64())), b.column(1)], ["x", "y"])

    got = rows.select("text", "y").mapInArrow(run, "x array<double>, y int").toPandas()
    if not len(got):
        return trees.fit(np.zeros((0, 1)), np.zeros(0), **options)
    got = got.assign(k=[tuple(r) for r in got.x]).sort_values(["k", "y"])  # the order of rows must not matter
    return trees.fit(np.stack(got.x.to_numpy()), got.y.to_numpy().astype(float), **options)


def score(docs: DataFrame, forest: trees.Forest, threshold: float = 0.3) -> DataFrame:
    def run(batches):
        for b in batches:
            p = forest.proba(statistics(b.column(1)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double, predicted int")
    held = F.coalesce(fold(F.col("doc_id"), FOLDS) == HELD, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", "predicted")
