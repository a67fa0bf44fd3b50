"""Exact cosine search: blocks of rows meet blocks of queries, and only candidates leave a block."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ROWS, QUERIES = 4096, 1024
ROUNDED = 1.1e-6  # two cosines further apart than this differ after rounding to six places
NONE = -2.0  # stands for a pair without a cosine, which is ranked last
_BLOCK = "ids array<long>, sizes array<int>, flat array<float>"


def _blocks(rows: DataFrame, size: int) -> DataFrame:
    """vec_id, embedding as blocks of ids, lengths (-1: null, or with a null inside) and values."""

    def run(batches):
        for b in batches:
            for at in range(0, len(b), size):
                ids, vectors = b.column(0)[at : at + size], b.column(1)[at : at + size].to_pylist()
                whole = [v is not None and None not in v for v in vectors]
                sizes = [len(v) if w else -1 for v, w in zip(vectors, whole, strict=True)]
                flat = [x for v, w in zip(vectors, whole, strict=True) if w for x in v]
                yield pa.RecordBatch.from_arrays([pa.array([ids.to_pylist()], pa.list_(pa.int64())), pa.array([sizes], pa.list_(pa.int32())), pa.array([flat], pa.list_(pa.float32()))], ["ids", "sizes", "flat"])

    return rows.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<float>")).mapInArrow(run, _BLOCK)


def _matrix(sizes, flat, width: int) -> np.ndarray:
    out = np.zeros((len(sizes), width))
    full = np.arange(width)[None, :] < np.maximum(sizes, 0)[:, None]
    out[full] = flat
    return out


def _sums(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Row by row products summed from the first dimension on, as the statement does."""
    out = np.zeros(len(left))
    for k in range(left.shape[1]):
        out += left[:, k] * right[:, k]
    return out


def _firsts(keys: list, ids: np.ndarray, most: int) -> np.ndarray:
    """Places of the ``most`` smallest ids of each key."""
    seen: dict = {}
    kept = []
    for i in np.argsort(ids, kind="stable"):
        seen[keys[i]] = n = seen.get(keys[i], 0) + 1
        if n <= most:
            kept.append(i)
    return np.array(kept, np.int64)


def candidates(asked: tuple, held: tuple, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """query id, row id, cosine (NaN with a mask for none) of all pairs that may be among a query's ``most`` best of this block.

    ``asked`` and ``held`` are ids, lengths and values.  Of equal vectors only the first ``most`` + 1
    ids can be among them: the query itself is one of those at most.
    """
    width = max([1, *asked[1], *held[1]])
    q_ids, q_sizes, q = np.asarray(asked[0]), np.asarray(asked[1]), _matrix(np.asarray(asked[1]), asked[2], width)
    ids, sizes, rows = np.asarray(held[0]), np.asarray(held[1]), _matrix(np.asarray(held[1]), held[2], width)
    kept = _firsts([(n, v.tobytes()) for n, v in zip(sizes.tolist(), rows, strict=True)], ids, most + 1)
    ids, sizes, rows = ids[kept], sizes[kept], rows[kept]
    q_norm, norm = _sums(q, q), _sums(rows, rows)
    no = (q_sizes[:, None] != sizes[None, :]) | (q_sizes < 0)[:, None] | (q_norm[:, None] * norm[None, :] == 0)
    with np.errstate(all="ignore"):
        near = q @ rows.T / np.sqrt(q_norm[:, None] * norm[None, :])
    near = np.where(no, NONE, np.where(np.isnan(near), np.inf, near))
    own = q_ids[:, None] == ids[None, :]
    near[own] = -np.inf
    at = max(near.shape[1] - most, 0)
    least = np.partition(near, at, axis=1)[:, at]
    least = np.where(least == -np.inf, NONE, least)
    chosen = (near >= least[:, None] - ROUNDED) & ~own
    for k in np.flatnonzero(least == NONE):  # of pairs without a cosine the smallest ids come first
        last = np.flatnonzero(chosen[k] & (near[k] == NONE))
        chosen[k, last[np.argsort(ids[last], kind="stable")][most:]] = False
    i, j = np.nonzero(chosen)
    with np.errstate(all="ignore"):
        exact = _sums(q[i], rows[j]) / np.sqrt(q_norm[i] * norm[j])
    return q_ids[i], ids[j], np.ma.masked_array(exact, no[i, j])


def search(rows: DataFrame, queries: DataFrame, most: int = 5) -> DataFrame:
    """q, vec_id, place: the ``most`` rows of the largest cosine (six places, ties by id) for every query, without itself.

    Every query meets every row.  Products of whole blocks find candidates within the rounding; those
    are computed again in the statement's order of additions and ranked.
    """

    def run(batches):
        for b in batches:
            for k in range(len(b)):
                block = lambda *names: tuple(b.column(n)[k].values.to_numpy(zero_copy_only=False) for n in names)  # noqa: B023, E731
                q, v, c = candidates(block("ids", "sizes", "flat"), block("row_ids", "row_sizes", "row_flat"), most)
                yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(v, pa.int64()), pa.array(c.data, pa.float64(), mask=np.ma.getmaskarray(c))], ["q", "vec_id", "c"])

    asked = _blocks(queries, QUERIES)
    held = _blocks(rows, ROWS).select(F.col("ids").alias("row_ids"), F.col("sizes").alias("row_sizes"), F.col("flat").alias("row_flat"))
    found = held.crossJoin(asked).mapInArrow(run, "q long, vec_id long, c double")
    best = Window.partitionBy("q").orderBy(F.desc(F.round("c", 6)), "vec_id")
    return found.withColumn("place", F.row_number().over(best)).where(F.col("place") <= most).select("q", "vec_id", "place")
