"""Rows of a table ranked by attention without its vectors: a task adds up scores by row and gives places only."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.operators import attention as A
from gistloom.operators.chunking import CHUNK

PACK = 256  # questions of one table that a task handles together
CELLS = 4_000_000  # sums of a task at a time
SHARES = 8  # tasks among which the packs of a table are dealt
BLOCK = 100_000  # weights looked up together, as many as stay in a cache
SIGNS = A.LAYERS * A.HEADS
RANKED = "doc_id long, query_id string, gold_place int, best array<int>"


@lru_cache(maxsize=400_000)
def _key(before: str, token: str) -> bytes:
    """``attention.keys_of`` of one token after its predecessor, layer by layer."""
    return A._signs(token) + A._signs(f"{before} {token}") + A._signs(token[:4])


def _keys(texts: list[list[str]]) -> np.ndarray:
    """(tokens, layers times heads) sign words of chunks or questions one after the other."""
    low = [[t.lower() for t in tokens] for tokens in texts]
    flat = b"".join(_key(b, t) for tokens in low for b, t in zip(["^", *tokens], tokens, strict=False))
    return np.frombuffer(flat, ">u4").astype(np.uint32).reshape(-1, SIGNS)


def signs(tokens: list[str]) -> np.ndarray:
    """(layers times heads, tokens) sign words."""
    return _keys([tokens]).T


def _question_rows(questions: list[list[str]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct rows of question tokens (signs, what the question adds to denominators) and, of each question token, its row; questions flat."""
    table = np.array(A.TABLE, np.int64)
    keys = _keys(questions)
    sizes = np.array([len(q) for q in questions])
    first = np.cumsum(sizes) - sizes
    rows = np.zeros((len(keys), 2 * SIGNS), np.int64)
    rows[:, :SIGNS] = keys
    for m in set(sizes.tolist()) - {0}:
        at = first[sizes == m][:, None] + np.arange(m)
        k = keys[at].transpose(0, 2, 1)
        rows[at, SIGNS:] = np.tril(table[np.bitwise_count(k[..., :, None] ^ k[..., None, :])]).sum(-1).transpose(0, 2, 1)
    _, once, which = np.unique(rows.view(f"V{rows.shape[1] * 8}").ravel(), return_index=True, return_inverse=True)
    return rows[once, :SIGNS].astype(np.uint32), rows[once, SIGNS:], which


def row_scores(tokens: list[str], structural: np.ndarray, starts: np.ndarray, keys: np.ndarray, own: np.ndarray, base_len: int = CHUNK) -> np.ndarray:
    """(question token row, table row): chunk scores times the chunk's length, summed over a table row's tokens."""
    numerators = np.concatenate([np.array(A.TABLE, np.int64), np.array(A.TABLE, np.int64) * A.GAIN])
    scaled = (numerators * A.UNIT).astype(np.uint64)
    shift = np.where(structural, 33, 0).astype(np.uint8)
    keys, own = np.ascontiguousarray(keys.T)[:, :, None], np.ascontiguousarray(own.T) + A.SINK
    out = np.zeros((keys.shape[1], len(starts)), np.int64)
    for a in range(0, len(tokens), base_len):
        ctx = signs(tokens[a : a + base_len])[:, None, :]
        n = ctx.shape[2]
        low = int(np.searchsorted(starts, a, "right")) - 1
        cuts = np.concatenate([[0], starts[low + 1 : int(np.searchsorted(starts, a + n, "left"))] - a])
        most = max(1, BLOCK // (SIGNS * n))
        lines = (np.arange(SIGNS * most) * len(numerators)).reshape(SIGNS, most, 1)
        for r in range(0, keys.shape[1], most):
            at = np.bitwise_count(keys[:, r : r + most] ^ ctx)
            at += shift[a : a + n]
            at = at.astype(np.intp)
            width = at.shape[1]
            denominators = numerators.take(at, mode="clip").sum(2) + own[:, r : r + width]
            quotients = scaled // denominators.astype(np.uint64)[:, :, None]
            at += lines[:, :width] if width == most else (np.arange(SIGNS * width) * len(numerators)).reshape(SIGNS, width, 1)
            total = quotients.view(np.int64).ravel().take(at, mode="clip").sum(0)
            out[r : r + width, low : low + len(cuts)] += np.add.reduceat(total, cuts, axis=1) * n
    return out


def ranked(tokens: list[str], structural: np.ndarray, sizes: np.ndarray, questions: list[list[str]], golds: list[int], most: int) -> tuple[list, list]:
    """Of every question the place of its gold row and the ``most`` best rows (from 1), by score and then order; a row has a token at least."""
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.int64)
    places: list = []
    best: list = []
    step = max(1, CELLS // max(1, 4 * len(sizes)))
    for k in range(0, len(questions), step):
        some, gold = questions[k : k + step], np.asarray(golds[k : k + step]) - 1
        keys, own, which = _question_rows(some)
        scores = row_scores(tokens, structural, starts, keys, own)
        ends = np.cumsum([0] + [len(q) for q in some])
        if len(some[0]) and np.all(np.diff(ends) == len(some[0])):
            mine = scores[which.reshape(len(some), -1)].sum(1)
        else:
            mine = np.stack([scores[which[a:z]].sum(0) for a, z in zip(ends[:-1], ends[1:], strict=True)])
        g = np.take_along_axis(mine, gold[:, None], 1)
        ahead = (mine > g) | ((mine == g) & (np.arange(mine.shape[1]) < gold[:, None]))
        places += (1 + ahead.sum(1)).tolist()
        for row in mine if most else ():
            least = np.partition(row, len(row) - most)[len(row) - most] if len(row) > most else row.min()
            kept = np.flatnonzero(row >= least)
            best.append((kept[np.argsort(-row[kept], kind="stable")][:most] + 1).tolist())
    return places, best or [[]] * len(questions)


def rank_rows(packed: DataFrame, most: int = 0) -> DataFrame:
    """doc_id, query_id, gold_place, best of rows doc_id, tokens, structural, sizes, questions (query_id, tokens, gold_row)."""

    def run(batches):
        for b in batches:
            sizes, words = b.column("sizes"), b.column("tokens")
            for i, doc in enumerate(b.column("doc_id").to_pylist()):
                asked = b.column("questions")[i].as_py()
                if not asked:
                    continue
                flags = b.column("structural")[i].values.to_numpy(zero_copy_only=False).astype(bool)
                places, best = ranked(words[i].as_py(), flags, sizes[i].values.to_numpy(), [q["tokens"] for q in asked], [q["gold_row"] for q in asked], most)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([doc] * len(asked), pa.int64()), pa.array([q["query_id"] for q in asked], pa.string()), pa.array(places, pa.int32()), pa.array(best, pa.list_(pa.int32()))],
                    ["doc_id", "query_id", "gold_place", "best"])

    return packed.select("doc_id", "tokens", "structural", "sizes", "questions").mapInArrow(run, RANKED)


def packs(asked: DataFrame, most: int = PACK) -> DataFrame:
    """doc_id, pack, questions: the questions of a table in arrays of about ``most``."""
    counts = asked.groupBy("doc_id").agg(F.ceil(F.count("*") / most).alias("packs"))
    dealt = asked.select("doc_id", "query_id", "tokens", F.col("gold_row").cast("int").alias("gold_row")).join(counts, "doc_id")
    rows = dealt.groupBy("doc_id", F.pmod(F.xxhash64("query_id"), F.col("packs")).alias("pack"))
    return rows.agg(F.collect_list(F.struct("query_id", "tokens", "gold_row")).alias("questions"))


def meet(tables: DataFrame, packed: DataFrame) -> DataFrame:
    """Tables with their packs of questions; a table goes to ``SHARES`` tasks, however many packs it has."""
    n = 4 * tables.sparkSession.sparkContext.defaultParallelism
    left = tables.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(SHARES - 1)))).repartition(n, "doc_id", "share")
    right = packed.withColumn("share", F.pmod("pack", F.lit(SHARES)).cast("int")).repartition(n, "doc_id", "share")
    return left.join(right, ["doc_id", "share"])
