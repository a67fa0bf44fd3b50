"""Attention of queries over chunks: providers, the key cache and the sum over tokens, layers and heads.

The default provider is a deterministic stand-in for a language model: causal softmax over hashed
sign vectors, in whole numbers.  A weight is ``gain * E[distance] * 10^9 div sum``, so sums do not
depend on order and ties are exact.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterable
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HEADS, LAYERS, GAIN, SINK, UNIT = 4, 3, 4, 16 << 20, 10**9
TABLE = [round(math.exp((32 - 2 * i) / math.sqrt(32)) * 2**20) for i in range(33)]
ALL_LAYERS, ALL_HEADS = (0, 1, 2), (0, 1, 2, 3)
BROADCAST_QUERIES, BROADCAST_BYTES = 200_000, 64 << 20
PACK = 64  # questions of one document that a task handles together
PAIRS = 1  # the layer of tokens after their predecessors, which hardly come back
HELD_CHUNKS = 512  # encoded chunks that a task remembers
FLUSH = 2_000_000  # scores of a batch
CLOSE = 1e-6  # products up to UNIT are off by less than a third of this
_NUMERATORS = np.array([*TABLE, *[GAIN * x for x in TABLE], *[0] * 33], np.int64)  # plain, structural and no tokens, by distance
_FLOATS = _NUMERATORS.astype(np.float64)
_STRUCTURAL = _FLOATS[33:66]
_PAIRED = np.zeros((len(_FLOATS), 256, 2), np.int32)  # by two bytes, the earlier one low
_PAIRED[:, : len(_FLOATS), 0] = _NUMERATORS[None, :]
_PAIRED[:, : len(_FLOATS), 1] = _NUMERATORS[:, None]
_PAIRED = _PAIRED.view(np.uint64).ravel()
KEY_TYPE = "doc_id long, chunk_hash string, keys array<long>"


@lru_cache(maxsize=200_000)
def _signs(view: str) -> bytes:
    return hashlib.md5(view.encode()).digest()


def keys_of(tokens: list[str], starts: Iterable[int] = (0,)) -> np.ndarray:
    """(layers, heads, tokens) sign words: the token, the token after its predecessor, its stem.

    Tokens at ``starts`` have no predecessor, so that keys of several chunks or questions are made at once.
    """
    low = [t.lower() for t in tokens]
    before = ["^", *low[:-1]]
    for s in starts:
        before[s] = "^"
    # Pairs hardly come back, so they would only drive tokens and stems out of the cache.
    pairs = [hashlib.md5(f"{p} {t}".encode()).digest() for p, t in zip(before, low, strict=False)]
    flat = b"".join([*map(_signs, low), *pairs, *[_signs(t[:4]) for t in low]])
    return np.ascontiguousarray(np.frombuffer(flat, ">u4").astype(np.uint32).reshape(LAYERS, len(low), HEADS).transpose(0, 2, 1))


def weights(ctx: np.ndarray, structural: np.ndarray, query: np.ndarray, layers=ALL_LAYERS, heads=ALL_HEADS):
    """Weights (query token, context token) of every layer and head, one pair of those at a time."""
    table = np.array(TABLE, np.int64)
    gain = np.where(structural, GAIN, 1).astype(np.int64)
    m = query.shape[2]
    for layer in layers:
        for head in heads:
            c, q = ctx[layer, head], query[layer, head]
            e = table[np.bitwise_count(q[:, None] ^ c[None, :])] * gain
            own = np.tril(table[np.bitwise_count(q[:, None] ^ q[None, :])]) if m else np.zeros((0, 0), np.int64)
            total = e.sum(1) + own.sum(1) + SINK
            yield layer, head, e * UNIT // total[:, None], own * UNIT // total[:, None], SINK * UNIT // total


class AttentionProvider:
    """Turns (chunks, queries) into doc_id, query_id, chunk_no, n_chunk, s ARRAY<BIGINT>."""

    def encode(self, chunks: DataFrame) -> DataFrame:
        raise NotImplementedError

    def attend(self, chunks: DataFrame, queries: DataFrame, layers=ALL_LAYERS, heads=ALL_HEADS, reuse: bool = True) -> DataFrame:
        raise NotImplementedError


def pair(chunks: DataFrame, queries: DataFrame) -> DataFrame:
    """Chunks with the questions of their document: broadcast under a counted bound of rows and bytes, else shuffled."""
    asked = queries.select("doc_id", "query_id", F.col("tokens").alias("question"))
    return chunks.join(_bounded(asked, F.array_join("question", " ")), "doc_id")


def _bounded(asked: DataFrame, text) -> DataFrame:
    size = asked.agg(F.count("*").alias("rows"), F.coalesce(F.sum(F.octet_length(text)), F.lit(0)).alias("bytes")).first()
    return F.broadcast(asked) if size.rows <= BROADCAST_QUERIES and size.bytes <= BROADCAST_BYTES else asked


def packs(queries: DataFrame, most: int = PACK) -> DataFrame:
    """doc_id, questions: the questions of a document in arrays of about ``most``, so that no document's meet in one row."""
    counts = queries.groupBy("doc_id").agg(F.ceil(F.count("*") / most).alias("packs"))
    dealt = queries.select("doc_id", "query_id", "tokens").join(counts, "doc_id")
    rows = dealt.groupBy("doc_id", F.pmod(F.xxhash64("query_id"), F.col("packs")).alias("pack"))
    return rows.agg(F.array_sort(F.collect_list(F.struct("query_id", "tokens"))).alias("questions")).drop("pack")


def _lists(column) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and flat values of an Arrow list column."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten()
    ends = np.asarray(column.offsets)
    return ends - ends[0], flat


class _Pack:
    """Keys of several questions one after the other, with what each adds to its own denominators."""

    def __init__(self, ids: list[str], questions: list[list[str]]):
        kept = [(i, q) for i, q in zip(ids, questions, strict=True)]
        self.ids = [i for i, _ in kept]
        sizes = [len(q) for _, q in kept]
        self.filled = np.flatnonzero(sizes)
        self.starts = np.concatenate([[0], np.cumsum(sizes)]).astype(int)[:-1][self.filled]
        self.keys = keys_of([t for _, q in kept for t in q], self.starts.tolist()) if len(self.filled) else np.zeros((LAYERS, HEADS, 0), np.uint32)
        keys = np.split(self.keys, self.starts[1:], 2) if len(self.filled) else []
        table = np.array(TABLE, np.int64)
        own = [np.tril(table[np.bitwise_count(k[:, :, :, None] ^ k[:, :, None, :])]).sum(3) for k in keys]
        self.own = np.concatenate(own, 2) if own else np.zeros((LAYERS, HEADS, 0), np.int64)

    def scores(self, ctx: np.ndarray, structural: np.ndarray, layers, heads) -> np.ndarray:
        """(question, context token): weights summed over question tokens, layers and heads.

        A context token that comes back in the chunk is scored once in the layers of tokens and stems.  Numerators are
        looked up for two tokens at once and are exact as floats.  So is the whole part of a product
        with UNIT / total, unless a product of the row is within ``CLOSE`` of a whole number; such rows
        are divided as whole numbers.
        """
        n = ctx.shape[2]
        out = np.zeros((len(self.ids), n), np.int64)
        if not len(self.filled) or not n:
            return out
        kinds = np.where(structural, 33, 0).astype(np.uint8)
        for layer in layers:
            first, back, count = _columns(ctx[layer], kinds) if layer != PAIRS else (np.arange(n), np.arange(n), np.ones(n))
            size = len(first)
            shift = np.full(size + size % 2, 66, np.uint8)
            shift[:size] = kinds[first]
            times = np.zeros(len(shift))
            times[:size] = count
            signs = np.zeros(len(shift), np.uint32)
            shape = (self.keys.shape[2], len(shift))
            apart, at, e, summed = np.empty(shape, np.uint32), np.empty(shape, np.uint8), np.empty(shape), np.zeros(shape)
            found = np.empty(shape, np.int32)
            for head in heads:
                signs[:size] = ctx[layer, head, first]
                np.bitwise_xor(self.keys[layer, head][:, None], signs, out=apart)
                np.bitwise_count(apart, out=at)
                at += shift
                np.take(_PAIRED, at.view(np.uint16), out=found.view(np.uint64), mode="clip")
                e[:] = found
                total = (e @ times).astype(np.int64) + self.own[layer, head] + SINK
                rate = UNIT / total
                # A structural product is GAIN times a plain one: near a whole number if either is.
                near = _STRUCTURAL[:, None] * rate
                near -= np.rint(near)
                close = np.flatnonzero(np.abs(near, out=near).min(0) < GAIN * CLOSE)
                exact = [(r, (_NUMERATORS * UNIT // total[r])[at[r]]) for r in close]
                e *= rate[:, None]
                np.floor(e, out=e)
                for r, quotients in exact:
                    e[r] = quotients
                summed += e
            out[self.filled] += np.add.reduceat(summed, self.starts, 0).astype(np.int64)[:, back]
        return out


def _columns(signs: np.ndarray, kinds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A place of each distinct context token of a layer, the one each token has, and how often each occurs."""
    wide = signs[0].astype(np.uint64) << np.uint64(32) | signs[-1]
    wide ^= kinds
    order = np.argsort(wide)
    ordered = wide[order]
    new = np.concatenate([[True], ordered[1:] != ordered[:-1]])
    starts = np.flatnonzero(new)
    first, count = order[starts], np.diff(np.append(starts, len(wide)))
    back = np.empty(len(wide), np.intp)
    back[order] = np.cumsum(new) - 1
    if (signs[:, first[back]] == signs).all() and (kinds[first[back]] == kinds).all():
        return first, back, count
    return np.arange(len(kinds)), np.arange(len(kinds)), np.ones(len(kinds), np.int64)


class PopcountProvider(AttentionProvider):
    def encode(self, chunks: DataFrame) -> DataFrame:
        """Each distinct chunk of a document once: the key cache, scoped to the document, as a table."""

        def run(batches):
            for b in batches:
                keys = [keys_of(t.as_py()).astype(np.int64).ravel() for t in b.column(2)]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "chunk_hash", "keys"])

        once = chunks.select("doc_id", "chunk_hash", "tokens").dropDuplicates(["doc_id", "chunk_hash"])
        return once.mapInArrow(run, KEY_TYPE)

    def attend(self, chunks, queries, layers=ALL_LAYERS, heads=ALL_HEADS, reuse=True):
        """Chunks are encoded in the task that attends, once for all questions of a pack.

        Keys never cross a shuffle: equal chunks of a document come out of one row, one after the
        other, and the task remembers them by document and hash.  ``reuse=False`` encodes a chunk
        anew for every question.
        """
        names = ["doc_id", "query_id", "chunk_no", "n_chunk"]

        def run(batches):
            chunk_keys: dict = {}
            question_packs: dict = {}
            rows: list = []
            held = 0

            def flush():
                flat = np.concatenate([r[4].ravel() for r in rows])
                ends = np.concatenate([[0], np.cumsum([n for r in rows for n in [r[4].shape[1]] * len(r[1])])]).astype(np.int32)
                plain = [[r[0] for r in rows for _ in r[1]], [q for r in rows for q in r[1]], [r[2] for r in rows for _ in r[1]], [r[3] for r in rows for _ in r[1]]]
                arrays = [pa.array(c, k) for c, k in zip(plain, (pa.int64(), pa.string(), pa.int32(), pa.int32()), strict=True)]
                return pa.RecordBatch.from_arrays([*arrays, pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], [*names, "s"])

            for b in batches:
                ids, numbers, hashes = b.column("doc_id").to_pylist(), b.column("chunk_no").to_pylist(), b.column("chunk_hash").to_pylist()
                ends, words = _lists(b.column("tokens"))
                flags = np.asarray(_lists(b.column("structural"))[1].to_numpy(zero_copy_only=False), bool)
                for i, (doc, no, name) in enumerate(zip(ids, numbers, hashes, strict=True)):
                    asked = b.column("questions")[i].as_py()
                    key = (doc, asked[0]["query_id"])
                    if key not in question_packs:
                        question_packs = {key: _Pack([q["query_id"] for q in asked], [q["tokens"] for q in asked])}
                    pack = question_packs[key]
                    tokens = words.slice(ends[i], ends[i + 1] - ends[i])
                    if not reuse:
                        ctx = [keys_of(tokens.to_pylist()) for _ in pack.ids][-1]
                    elif (doc, name) in chunk_keys:
                        ctx = chunk_keys[doc, name]
                    else:
                        if len(chunk_keys) >= HELD_CHUNKS:
                            chunk_keys.clear()
                        ctx = chunk_keys[doc, name] = keys_of(tokens.to_pylist())
                    s = pack.scores(ctx, flags[ends[i] : ends[i + 1]], layers, heads)
                    rows.append((doc, pack.ids, no, s.shape[1], s))
                    held += s.size
                    if held >= FLUSH:
                        yield flush()
                        rows, held = [], 0
            if rows:
                yield flush()

        slim = chunks.select("doc_id", "chunk_no", "chunk_hash", "structural", "tokens")
        packed = _bounded(packs(queries), F.array_join(F.transform("questions", lambda q: F.array_join(q["tokens"], " ")), " "))
        wanted = slim.join(packed, "doc_id").select("doc_id", "chunk_no", "chunk_hash", "structural", "tokens", "questions")
        return wanted.mapInArrow(run, "doc_id long, query_id string, chunk_no int, n_chunk int, s array<long>")

    def exploded(self, chunks: DataFrame, queries: DataFrame) -> DataFrame:
        """One row for each (query token, layer, head, context token); for small inputs and audits."""

        def run(batches):
            for b in batches:
                for i in range(len(b)):
                    r = {n: b.column(n)[i].as_py() for n in ("doc_id", "query_id", "start_pos", "tokens", "structural", "question")}
                    ctx, q = keys_of(r["tokens"]), keys_of(r["question"])
                    for layer, head, w, own, sink in weights(ctx, np.array(r["structural"], bool), q):
                        k, t = w.shape
                        size = k * t
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(np.full(size, r["doc_id"])), pa.array([r["query_id"]] * size), pa.array(np.full(size, layer, np.int32)), pa.array(np.full(size, head, np.int32)),
                             pa.array(np.repeat(np.arange(k, dtype=np.int32), t)), pa.array(np.tile(np.arange(t, dtype=np.int32) + r["start_pos"], k)), pa.array(w.ravel()), pa.array(np.repeat(own.sum(1) + sink, t))],
                            ["doc_id", "query_id", "layer", "head", "q_pos", "pos", "w", "rest"])

        wanted = pair(chunks, queries).select("doc_id", "query_id", "start_pos", "tokens", "structural", "question")
        return wanted.mapInArrow(run, "doc_id long, query_id string, layer int, head int, q_pos int, pos int, w long, rest long")


class PrecomputedProvider(AttentionProvider):
    """Reads weights (doc_id, query_id, chunk_no, layer, head, q_pos, weights ARRAY) of an outside job."""

    def __init__(self, table: DataFrame):
        self.table = table

    def encode(self, chunks):
        return chunks.select("doc_id", "chunk_hash").distinct()

    def attend(self, chunks, queries, layers=ALL_LAYERS, heads=ALL_HEADS, reuse=True):
        kept = self.table.where(F.col("layer").isin(*layers) & F.col("head").isin(*heads))
        long = kept.select("doc_id", "query_id", "chunk_no", F.posexplode("weights").alias("at", "w"))
        cells = long.groupBy("doc_id", "query_id", "chunk_no", "at").agg(F.sum((F.col("w") * UNIT).cast("long")).alias("v"))
        rows = cells.groupBy("doc_id", "query_id", "chunk_no").agg(F.array_sort(F.collect_list(F.struct("at", "v"))).alias("s"))
        sized = rows.join(chunks.select("doc_id", "chunk_no", "n_chunk"), ["doc_id", "chunk_no"])
        return sized.join(queries.select("doc_id", "query_id"), ["doc_id", "query_id"], "left_semi").select("doc_id", "query_id", "chunk_no", "n_chunk", F.col("s.v").alias("s"))


class LlmProvider(AttentionProvider):
    """Runs a user's model: ``load()`` once a worker gives f(context tokens, question tokens) -> weights."""

    def __init__(self, load: Callable):
        self.load = load

    def encode(self, chunks):
        return chunks.select("doc_id", "chunk_hash").distinct()

    def attend(self, chunks, queries, layers=ALL_LAYERS, heads=ALL_HEADS, reuse=True):
        load = self.load

        def run(batches):
            model = load()
            for b in batches:
                out = [(np.asarray(model(t.as_py(), q.as_py())) * UNIT).astype(np.int64) for t, q in zip(b.column("tokens"), b.column("question"), strict=True)]
                names = ["doc_id", "query_id", "chunk_no", "n_chunk"]
                yield pa.RecordBatch.from_arrays([*[b.column(n) for n in names], pa.array(out, pa.list_(pa.int64()))], [*names, "s"])

        wanted = pair(chunks, queries).select("doc_id", "query_id", "chunk_no", "n_chunk", "tokens", "question")
        return wanted.mapInArrow(run, "doc_id long, query_id string, chunk_no int, n_chunk int, s array<long>")


def cache_ledger(chunks: DataFrame, queries: DataFrame) -> DataFrame:
    """Per document: lookups, misses (distinct chunks) and hits of the key cache."""
    asked = queries.groupBy("doc_id").agg(F.count("*").alias("n_queries"))
    held = chunks.groupBy("doc_id").agg(F.count("*").alias("n_chunks"), F.count_distinct("chunk_hash").alias("misses"))
    both = held.join(asked, "doc_id").withColumn("lookups", F.col("n_chunks") * F.col("n_queries"))
    return both.select("doc_id", "n_chunks", "n_queries", "lookups", "misses", (F.col("lookups") - F.col("misses")).alias("hits"))
