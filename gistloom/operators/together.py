"""All methods on one document at once: a row has the document and its questions, and only counts leave the task.

For question sets with a fixed number of questions a document.  Score vectors, contrasts, rankings
and contexts live as long as their document's turn; nothing of them is shuffled or written.  Results
are those of ``plans.experiments.judged`` over ``contexts`` with trimmed windows.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.operators import attention, retrieval, scoring, selection
from gistloom.operators.chunking import CHUNK

DIMS = {"unigram": 64, "trigram": 256, "tfidf": 1024}
PLACES, BAG = 8, 64  # most chunks of a retrieved context; dimensions of the bags that are contrasted
ASKED = "array<struct<query_id:string,kind:string,tokens:array<string>,golds:array<struct<first_pos:int,last_pos:int>>>>"
BLOCK = 4096  # md5 blocks that are made together
HELD_TERMS = 200_000
STEP = retrieval.LENGTH - retrieval.OVERLAP
_FIXED = scoring.FIXED_CONTRAST.split()


# ---- numbers as Spark makes them --------------------------------------------------------------------

def half_up(x: np.ndarray, places: int) -> np.ndarray:
    """Spark's round() of doubles, as whole numbers of units of the last place."""
    y = np.asarray(x, np.float64) * 10.0**places
    out = np.floor(y + 0.5)
    for at in np.argwhere(np.abs(y - np.floor(y) - 0.5) < 1e-4):
        at = tuple(at)
        out[at] = int(Decimal(repr(float(x[at]))).scaleb(places).to_integral_value(ROUND_HALF_UP))
    return out


_SHIFTS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_SINES = np.array([int(abs(math.sin(i + 1)) * 2**32) for i in range(64)], np.uint32)
_WORDS = [*range(16), *[(5 * i + 1) % 16 for i in range(16)], *[(3 * i + 5) % 16 for i in range(16)], *[7 * i % 16 for i in range(16)]]
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)


def _md5_of_blocks(words: np.ndarray) -> np.ndarray:
    """First four bytes, as a big-endian number, of the md5 of messages of one block: (16, messages) little-endian words."""
    n = words.shape[1]
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        f += a
        f += _SINES[i]
        f += words[_WORDS[i]]
        np.right_shift(f, 32 - _SHIFTS[i], out=t)
        f <<= _SHIFTS[i]
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    a += _START[0]
    return a.byteswap()


def chance(ids: list[str], n: int) -> np.ndarray:
    """(id, position): the whole number of the first seven hex digits of md5('id:position'), for n positions."""
    heads = [f"{i}:".encode() for i in ids]
    no = np.arange(n)
    digits = len(str(max(n - 1, 0)))
    if max(map(len, heads), default=0) + digits > 55:
        return np.array([[int(hashlib.md5(h + str(i).encode()).hexdigest()[:7], 16) for i in range(n)] for h in heads], np.int64).reshape(len(heads), n)
    tails = np.zeros((n, digits + 1), np.uint8)  # the digits and the bit that ends a message
    sizes = np.ones(n, np.int64)
    for k in range(1, digits):
        sizes += no >= 10**k
    for k in range(digits):
        tails[:, k] = np.where(k < sizes, no // 10 ** np.maximum(sizes - 1 - k, 0) % 10 + 48, 0)
    tails[no, sizes] = 128
    text = np.zeros((len(heads), n, 64), np.uint8)
    for row, h in zip(text, heads, strict=True):
        row[:, : len(h)] = np.frombuffer(h, np.uint8)
        row[:, len(h) : len(h) + digits + 1] = tails
        bits = 8 * (len(h) + sizes)
        row[:, 56], row[:, 57] = bits & 255, bits >> 8
    words = text.view("<u4").reshape(-1, 16)
    out = np.empty(len(words), np.int64)
    for at in range(0, len(words), BLOCK):
        out[at : at + BLOCK] = _md5_of_blocks(np.ascontiguousarray(words[at : at + BLOCK].T)) >> 4
    return out.reshape(len(heads), n)


# ---- contexts of windows ----------------------------------------------------------------------------

def highest(v: np.ndarray, size: int) -> np.ndarray:
    """For each row of smoothed scores and each token the best sum of a window of ``size`` over it.

    Taking windows from the best one on, ties by start, and trimming the last takes tokens by this
    value, ties by position: of equal windows the later one only adds tokens behind the earlier.
    """
    rows, n = v.shape
    if v.size and int(np.abs(v).max()) * n >= 2**62:
        v = v.astype(object)
    total = np.concatenate([np.zeros((rows, 1), v.dtype), np.cumsum(v, 1)], 1)
    sums = total[:, size:] - total[:, :-size]
    pad = np.full((rows, size - 1), sums.min() if sums.size else 0, sums.dtype)
    out = np.concatenate([pad, sums, pad], 1)
    reach = 1
    while reach < size:
        step = min(reach, size - reach)
        out = np.maximum(out[:, :-step], out[:, step:])
        reach += step
    return out[:, :n]


def trimmed(v: np.ndarray, budgets, share: str = selection.SHARE) -> Iterator[np.ndarray]:
    """Masks (rows, tokens) of the windows within each budget."""
    n = v.shape[1]
    flat = selection.smooth(v.T).T
    made: dict = {}
    for b in budgets:
        need = selection._up(b, n)
        size = min(need, selection._up(share, n))
        if not n or not need:
            yield np.zeros(v.shape, bool)
            continue
        if size not in made:
            best = highest(flat, size)
            made[size] = best, np.sort(best, 1)
        best, ordered = made[size]
        least = ordered[:, n - need][:, None]
        above = best > least
        even = best == least
        yield above | (even & (np.cumsum(even, 1) <= need - above.sum(1)[:, None]))


def contrasts(ids: list[str], bags: np.ndarray) -> list[int | None]:
    """The question of the lowest cosine, ties to the smaller id; none for an only question."""
    if len(ids) < 2:
        return [None] * len(ids)
    norm = np.sqrt((bags * bags).sum(1))
    alike = half_up(bags @ bags.T / np.maximum(norm[:, None] * norm[None, :], 1e-12), 9)
    by_id = np.argsort(np.array(ids, object), kind="stable")
    rank = np.empty(len(ids), np.int64)
    rank[by_id] = np.arange(len(ids))
    return [int(min((k for k in range(len(ids)) if k != i), key=lambda k: (alike[i, k], rank[k]))) for i in range(len(ids))]


# ---- retrieval --------------------------------------------------------------------------------------

class _Trigrams:
    """Buckets of character trigrams; those of Latin-1 characters are looked up in one table."""

    def __init__(self):
        self.table = np.full(1 << 24, -1, np.int16)
        self.others: dict[int, int] = {}

    @staticmethod
    def _bucket(key: int) -> int:
        text = "".join(chr(key >> s & 0x1FFFFF) for s in (42, 21, 0))
        return hashlib.md5(text.encode()).digest()[3] % DIMS["trigram"]

    def __call__(self, text: str) -> np.ndarray:
        c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        a, b, d = c[:-2], c[1:-1], c[2:]
        key = a << 42 | b << 21 | d
        latin = (a | b | d) < 256
        at = np.where(latin, a << 16 | b << 8 | d, 0)
        out = self.table[at].astype(np.int64)
        fresh = np.flatnonzero(latin & (out < 0))
        if len(fresh):
            for k in np.unique(key[fresh]).tolist():
                self.table[(k >> 42 & 255) << 16 | (k >> 21 & 255) << 8 | k & 255] = self._bucket(k)
            out = self.table[at].astype(np.int64)
        for i in np.flatnonzero(~latin).tolist():
            k = int(key[i])
            if k not in self.others:
                if len(self.others) >= HELD_TERMS:
                    self.others.clear()
                self.others[k] = self._bucket(k)
            out[i] = self.others[k]
        return out


def _bounds(n: int) -> list[tuple[int, int]]:
    return [(s, min(s + retrieval.LENGTH, n)) for s in range(0, max(n - retrieval.OVERLAP - 1, 0) + 1, STEP)]


def _similar(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """(question, chunk) scores in millionths; NaN where either has no feature at all."""
    zq, zc = np.sqrt((q * q).sum(1)), np.sqrt((c * c).sum(1))
    z = zq[:, None] * zc[None, :]
    out = half_up(np.divide(q @ c.T, z, out=np.zeros(z.shape), where=z > 0), 6)
    return np.where(z > 0, out, np.nan)


def _places(scores: np.ndarray) -> np.ndarray:
    """0 for the best chunk of each question, ties by number; chunks without a score come after all."""
    order = np.argsort(np.where(np.isnan(scores), np.inf, -scores), axis=1, kind="stable")
    out = np.empty(scores.shape, np.int64)
    np.put_along_axis(out, order, np.broadcast_to(np.arange(scores.shape[1]), scores.shape), 1)
    return np.where(np.isnan(scores), PLACES, np.minimum(out, PLACES))


class Corpus:
    """What retrieval knows of all chunks: their number, tokens, and chunks with a token of each tf-idf bucket."""

    def __init__(self, n_chunks: int, n_tokens: int, buckets: dict[int, int]):
        self.n, self.average = n_chunks, n_tokens / max(n_chunks, 1)
        self.idf = np.zeros(DIMS["tfidf"])
        for b, k in buckets.items():
            self.idf[b] = float(half_up(np.array([math.log(n_chunks / k) + 1]), 6)[0]) / 1e6


def counted(pages: DataFrame) -> DataFrame:
    """t, df: chunks of ``pages`` (doc_id, text) that have a lower-cased token; the names '\\t...' hold the counts of ``Corpus``."""
    pattern = _token_pattern()

    def run(batches):
        import re

        find = re.compile(pattern).findall
        held: Counter = Counter()

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array(list(held.values()), pa.int64())], ["t", "df"])
            held.clear()
            return out

        for batch in batches:
            for text in batch.column(1):
                low = [t.lower() for t in find(text.as_py() or "")]
                for s, e in _bounds(len(low)) if low else ():
                    terms = set(low[s:e])
                    held.update(terms)
                    held.update({f"\t{int.from_bytes(attention._signs(t)[:4], 'big') % DIMS['tfidf']}" for t in terms})
                    held["\tchunks"] += 1
                    held["\ttokens"] += e - s
                if len(held) >= HELD_TERMS:
                    yield flush()
        yield flush()

    return pages.select("doc_id", "text").mapInArrow(run, "t string, df long").groupBy("t").agg(F.sum("df").alias("df"))


def corpus_of(counts: DataFrame) -> Corpus:
    """At most 1,026 rows come to the driver."""
    rows = {r.t[1:]: r.df for r in counts.where(F.startswith("t", F.lit("\t"))).collect()}
    return Corpus(rows.pop("chunks", 0), rows.pop("tokens", 0), {int(k): v for k, v in rows.items()})


def with_frequencies(pages: DataFrame, counts: DataFrame) -> DataFrame:
    """Pages with ``dfs``: the number of chunks, of all pages, that have each word of their questions."""
    terms = F.array_distinct(F.flatten(F.transform("questions", lambda q: F.transform(q["tokens"], F.lower))))
    asked = pages.select("doc_id", F.explode(terms).alias("t")).join(counts, "t")
    dfs = asked.groupBy("doc_id").agg(F.collect_list(F.struct("t", "df")).alias("dfs"))
    return pages.join(dfs, "doc_id", "left")


def _token_pattern() -> str:
    from gistloom.functions.tokens import WORD

    return WORD


# ---- the operator -----------------------------------------------------------------------------------

class _Page:
    """One document with its questions."""

    def __init__(self, tokens: list[str], structural: np.ndarray, questions: list[dict]):
        self.tokens, self.structural, self.n = tokens, structural, len(tokens)
        self.low = [t.lower() for t in tokens]
        self.ids = [q["query_id"] for q in questions]
        self.asked = [q["tokens"] for q in questions]
        self.keys = attention.keys_of(tokens, range(0, self.n, CHUNK))
        self.bounds = _bounds(self.n) if self.n else []
        flat = [attention._signs(t.lower()) for q in self.asked for t in q]
        self.signs = np.frombuffer(b"".join(flat), ">u4").astype(np.int64)[::4]
        self.owner = np.repeat(np.arange(len(self.asked)), [len(q) for q in self.asked])

    def bags(self, dims: int) -> np.ndarray:
        """(question, bucket): how many tokens of the question fall into each."""
        flat = np.bincount(self.owner * dims + self.signs % dims, minlength=len(self.asked) * dims)
        return flat.reshape(-1, dims).astype(np.float64)

    def vectors(self, questions: list[list[str]]) -> np.ndarray:
        """(question, token), scaled by the length of the chunk; equal questions are scored once."""
        place = {tuple(q): None for q in questions}
        place = {q: i for i, q in enumerate(place)}
        pack = attention._Pack([str(i) for i in place.values()], [list(q) for q in place])
        parts = [np.zeros((len(place), 0), np.int64)]
        for s in range(0, self.n, CHUNK):
            e = min(s + CHUNK, self.n)
            parts.append(pack.scores(self.keys[:, :, s:e], self.structural[s:e], attention.ALL_LAYERS, attention.ALL_HEADS) * (e - s))
        return np.concatenate(parts, 1)[[place[tuple(q)] for q in questions]]

    def scores(self, methods) -> Iterator[tuple[str, np.ndarray]]:
        """Score vectors of the methods that choose windows."""
        if set(methods) & {"raw", "fixed", "auto"}:
            every = self.vectors([*self.asked, _FIXED])
            v, fixed = every[:-1], every[-1]
        for m in methods:
            if m == "raw":
                yield m, v
            elif m == "fixed":
                yield m, np.stack([x * len(_FIXED) - fixed * len(q) for x, q in zip(v, self.asked, strict=True)])
            elif m == "auto":
                far = contrasts(self.ids, self.bags(BAG))
                other = [(fixed, len(_FIXED)) if k is None else (v[k], len(self.asked[k])) for k in far]
                yield m, np.stack([x * k - u * len(q) for x, q, (u, k) in zip(v, self.asked, other, strict=True)])
            elif m == "random":
                yield m, chance(self.ids, self.n)

    def places(self, method: str, corpus: Corpus | None, dfs: dict, trigrams) -> np.ndarray:
        """(question, chunk): places of the chunks in a retrieval method."""
        if method == "rag_bm25":
            return _places(self._bm25(corpus, dfs))
        kind = method.removeprefix("rag_")
        dims = DIMS[kind]
        if kind == "trigram":
            text = " ".join(self.low)
            at = np.concatenate([[0], np.cumsum([len(t) + 1 for t in self.low])])
            found = trigrams(text) if len(text) > 2 else np.zeros(0, np.int64)
            c = np.stack([np.bincount(found[at[s] : max(at[e] - 3, at[s])], minlength=dims) for s, e in self.bounds])
            q = [" ".join(t.lower() for t in q) for q in self.asked]
            q = np.stack([np.bincount(trigrams(t) if len(t) > 2 else np.zeros(0, np.int64), minlength=dims) for t in q])
            return _places(_similar(q.astype(np.float64), c.astype(np.float64)))
        buckets = self.keys[0, 0].astype(np.int64) % dims
        c = np.stack([np.bincount(buckets[s:e], minlength=dims) for s, e in self.bounds]).astype(np.float64)
        q = self.bags(dims)
        return _places(_similar(q * corpus.idf, c * corpus.idf) if kind == "tfidf" else _similar(q, c))

    def _bm25(self, corpus: Corpus, dfs: dict, k1: float = 1.2, b: float = 0.75) -> np.ndarray:
        terms = [list(dict.fromkeys(t.lower() for t in q)) for q in self.asked]
        column = {t: i for i, t in enumerate(dict.fromkeys(t for q in terms for t in q))}
        none = len(column)
        at = np.array([column.get(t, none) for t in self.low], np.int64)
        tf = np.stack([np.bincount(at[s:e], minlength=none + 1)[:none] for s, e in self.bounds]).astype(np.float64)
        df = np.array([dfs.get(t, 0) for t in column], np.float64)
        sizes = np.array([e - s for s, e in self.bounds], np.float64)[:, None]
        idf = np.log(1 + (corpus.n - df + 0.5) / (df + 0.5))
        weight = idf * tf * (k1 + 1) / (tf + k1 * (1 - b + b * sizes / corpus.average))
        out = np.full((len(terms), len(self.bounds)), np.nan)
        for i, q in enumerate(terms):
            at = [column[t] for t in q]
            total = half_up(weight[:, at].sum(1), 6)
            out[i] = np.where((tf[:, at] > 0).any(1), total, np.nan)
        return out


def _kept(page: _Page, methods, budgets, corpus, dfs, trigrams) -> Iterator[tuple[str, int, np.ndarray]]:
    """method, number of the budget, mask (question, token) of its context."""
    windows = dict(page.scores(methods))
    shape = (len(page.ids), page.n)
    if windows:
        for i, masks in enumerate(trimmed(np.concatenate(list(windows.values())), budgets)):
            for m, mask in zip(windows, masks.reshape(len(windows), *shape), strict=True):
                yield m, i, mask
    for m in methods:
        if m in windows:
            continue
        if m == "head":
            for i, b in enumerate(budgets):
                yield m, i, np.broadcast_to(np.arange(page.n) < selection._up(b, page.n), shape)
        else:
            places = page.places(m, corpus, dfs, trigrams)
            of_token = np.full(shape, PLACES, np.int64)
            for k, (s, e) in enumerate(page.bounds):
                np.minimum(of_token[:, s:e], places[:, k, None], out=of_token[:, s:e])
            used = np.stack([(of_token < k).sum(1) for k in range(1, PLACES + 1)], 1)
            for i, b in enumerate(budgets):
                most = np.maximum((used <= selection._up(b, page.n)).sum(1), 1)
                yield m, i, of_token < most[:, None]


def judge(pages: DataFrame, budgets, methods, corpus: Corpus | None = None) -> DataFrame:
    """meth, doc_id, query_id, kind, b, n_tokens, n_used, n_in, n_gold for every question, method and budget.

    ``pages`` has doc_id, tokens, structural and questions, and dfs if a method is ``rag_bm25``;
    ``corpus`` is needed by that and by ``rag_tfidf``.
    """
    known = {"raw", "fixed", "auto", "random", "head", "rag_bm25", *(f"rag_{k}" for k in DIMS)}
    if set(methods) - known:
        raise ValueError(f"unknown methods {sorted(set(methods) - known)}")
    types = (pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
    names = ["meth", "doc_id", "query_id", "kind", "b", "n_tokens", "n_used", "n_in", "n_gold"]

    def run(batches):
        trigrams = _Trigrams() if "rag_trigram" in methods else None
        for batch in batches:
            columns: list[list] = [[] for _ in names]
            for i in range(len(batch)):
                questions = batch.column("questions")[i].as_py()
                if not questions:
                    continue
                flags = batch.column("structural")[i].values
                page = _Page(batch.column("tokens")[i].as_py(), np.asarray(flags.to_numpy(zero_copy_only=False), bool), questions)
                dfs = {x["t"]: x["df"] for x in batch.column("dfs")[i].as_py() or ()} if "rag_bm25" in methods else {}
                weight = np.zeros((len(questions), page.n + 1), np.float64)
                for k, q in enumerate(questions):
                    np.add.at(weight[k], [g["first_pos"] for g in q["golds"]], 1)
                    np.add.at(weight[k], [g["last_pos"] for g in q["golds"]], -1)
                weight = np.cumsum(weight, 1)[:, :-1]
                gold = [sum(g["last_pos"] - g["first_pos"] for g in q["golds"]) for q in questions]
                kinds, doc = [q["kind"] for q in questions], batch.column("doc_id")[i].as_py()
                for m, no, mask in _kept(page, methods, budgets, corpus, dfs, trigrams):
                    rows = len(questions)
                    inside = np.einsum("ij,ij->i", mask, weight).astype(np.int64).tolist()
                    for c, values in zip(columns, ([m] * rows, [doc] * rows, page.ids, kinds, [str(budgets[no])] * rows, [page.n] * rows, mask.sum(1).tolist(), inside, gold), strict=True):
                        c += values
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names)

    given = ["doc_id", "tokens", "structural", "questions", *(["dfs"] if "rag_bm25" in methods else [])]
    out = pages.select(*given).mapInArrow(run, "meth string, doc_id long, query_id string, kind string, b string, n_tokens int, n_used long, n_in long, n_gold long")
    return out.withColumn("b", F.col("b").cast("decimal(9,6)"))


def ask(docs: DataFrame, questions: Callable[[int, str], list[dict]], least_chars: int = 0) -> DataFrame:
    """doc_id, text, questions of the documents for which ``questions`` finds some; shorter texts are not read in Python."""
    def run(batches):
        for batch in batches:
            docs, texts = batch.column(0).to_pylist(), batch.column(1)
            found = [questions(d, t.as_py()) for d, t in zip(docs, texts, strict=True)]
            at = [i for i, q in enumerate(found) if q]
            asked = pa.array([found[i] for i in at], _ASKED_TYPE)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at, pa.int64())), texts.take(pa.array(at, pa.int64())), asked], ["doc_id", "text", "questions"])

    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.char_length("text") >= least_chars)
    return kept.mapInArrow(run, f"doc_id long, text string, questions {ASKED}")


_SPAN = pa.list_(pa.struct([("first_pos", pa.int32()), ("last_pos", pa.int32())]))
_ASKED_TYPE = pa.list_(pa.struct([("query_id", pa.string()), ("kind", pa.string()), ("tokens", pa.list_(pa.string())), ("golds", _SPAN)]))
