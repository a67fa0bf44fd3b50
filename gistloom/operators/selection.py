"""Choosing spans under an exact token budget.

Scores are smoothed, windows of one length are ranked by (score down, start up), and taken until
the budget is full.  ``skip`` passes over windows that do not fit, ``stop`` ends at the first, and
``trim`` cuts the last one.  One (document, query) row is the unit, so a row is bounded by its text.
Sums that could pass 64 bits are made with whole numbers of any size.
"""

from __future__ import annotations

from decimal import ROUND_CEILING, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SHARE = "0.02"
SPANS = "array<struct<first_pos:int,last_pos:int>>"


def budget_tokens(n: Column, budget: Column) -> Column:
    return F.ceil(budget.cast("decimal(9,6)") * n).cast("int")


def window_len(n: Column, budget: Column, share: str = SHARE) -> Column:
    return F.least(budget_tokens(n, budget), budget_tokens(n, F.lit(share)))


def _up(share, n: int) -> int:
    return int((Decimal(str(share)) * n).to_integral_value(ROUND_CEILING))


def smooth(v: np.ndarray, radius: int = 2, kernel: str = "box") -> np.ndarray:
    """Sums over a neighbourhood, cut at the ends; triangle weighs the middle most."""
    if kernel == "none" or radius == 0:
        return v
    if len(v) and int(np.abs(v).max()) * (radius + 1) * (2 * radius + 1) >= 2**62:
        v = v.astype(object)
    out = np.zeros_like(v)
    for d in range(-radius, radius + 1):
        w = 1 if kernel == "box" else radius + 1 - abs(d)
        lo, hi = max(0, -d), min(len(v), len(v) - d)
        out[lo:hi] += w * v[lo + d : hi + d]
    return out


def window_scores(v: np.ndarray, length: int) -> np.ndarray:
    """Sums of all windows; exact beyond 64 bits, too."""
    if len(v) and int(np.abs(v).max()) * len(v) >= 2**62:
        v = v.astype(object)
    total = np.concatenate([[0], np.cumsum(v)])
    return total[length:] - total[:-length] if length else np.zeros(0, np.int64)


def ranked(v: np.ndarray, length: int, stride: int = 1) -> np.ndarray:
    """Window starts, best score first, ties by start; only every ``stride``-th start."""
    scores = window_scores(v, length)[::stride]
    if scores.dtype == object:
        return np.array(sorted(range(len(scores)), key=lambda s: (-scores[s], s)), np.int64) * stride
    return np.argsort(-scores, kind="stable") * stride


def choose(v: np.ndarray, budget, overflow: str = "skip", share=SHARE, length: int | None = None, stride: int = 1, orders: dict | None = None) -> np.ndarray:
    """Mask of the tokens taken from scores ``v``; ``orders`` keeps rankings for further budgets of the same scores."""
    n = len(v)
    left = _up(budget, n)
    size = length or min(left, _up(share, n))
    taken = bytearray(n)
    if not n or not left:
        return np.frombuffer(taken, np.uint8).astype(bool)
    orders = {} if orders is None else orders
    if size not in orders:
        orders[size] = ranked(v, size, stride).tolist()
    whole = b"\1" * size
    for s in orders[size]:
        fresh = size - taken.count(1, s, s + size)
        if fresh <= left:
            taken[s : s + size] = whole
            left -= fresh
            if not left:
                break
        elif overflow == "stop":
            break
        elif overflow == "trim":
            for at in [k for k in range(s, s + size) if not taken[k]][:left]:
                taken[at] = 1
            break
    return np.frombuffer(taken, np.uint8).astype(bool)


def spans_of(taken: np.ndarray) -> list[tuple[int, int]]:
    """Half-open runs of taken tokens; touching ones are one span."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], taken.astype(np.int8), [0]])))
    return [(int(a), int(b)) for a, b in zip(edge[::2], edge[1::2], strict=True)]


def select_windows(scores: DataFrame, budgets=("0.1",), overflow: str = "skip", share: str = SHARE, radius: int = 2, kernel: str = "box", single: bool = False, isolated: bool = False, stride: int = 1) -> DataFrame:
    """doc_id, query_id, b, n_tokens, spans for every score vector and budget; a vector is read and ranked once."""

    def run(batches):
        for batch in batches:
            ends, values = np.asarray(batch.column("v").offsets), batch.column("v").values.to_numpy(zero_copy_only=False)
            chosen, sizes = [], []
            for i in range(len(batch)):
                raw = values[ends[i] : ends[i + 1]]
                flat = raw if isolated else smooth(raw, radius, kernel)
                orders: dict = {}
                for b in budgets:
                    length = 1 if isolated else (_up(b, len(raw)) if single else None)
                    chosen.append(spans_of(choose(flat, b, overflow, share, length, stride, orders)))
                    sizes.append(len(raw))
            at = np.repeat(np.arange(len(batch)), len(budgets))
            pairs = np.array([x for c in chosen for x in c], np.int32).reshape(-1, 2)
            spans = pa.StructArray.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["first_pos", "last_pos"])
            stops = np.concatenate([[0], np.cumsum([len(c) for c in chosen])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(at)), batch.column("query_id").take(pa.array(at)), pa.array([str(b) for b in budgets] * len(batch), pa.string()),
                 pa.array(sizes, pa.int32()), pa.ListArray.from_arrays(pa.array(stops), spans)],
                ["doc_id", "query_id", "b", "n", "spans"])

    out = scores.select("doc_id", "query_id", "v").mapInArrow(run, f"doc_id long, query_id string, b string, n int, spans {SPANS}")
    return out.select("doc_id", "query_id", F.col("b").cast("decimal(9,6)").alias("b"), F.col("n").alias("n_tokens"), "spans")


def merge_spans(spans: Column) -> Column:
    """Overlapping or touching spans of an array as one, sorted."""
    def step(acc, x):
        last = F.element_at(acc, -1)
        joined = F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(last["first_pos"].alias("first_pos"), F.greatest(last["last_pos"], x["last_pos"]).alias("last_pos"))))
        return F.when((F.size(acc) > 0) & (F.get(acc, F.size(acc) - 1)["last_pos"] >= x["first_pos"]), joined).otherwise(F.concat(acc, F.array(x)))

    return F.aggregate(F.array_sort(spans), F.array().cast(SPANS), step)


def used_tokens(spans: Column) -> Column:
    return F.aggregate(spans, F.lit(0), lambda s, x: s + x["last_pos"] - x["first_pos"])


def assemble(tokenized: DataFrame, spans: DataFrame, separator: str = " [...] ") -> DataFrame:
    """The kept spans in document order as one prompt."""
    joined = spans.join(tokenized.select("doc_id", "tokens"), "doc_id")
    piece = lambda s: F.array_join(F.slice("tokens", s["first_pos"] + 1, s["last_pos"] - s["first_pos"]), " ")
    return joined.select("doc_id", "query_id", "b", "n_tokens", used_tokens(F.col("spans")).alias("used"), F.array_join(F.transform("spans", piece), separator).alias("prompt"))
