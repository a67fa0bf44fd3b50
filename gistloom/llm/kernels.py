"""Vectorised numpy kernels over UTF-8 buffers of Arrow string columns.

A batch is cut into pieces of a few MB by whole rows, so memory follows the piece and the longest
text, never the batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
PIECE = 2_000_000
GOLDEN = U(0x9E3779B97F4A7C15)


def mix(h: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit words."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h = h ^ (h >> U(27))
    h = h * U(0x94D049BB133111EB)
    return h ^ (h >> U(31))


def pieces(column: pa.Array, size: int = PIECE) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets of the rows in bytes); nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("").cast(pa.large_string())
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    row = 0
    while row < len(column):
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + size, "right")) - 1)
        end = min(end, len(column))
        yield row, end, raw[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends) of words in bytes, and for each row the index of its first word (one more at the end)."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    solid = ~SPACE[data]
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    before = np.empty(len(data), bool)
    before[0] = True
    before[1:] = ~solid[:-1] | first[1:-1]
    after = np.empty(len(data), bool)
    after[-1] = True
    after[:-1] = ~solid[1:] | first[1:-1]
    starts, ends = np.flatnonzero(solid & before), np.flatnonzero(solid & after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word, eight bytes a step."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(data) + 1,), "<u8", buffer=padded, strides=(1,))
    length = ends - starts
    h = length.astype(U) * GOLDEN
    live, at = np.arange(len(starts)), starts
    done = 0
    while len(live):
        left = length[live] - done
        block = eight[at + done]
        short = left < 8
        if short.any():
            keep = (U(1) << (np.minimum(left, 7).astype(U) * U(8))) - U(1)
            block = np.where(short, block & keep, block)
        h[live] = mix(h[live] ^ block)
        more = left > 8
        live, at = live[more], at[more]
        done += 8
    return h


def shingle_sets(column: pa.Array, width: int) -> Iterator[np.ndarray]:
    """For each row its sorted distinct shingle hashes; fewer words than ``width`` are one shingle."""
    for row, end, data, offsets in pieces(column):
        data = FOLD[data]
        starts, ends, firsts = word_bounds(data, offsets)
        h = word_hashes(data, starts, ends)
        total = len(h)
        s = np.full(total, U(width))
        for k in range(width):
            if total > k:
                s[: total - k] = mix(s[: total - k] * U(3) + h[k:])
        for r in range(end - row):
            a, b = int(firsts[r]), int(firsts[r + 1])
            if b - a >= width:
                yield np.unique(s[a : b - width + 1])
            elif b > a:
                whole = np.array([1000 + b - a], U)
                for x in h[a:b]:
                    whole = mix(whole * U(3) + x)
                yield whole
            else:
                yield np.zeros(0, U)


def overlaps(left: list[np.ndarray], right: list[np.ndarray], step: int = 256) -> Iterator[tuple[int, np.ndarray]]:
    """Blocks of the matrix of intersection sizes: (first row, sizes of rows x right).

    Tokens that many rows hold are counted by a dense product, the others by their few pairs.
    """
    sizes_l, sizes_r = np.array([len(x) for x in left]), np.array([len(x) for x in right])
    token_l, token_r = np.concatenate(left), np.concatenate(right)
    row_l, row_r = np.repeat(np.arange(len(left)), sizes_l), np.repeat(np.arange(len(right)), sizes_r)
    words, back = np.unique(token_r, return_inverse=True)
    at = np.searchsorted(words, token_l)
    at[at == len(words)] = 0
    hit = words[at] == token_l if len(words) else np.zeros(len(token_l), bool)
    at, row_l = at[hit], row_l[hit]
    used = np.bincount(back, minlength=len(words))
    dense = used > 32
    number = np.cumsum(dense) - 1
    wide = int(dense.sum())
    right_dense = np.zeros((len(right), wide), np.float32)
    m = dense[back]
    right_dense[row_r[m], number[back[m]]] = 1
    rest = ~m
    order = np.argsort(back[rest], kind="stable")
    holders, holder_words = row_r[rest][order], back[rest][order]
    begin, stop = np.searchsorted(holder_words, np.arange(len(words))), np.searchsorted(holder_words, np.arange(len(words)), "right")
    for lo in range(0, len(left), step):
        hi = min(lo + step, len(left))
        mine = (row_l >= lo) & (row_l < hi)
        rows, toks = row_l[mine] - lo, at[mine]
        left_dense = np.zeros((hi - lo, wide), np.float32)
        d = dense[toks]
        left_dense[rows[d], number[toks[d]]] = 1
        counts = np.rint(left_dense @ right_dense.T).astype(np.int64)
        rows, toks = rows[~d], toks[~d]
        n = stop[toks] - begin[toks]
        if n.sum():
            where = np.repeat(begin[toks] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            flat = np.repeat(rows, n) * len(right) + holders[where]
            counts += np.bincount(flat, minlength=counts.size).reshape(counts.shape)
        yield lo, counts
