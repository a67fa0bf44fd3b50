"""Toxicity by compression distance.

Two zstandard dictionaries, one trained on ordinary and one on toxic text, compress every window of
a text; the bytes that the toxic dictionary saves over the ordinary one are the evidence.

*Training* takes a bounded sample of labelled documents outside the held-out fold, without near
copies; very long ones are read by windows spread over their length.  Most of a toxic text is
ordinary, so the trainer gets what sets a class apart: words of toxic text whose beginnings are
several times as frequent there, and ordinary text without these words.  The trainer chooses the
content of both dictionaries.  The toxic compressor continues the ordinary dictionary with its own,
so what ordinary text explains cancels out, and only longer or additional matches save bytes.

*Calibration*: dictionaries of each two thirds measure the windows of the remaining third, and a
logistic regression turns how many windows save how many bytes into a probability; the dictionaries
in use are trained on all of the sample.

*Windows* cover whole texts and overlap by a word.  Matches are at least seven bytes long, the most
that the compressor can be asked for.

Defined cases: null, empty and blank texts have no window and get the score of no evidence;
without labels of both classes the score is the prior; repeated rows are scored alike; empty tables
give empty results.  Labels, language, source and id are no inputs of a score.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard as zs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.llm.labelled import fold, hash_key, known_labels, sample

WORDS = re.compile(r"\w+")
FOLDS, HELD = 3, 1
MAX_TOXIC, MAX_ORDINARY, MAX_CHARS = 1200, 2400, 5_000_000
WINDOW, OVERLAP = 120, 20
PARTS = 3  # of the sample, for calibration
SHORTEST, LONGEST = 5, 9  # beginnings of words, with the space before them
TIMES, LEAST = 6.0, 8  # a toxic beginning is so many times as frequent, and in so many documents
ORDINARY_BYTES, TOXIC_BYTES = 400_000, 16_000
WINDOW_LOG, HASH_LOG = 21, 20
SAVED = (1, 2, 3, 4, 6)  # bytes that a window saves


def _flat(text: str) -> str:
    """Lower-case words with one space around each; signs between them say nothing."""
    return " " + " ".join(WORDS.findall(text.lower())) + " "


def spelled(flat: str) -> bytes:
    """Words with capital copies of their outer letters for the spaces: a match that ends a word leaves the next one whole."""
    return "".join([f"{w[0].upper()}{w[0].upper()}{w}{w[-1].upper()}" for w in flat.split()]).encode()


def _distinct(texts: list[str]) -> list[str]:
    """Texts that share no more than a fifth of their 4-word runs with earlier ones."""
    seen: set = set()
    out = []
    for t in texts:
        w = t.split()
        runs = {hash(tuple(w[i : i + 4])) for i in range(max(1, len(w) - 3))}
        if len(runs & seen) <= 0.2 * len(runs):
            out.append(t)
        seen |= runs
    return out


class Contrast:
    """Beginnings of words, and whole words, that are far more frequent in one class of documents."""

    def __init__(self, own: list[str], other: list[str]):
        self.parts: dict[str, list[str]] = {}
        mine, theirs = self._documents(own), self._documents(other)
        scale = TIMES * len(own) / max(1, len(other))
        least = min(LEAST, max(2, len(own) // 8))
        self.typical = {g for g, n in mine.items() if n >= least and n >= scale * (theirs[g] + 0.5)}

    def _parts(self, word: str) -> list[str]:
        if word not in self.parts:
            w = f" {word} "
            self.parts[word] = [w[:k] for k in range(SHORTEST, min(LONGEST, len(w) - 1) + 1)] + [w]
        return self.parts[word]

    def _documents(self, texts: list[str]) -> Counter:
        held: Counter = Counter()
        for t in texts:
            held.update({g for w in set(t.split()) for g in self._parts(w)})
        return held

    def split(self, text: str) -> tuple[str, str]:
        """The text's typical words, and the text without them."""
        words = text.split()
        marks = [any(g in self.typical for g in self._parts(w)) for w in words]
        return tuple(_flat(" ".join(w for w, m in zip(words, marks, strict=True) if m == side)) for side in (True, False))


def _windows(raw: bytes) -> list[bytes]:
    return [raw[k : k + WINDOW + OVERLAP] for k in range(0, max(1, len(raw) - OVERLAP), WINDOW)]


REPEATS = b"\1\0\0\0\4\0\0\0\x08\0\0\0"  # fixed value: what ends the header of a trained dictionary


def _trained(samples: list[bytes], size: int) -> bytes:
    """Content that the trainer chooses; samples too few for it are the content themselves."""
    whole = b"".join(samples)
    if len(whole) < 2 * size and len(samples) < 40:
        return whole[-size:]
    try:
        made = zs.train_dictionary(min(size, max(1024, len(whole) // 2)), samples, k=64, d=6, steps=1).as_bytes()
    except zs.ZstdError:  # too little text
        return whole[-size:]
    return made[made.index(REPEATS) + len(REPEATS) :]


def train_dictionaries(toxic: list[str], ordinary: list[str]) -> tuple[bytes, bytes]:
    """(ordinary, toxic) content of the two dictionaries."""
    contrast = Contrast(toxic, ordinary)
    own = [s for s in (spelled(contrast.split(t)[0]) for t in toxic) if len(s) > 8]
    plain = [w for t in ordinary for w in _windows(spelled(contrast.split(t)[1])) if len(w) > 8]
    return _trained(plain, ORDINARY_BYTES), _trained(own, TOXIC_BYTES)


def _compressor(content: bytes) -> zs.ZstdCompressor:
    shape = {"strategy": zs.STRATEGY_FAST, "min_match": 7, "target_length": 1, "window_log": WINDOW_LOG, "hash_log": HASH_LOG, "chain_log": 10}
    params = zs.ZstdCompressionParameters.from_level(-1, write_content_size=False, write_checksum=False, write_dict_id=False, **shape)
    book = zs.ZstdCompressionDict(content + b"\0" * 8, dict_type=zs.DICT_TYPE_RAWCONTENT)
    book.precompute_compress(compression_params=params)
    return zs.ZstdCompressor(compression_params=params, dict_data=book)


@dataclass
class Model:
    ordinary: bytes
    toxic: bytes
    weights: list[float]  # of the features below, with a constant first
    _books: list = field(default_factory=list, repr=False, compare=False)

    def __getstate__(self):
        return {"ordinary": self.ordinary, "toxic": self.toxic, "weights": self.weights, "_books": []}

    def savings(self, text: str) -> np.ndarray:
        """Bytes that each window saves with the toxic dictionary."""
        if not self._books:
            self._books = [_compressor(self.ordinary), _compressor(self.ordinary + self.toxic)]
        a, b = self._books
        raw = spelled(_flat(text))
        if not raw:
            return np.zeros(0, np.int64)
        return np.array([len(a.compress(w)) - len(b.compress(w)) for w in _windows(raw)])

    def evidence(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), len(SAVED) + 5))
        for i, t in enumerate(texts):
            s = self.savings(t)
            if len(s):
                plus = np.maximum(s, 0).sum()
                counts = [np.log1p((s >= k).sum()) for k in SAVED]
                out[i] = [*counts, min(s.max(), 24) / 4, plus / len(s), np.log1p(plus), np.log(len(s)), np.log1p(plus) / np.sqrt(len(s))]
        return out

    def proba(self, texts: list[str]) -> np.ndarray:
        w = np.array(self.weights)
        return 1 / (1 + np.exp(-(w[0] + self.evidence(texts) @ w[1:])))


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.3, steps: int = 60) -> list[float]:
    x = np.concatenate([np.ones((len(x), 1)), x], 1)
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        hess = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        w = w - np.linalg.solve(hess, x.T @ (p - y) + ridge * w)
    return [float(v) for v in w]


def fit(toxic: list[str], ordinary: list[str]) -> Model:
    """Dictionaries and calibration from flat texts of both classes."""
    x, y = [], []
    parts = min(PARTS, len(toxic), len(ordinary))
    for k in range(parts):
        rest = [[t for i, t in enumerate(texts) if parts == 1 or i % parts != k] for texts in (toxic, ordinary)]
        model = Model(*train_dictionaries(*rest), [])
        for value, texts in ((1.0, toxic), (0.0, ordinary)):
            x.append(model.evidence(texts[k::parts]))
            y += [value] * len(texts[k::parts])
    return Model(*train_dictionaries(toxic, ordinary), _logistic(np.concatenate(x), np.array(y)))


def train(docs: DataFrame, labels: DataFrame, max_toxic: int = MAX_TOXIC, max_ordinary: int = MAX_ORDINARY, max_chars: int = MAX_CHARS) -> Model:
    keep = fold(F.col("doc_id"), FOLDS) != HELD
    rows = []
    for value, most in ((1, max_toxic), (0, max_ordinary)):
        got = sample(docs, labels, "toxic", keep, most, max_chars, value).select("doc_id", "text", "y").collect()
        if not got and known_labels(labels, "toxic", keep, value).limit(1).count():
            raise ValueError(f"labels with toxic = {value} exist, but none of those sampled has a document")
        rows.append([_flat(r.text) for r in sorted(got, key=lambda r: (hash_key(r.doc_id), r.text))])
    toxic, ordinary = (_distinct(r) for r in rows)
    if not toxic or not ordinary:
        share = min(max((len(toxic) + 0.5) / (len(toxic) + len(ordinary) + 1), 0.01), 0.99)
        return Model(b"", b"", [float(np.log(share / (1 - share)))] + [0.0] * (len(SAVED) + 5))
    return fit(toxic, ordinary)


def score(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""

    def run(batches):
        for batch in batches:
            texts = batch.column(1).fill_null("")
            p = np.concatenate([model.proba(texts[i : i + 200].to_pylist()) for i in range(0, len(texts), 200)] or [np.zeros(0)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double, predicted int")
    held = F.coalesce(fold(F.col("doc_id"), FOLDS) == HELD, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", "predicted")


def drop_toxic(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """Documents below the threshold, with their columns as they were."""
    schema = docs.schema

    def run(batches):
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).fill_null("")
            p = np.concatenate([model.proba(texts[i : i + 200].to_pylist()) for i in range(0, len(texts), 200)] or [np.zeros(0)])
            yield batch.filter(pa.array(p < threshold))

    return docs.mapInArrow(run, schema)
