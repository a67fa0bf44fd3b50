"""Answers from shortened contexts, and judges of them; deterministic, and all built-in functions but for outside models.

The stand-in for an answer model reads on: it finds the question's last words in the context and
answers with what follows.  It can only be right when the evidence has been kept.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StringType, StructField, StructType

from gistloom.operators.measures import rouge

LENGTH = 16  # tokens of an answer
CUES = (3, 2, 1)  # last tokens of the question that are looked up, longest first
EMPTY = "array<string>"


def context_tokens(tokens: Column, spans: Column) -> Column:
    return F.flatten(F.transform(spans, lambda x: F.slice(tokens, x["first_pos"] + 1, x["last_pos"] - x["first_pos"])))


def extractive(context: Column, question: Column, length: int = LENGTH) -> Column:
    """Tokens after the first place of the question's last three tokens; of two or one where these do not occur."""
    def runs_of(k: int) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.size(context) - (k - 1), F.lit(1)))
        return F.when(F.size(context) >= k, F.transform(starts, lambda i: F.slice(context, i, F.lit(k)))).otherwise(F.array().cast("array<array<string>>"))

    out = F.array().cast(EMPTY)
    for k in reversed(CUES):
        runs = runs_of(k)
        cue = F.slice(question, F.greatest(F.size(question) - (k - 1), F.lit(1)), F.lit(k))
        at = F.when(F.size(question) >= k, F.array_position(runs, cue)).otherwise(F.lit(0))
        out = F.when(at > 0, F.slice(context, F.greatest(at, F.lit(1)).cast("int") + k, F.lit(length))).otherwise(out)
    return out


class Outside:
    """A user's answer model: ``load()`` once a worker gives f(context tokens, question tokens) -> answer tokens."""

    def __init__(self, load: Callable):
        self.load = load


def generate(prompts: DataFrame, answerer=extractive) -> DataFrame:
    """``prompts`` (with context and question, arrays of tokens) and the answer's tokens.

    ``answerer`` makes a column out of the two columns, or is an ``Outside`` model.
    """
    if not isinstance(answerer, Outside):
        return prompts.withColumn("answer", answerer(F.col("context"), F.col("question")))
    load = answerer.load

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = load()
        for f in frames:
            yield f.assign(answer=[list(model(list(c), list(q))) for c, q in zip(f["context"], f["question"], strict=True)])

    schema = StructType([*prompts.schema.fields, StructField("answer", ArrayType(StringType()))])
    return prompts.mapInPandas(run, schema)


def open_judge(answer: Column, gold: Column, least: float = 0.5) -> Column:
    """Lenient: the reference is part of the answer, or the F1 of their words reaches ``least``; empty references never fit."""
    told = lambda t: F.concat(F.lit(" "), F.lower(F.array_join(t, " ")), F.lit(" "))
    return (F.size(gold) > 0) & (F.contains(told(answer), told(gold)) | (rouge(answer, gold, 1) >= least))


def overlap(context: Column, option: Column) -> Column:
    """Distinct words of an option that the context has."""
    low = lambda t: F.transform(t, F.lower)
    return F.size(F.array_intersect(low(context), low(option)))


def cosine(answer: Column, gold: Column) -> Column:
    """Cosine of the word counts, 0 for an empty side; whole numbers up to the last division."""
    a, g = F.transform(answer, F.lower), F.transform(gold, F.lower)
    count = lambda xs, x: F.size(F.filter(xs, lambda y: y == x)).cast("long")
    dot = lambda x, y: F.aggregate(F.array_distinct(x), F.lit(0).cast("long"), lambda s, t: s + count(x, t) * count(y, t))
    return F.when((F.size(a) == 0) | (F.size(g) == 0), F.lit(0.0)).otherwise(F.round(dot(a, g) / F.sqrt((dot(a, a) * dot(g, g)).cast("double")), 6))


def rouge_l(answer: Column, gold: Column) -> Column:
    """F1 of the longest common subsequence of words.

    One row of the table of lengths is folded over the answer; as rows never fall, the new one is the
    running maximum of what a match or the old row gives.
    """
    zero = F.transform(gold, lambda _: F.lit(0))

    def step(row: Column, word: Column) -> Column:
        cells = F.transform(gold, lambda g, j: F.when(F.lower(g) == F.lower(word), F.when(j > 0, F.get(row, j - 1)).otherwise(F.lit(0)) + 1).otherwise(F.get(row, j)))
        return F.transform(F.array(cells), lambda c: F.transform(c, lambda _, j: F.array_max(F.slice(c, 1, j + 1))))[0]

    longest = F.coalesce(F.array_max(F.aggregate(answer, zero, step)), F.lit(0))
    total = F.size(answer) + F.size(gold)
    return F.when(total == 0, F.lit(0.0)).otherwise(F.round(2.0 * longest / total, 6))
