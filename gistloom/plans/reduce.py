"""The reducer as one plan, and the choices around it: contrast, budget sweep, sharing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.operators import attention, chunking, scoring, selection
from gistloom.plans import workloads
from gistloom.staging import materialize


def all_queries(questions: DataFrame) -> DataFrame:
    """The questions and each document's content-free one: every score vector is computed once."""
    return questions.select("doc_id", "query_id", "tokens").unionByName(scoring.fixed_queries(questions))


def vectors(tokenized: DataFrame, questions: DataFrame, base_len: int = chunking.CHUNK, provider=None, scale: str = "chunk", layers=attention.ALL_LAYERS, heads=attention.ALL_HEADS, reuse: bool = True, fixed: bool = True) -> DataFrame:
    """doc_id, query_id, v over the denominator base_len, for questions and the fixed contrast."""
    provider = provider or attention.PopcountProvider()
    asked = all_queries(questions) if fixed else questions.select("doc_id", "query_id", "tokens")
    raw = provider.attend(chunking.chunk(tokenized, base_len), asked, layers, heads, reuse)
    return scoring.reconstruct(scoring.scale_by_chunk(raw, scale))


def contrasted(scores: DataFrame, questions: DataFrame, contrast: str = "auto", query_norm: str = "mean") -> DataFrame:
    """Score vectors of the questions after the contrast; ``raw`` skips the join altogether."""
    if contrast == "raw":
        kept = scores.join(questions.select("query_id"), "query_id", "left_semi")
        return kept.select("doc_id", "query_id", F.lit(None).cast("string").alias("contrast_id"), F.lit("raw").alias("contrast_kind"), "v")
    lengths = all_queries(questions).select("query_id", F.size("tokens").alias("n"))
    return scoring.differential(scores, scoring.contrast_pairs(questions, contrast), lengths, query_norm)


def reduce(docs: DataFrame, questions: DataFrame, budget="0.1", contrast: str = "auto", overflow: str = "skip", base_len: int = chunking.CHUNK, provider=None, share: str = selection.SHARE) -> DataFrame:
    """doc_id, query_id, b, n_tokens, used, prompt: the shortened context of every question.

    Questions and score vectors are written once: the contrast reads a vector twice, attention runs once.
    """
    asked = materialize(questions.select("doc_id", "query_id", "tokens"), "questions")
    tokenized = workloads.asked_documents(docs, asked)
    scores = materialize(vectors(tokenized, asked, base_len, provider, fixed=contrast != "raw"), "scores")
    spans = selection.select_windows(contrasted(scores, asked, contrast), (budget,), overflow, share)
    return selection.assemble(tokenized, spans)


BUDGETS = ("0.005", "0.02", "0.05", "0.1", "0.15", "0.2", "0.4", "1")


def sweep(scores: DataFrame, budgets=BUDGETS, overflow: str = "skip") -> DataFrame:
    """Spans of every budget from one score table."""
    return selection.select_windows(scores, budgets, overflow)
