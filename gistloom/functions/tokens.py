"""Tokenisers and small text expressions; all are built-in functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"[^ \t\n\r\f]+"
WORDPUNCT = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"


def char_grams(text: Column, n: int = 3) -> Column:
    """Character n-grams; the text is cut into characters once, so time is linear."""
    empty = F.array().cast("array<string>")
    grams = lambda c: F.when(F.size(c) < n, empty).otherwise(F.transform(F.sequence(F.lit(1), F.size(c) - (n - 1)), lambda i: F.array_join(F.slice(c, i, F.lit(n)), "")))
    return F.transform(F.array(F.regexp_extract_all(text, F.lit("(?s)."), F.lit(0))), grams)[0]


def words(text: Column, kind: str = "ws", size: int = 4) -> Column:
    """Tokens: whitespace words, words and signs, word pieces of ``size`` characters, or 3-grams."""
    text = F.coalesce(text, F.lit(""))
    if kind == "ws":
        return F.regexp_extract_all(text, F.lit(WORD), F.lit(0))
    if kind == "wordpunct":
        return F.regexp_extract_all(text, F.lit(WORDPUNCT), F.lit(0))
    if kind == "piece":
        cut = lambda t: F.transform(F.sequence(F.lit(0), F.ceil(F.char_length(t) / size).cast("int") - 1), lambda i: F.substr(t, i * size + 1, F.lit(size)))
        return F.flatten(F.transform(words(text), cut))
    if kind == "trigram":
        return char_grams(text)
    raise ValueError(f"unknown tokeniser {kind!r}")


def structural(token: Column, first: Column) -> Column:
    return first | ~token.rlike(r"[\p{L}\p{N}]") | token.rlike(r"[|<>]")


def tokenize(docs: DataFrame, text: str = "text", kind: str = "ws", more: list[str] | tuple = ()) -> DataFrame:
    """doc_id, n_tokens, tokens; for words also whether each is structural, and the columns ``more``."""
    if kind != "ws":
        return docs.select("doc_id", words(F.col(text), kind).alias("tokens")).select("doc_id", F.size("tokens").alias("n_tokens"), "tokens")
    by_line = F.transform(F.split(F.coalesce(F.col(text), F.lit("")), "\n"), lambda x: F.transform(words(x), lambda t, i: F.struct(t.alias("t"), structural(t, i == 0).alias("s"))))
    flat = docs.select("doc_id", F.flatten(by_line).alias("p"), *more)
    return flat.select("doc_id", F.size("p").alias("n_tokens"), F.col("p.t").alias("tokens"), F.col("p.s").alias("structural"), *more)
