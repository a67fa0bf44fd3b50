"""Contiguous chunks of token sequences; the last one may be short."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHUNK = 256


def chunk(tokenized: DataFrame, base_len: int = CHUNK) -> DataFrame:
    """doc_id, chunk_no, start_pos, n_chunk, chunk_hash, tokens, structural; one row a chunk, no shuffle."""
    starts = F.when(F.col("n_tokens") > 0, F.sequence(F.lit(0), F.col("n_tokens") - 1, F.lit(base_len))).otherwise(F.array().cast("array<int>"))
    cut = lambda c: F.slice(c, F.col("start_pos") + 1, F.lit(base_len))
    rows = tokenized.select("*", F.posexplode(starts).alias("chunk_no", "start_pos"))
    return rows.select("doc_id", "chunk_no", "start_pos", cut("tokens").alias("tokens"), cut("structural").alias("structural")).select(
        "doc_id", "chunk_no", "start_pos", F.size("tokens").alias("n_chunk"), F.md5(F.array_join("tokens", " ")).alias("chunk_hash"), "tokens", "structural"
    )


def layout(context: str = "tokens", question: str = "question", cue: str = "Answer:"):
    """Prompt of a chunk: context first, then the question and the answer cue."""
    return F.concat_ws("\n", F.array_join(context, " "), F.lit("Question:"), F.array_join(question, " "), F.lit(cue))
