"""From chunk scores to document vectors: scaling, rebuilding, normalising and the contrast.

Divisions are deferred: vectors are whole numbers over the denominators base_len and token counts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.operators.chunking import CHUNK

# Fixed value: a content-free instruction of our own, the same for every document.
FIXED_CONTRAST = "Please read all of the text above and write it down once more"


def scale_by_chunk(scores: DataFrame, scale: str = "chunk") -> DataFrame:
    """s times the chunk's length (over base_len), or the raw s times base_len with ``scale='none'``."""
    factor = F.col("n_chunk") if scale == "chunk" else F.lit(CHUNK)
    return scores.withColumn("s", F.transform("s", lambda x: x * factor))


def reconstruct(scaled: DataFrame) -> DataFrame:
    """doc_id, query_id, v: the chunks' vectors in document order; the widest shuffle of the engine."""
    parts = scaled.groupBy("doc_id", "query_id").agg(F.array_sort(F.collect_list(F.struct("chunk_no", "s"))).alias("p"))
    return parts.select("doc_id", "query_id", F.flatten("p.s").alias("v"))


def hashed_bag(tokens, dims: int = 64):
    """Sparse token counts by hash bucket: map bucket -> count."""
    bucket = F.transform(tokens, lambda t: F.conv(F.substring(F.md5(F.lower(t)), 1, 8), 16, 10).cast("long") % dims)
    return F.map_from_entries(F.transform(F.array_distinct(bucket), lambda b: F.struct(b, F.size(F.filter(bucket, lambda x: x == b)).cast("double"))))


def cosine_of_bags(a, b):
    dot = F.aggregate(F.map_keys(a), F.lit(0.0), lambda s, k: s + a[k] * F.coalesce(F.try_element_at(b, k), F.lit(0.0)))
    norm = lambda m: F.sqrt(F.aggregate(F.map_values(m), F.lit(0.0), lambda s, x: s + x * x))
    return dot / F.greatest(norm(a) * norm(b), F.lit(1e-12))


def farthest(queries: DataFrame, dims: int = 64) -> DataFrame:
    """query_id, contrast_id, similarity: the sibling question of the lowest cosine, ties to the smaller id."""
    bags = queries.select("doc_id", "query_id", hashed_bag(F.col("tokens"), dims).alias("bag"))
    other = bags.select("doc_id", F.col("query_id").alias("contrast_id"), F.col("bag").alias("other"))
    pairs = bags.join(other, "doc_id").where("query_id <> contrast_id")
    scored = pairs.select("doc_id", "query_id", "contrast_id", F.round(cosine_of_bags(F.col("bag"), F.col("other")), 9).alias("similarity"))
    return scored.groupBy("doc_id", "query_id").agg(F.min(F.struct("similarity", "contrast_id")).alias("m")).select("doc_id", "query_id", "m.contrast_id", "m.similarity")


def fixed_queries(queries: DataFrame) -> DataFrame:
    """One content-free query for each document asked about."""
    words = F.array(*[F.lit(w) for w in FIXED_CONTRAST.split()])
    return queries.select("doc_id").distinct().select("doc_id", F.concat(F.lit("fixed@"), F.col("doc_id").cast("string")).alias("query_id"), words.alias("tokens"))


def contrast_pairs(queries: DataFrame, contrast: str = "auto") -> DataFrame:
    """doc_id, query_id, contrast_id, contrast_kind for raw, fixed, farthest or auto (farthest, else fixed)."""
    fixed = F.concat(F.lit("fixed@"), F.col("doc_id").cast("string"))
    base = queries.select("doc_id", "query_id")
    if contrast == "raw":
        return base.select("*", F.lit(None).cast("string").alias("contrast_id"), F.lit("raw").alias("contrast_kind"))
    if contrast == "fixed":
        return base.select("*", fixed.alias("contrast_id"), F.lit("fixed").alias("contrast_kind"))
    far = base.join(farthest(queries).select("doc_id", "query_id", "contrast_id"), ["doc_id", "query_id"], "left")
    kind = F.when(F.col("contrast_id").isNull(), "fixed").otherwise("farthest")
    return far.select("doc_id", "query_id", F.coalesce("contrast_id", fixed).alias("contrast_id"), kind.alias("contrast_kind"))


def differential(vectors: DataFrame, pairs: DataFrame, lengths: DataFrame, query_norm: str = "mean") -> DataFrame:
    """v of each query minus v of its contrast, cross-multiplied by the other's token count; raw stays.

    Token counts are joined to the pairs, which are narrow; a vector moves once as a query's and, if it is one, once as a contrast.
    """
    n = lengths.select("query_id", F.col("n").cast("long").alias("n"))
    sized = pairs.join(n, "query_id").join(n.select(F.col("query_id").alias("contrast_id"), F.col("n").alias("k")), "contrast_id", "left")
    own = vectors.join(sized, ["doc_id", "query_id"])
    wanted = pairs.select("doc_id", F.col("contrast_id").alias("query_id")).distinct()
    other = vectors.join(wanted, ["doc_id", "query_id"], "left_semi").select("doc_id", F.col("query_id").alias("contrast_id"), F.col("v").alias("u"))
    joined = own.join(other, ["doc_id", "contrast_id"], "left")
    a, b = (F.col("k"), F.col("n")) if query_norm == "mean" else (F.lit(1).cast("long"), F.lit(1).cast("long"))
    minus = F.zip_with("v", "u", lambda x, y: x * a - y * b)
    return joined.select("doc_id", "query_id", "contrast_id", "contrast_kind", F.when(F.col("u").isNull(), F.col("v")).otherwise(minus).alias("v"))
