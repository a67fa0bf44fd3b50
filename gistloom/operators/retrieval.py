"""Baselines: chunk retrieval inside a document, positional heatmaps and trivial selections."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gistloom.functions.tokens import char_grams
from gistloom.operators.selection import SPANS, budget_tokens, merge_spans, used_tokens

LENGTH, OVERLAP = 128, 32


def chunk_overlap(tokenized: DataFrame, length: int = LENGTH, overlap: int = OVERLAP) -> DataFrame:
    """doc_id, n_tokens, chunk_no, first_pos, last_pos, tokens of overlapping chunks."""
    step = length - overlap
    starts = F.sequence(F.lit(0), F.greatest(F.col("n_tokens") - overlap - 1, F.lit(0)), F.lit(step))
    rows = tokenized.where("n_tokens > 0").select("doc_id", "n_tokens", "tokens", F.posexplode(starts).alias("chunk_no", "first_pos"))
    return rows.select("doc_id", "n_tokens", "chunk_no", "first_pos", F.least(F.col("first_pos") + length, F.col("n_tokens")).alias("last_pos"), F.slice("tokens", F.col("first_pos") + 1, F.lit(length)).alias("tokens"))


def features_of(rows: DataFrame, key: list[str], kind: str) -> DataFrame:
    """key, bucket, w: sparse hashed vectors; words (64), character trigrams (256) or words (1024)."""
    dims = {"unigram": 64, "trigram": 256, "tfidf": 1024}[kind]
    if kind == "trigram":
        items = char_grams(F.lower(F.array_join("tokens", " ")))
    else:
        items = F.transform("tokens", lambda t: F.lower(t))
    bucket = F.conv(F.substring(F.md5("item"), 1, 8), 16, 10).cast("long") % dims
    return rows.select(*key, F.explode(items).alias("item")).groupBy(*key, bucket.alias("bucket")).agg(F.count("*").cast("double").alias("w"))


def retrieve(chunks: DataFrame, questions: DataFrame, kind: str = "unigram") -> DataFrame:
    """doc_id, query_id, chunk_no, similarity, place: chunks of the question's document, best first."""
    c, q = features_of(chunks, ["doc_id", "chunk_no"], kind), features_of(questions, ["doc_id", "query_id"], kind)
    if kind == "tfidf":
        n = chunks.count()
        idf = c.groupBy("bucket").agg(F.round(F.log(F.lit(float(n)) / F.count("*")) + 1, 6).alias("idf"))
        c = c.join(idf, "bucket").select("doc_id", "chunk_no", "bucket", (F.col("w") * F.col("idf")).alias("w"))
        q = q.join(idf, "bucket").select("doc_id", "query_id", "bucket", (F.col("w") * F.col("idf")).alias("w"))
    length = lambda df, *k: df.groupBy(*k).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("z"))
    dots = c.join(q.withColumnRenamed("w", "u"), ["doc_id", "bucket"]).groupBy("doc_id", "query_id", "chunk_no").agg(F.sum(F.col("w") * F.col("u")).alias("dot"))
    both = length(q, "doc_id", "query_id").withColumnRenamed("z", "zq").join(length(c, "doc_id", "chunk_no"), "doc_id")
    scored = both.join(dots, ["doc_id", "query_id", "chunk_no"], "left").select("doc_id", "query_id", "chunk_no", F.round(F.coalesce("dot", F.lit(0.0)) / (F.col("zq") * F.col("z")), 6).alias("similarity"))
    return _placed(scored, "similarity")


def _placed(scored: DataFrame, by: str) -> DataFrame:
    return scored.withColumn("place", F.row_number().over(Window.partitionBy("doc_id", "query_id").orderBy(F.desc(by), "chunk_no")))


def bm25(chunks: DataFrame, questions: DataFrame, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    words = chunks.select("doc_id", "chunk_no", F.size("tokens").alias("n"), F.explode("tokens").alias("t")).groupBy("doc_id", "chunk_no", "n", F.lower("t").alias("t")).agg(F.count("*").alias("tf"))
    total = chunks.agg(F.count("*").alias("n_chunks"), F.avg(F.size("tokens")).alias("avg_n"))
    df = words.groupBy("t").agg(F.count("*").alias("df"))
    asked = questions.select("doc_id", "query_id", F.explode(F.array_distinct(F.transform("tokens", lambda x: F.lower(x)))).alias("t"))
    hit = asked.join(words, ["doc_id", "t"]).join(df, "t").crossJoin(F.broadcast(total))
    idf = F.log(1 + (F.col("n_chunks") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    weight = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("n") / F.col("avg_n")))
    return _placed(hit.groupBy("doc_id", "query_id", "chunk_no").agg(F.round(F.sum(weight), 6).alias("score")), "score")


def maxsim(chunks: DataFrame, questions: DataFrame) -> DataFrame:
    """Late interaction: for every question token its nearest sign word in the chunk (first of the four), summed."""
    word = lambda t: F.conv(F.substring(F.md5(F.lower(t)), 1, 8), 16, 10).cast("long")
    c = chunks.select("doc_id", "chunk_no", F.array_distinct(F.transform("tokens", word)).alias("c"))
    q = questions.select("doc_id", "query_id", F.transform("tokens", word).alias("q"))
    best = F.aggregate("q", F.lit(0).cast("long"), lambda s, x: s + 32 - 2 * F.array_min(F.transform("c", lambda y: F.bit_count(x.bitwiseXOR(y)))))
    return _placed(q.join(c, "doc_id").select("doc_id", "query_id", "chunk_no", best.alias("score")), "score")


def stitch(hits: DataFrame, chunks: DataFrame) -> DataFrame:
    """doc_id, query_id, n_tokens, spans: hits in document order, overlaps taken once."""
    placed = hits.join(chunks.select("doc_id", "chunk_no", "n_tokens", "first_pos", "last_pos"), ["doc_id", "chunk_no"])
    keys = [c for c in hits.columns if c not in ("chunk_no", "similarity", "score", "place", "total")]
    got = placed.groupBy(*keys, "n_tokens").agg(F.collect_list(F.struct(F.col("first_pos").cast("int").alias("first_pos"), F.col("last_pos").cast("int").alias("last_pos"))).alias("s"))
    return got.select(*keys, "n_tokens", merge_spans(F.col("s").cast(SPANS)).alias("spans"))


def k_sweep(hits: DataFrame, chunks: DataFrame, ks=range(1, 9)) -> DataFrame:
    grid = F.array(*[F.lit(k) for k in ks])
    out = stitch(hits.select("*", F.explode(grid).alias("k")).where("place <= k"), chunks)
    return out.select("doc_id", "query_id", "k", "n_tokens", used_tokens(F.col("spans")).cast("long").alias("n_used"), "spans")


def align_k(swept: DataFrame, budget: Column) -> DataFrame:
    """Of a k sweep the largest context within the budget, else one chunk."""
    fits = F.col("n_used") <= budget_tokens(F.col("n_tokens"), budget)
    best = F.max(F.when(fits | (F.col("k") == 1), F.struct("k", "n_used", "spans"))).alias("m")
    return swept.groupBy("doc_id", "query_id", "n_tokens").agg(best).select("doc_id", "query_id", "n_tokens", "m.k", "m.n_used", "m.spans")


def fixed_region(tokenized: DataFrame, questions: DataFrame, budget, where: str = "head") -> DataFrame:
    """The first, the last, or half of each of the budgeted tokens."""
    b = F.lit(str(budget)).cast("decimal(9,6)")
    rows = questions.select("doc_id", "query_id").join(tokenized.select("doc_id", "n_tokens"), "doc_id").withColumn("b", b).withColumn("k", budget_tokens(F.col("n_tokens"), b))
    span = lambda a, z: F.struct(a.cast("int").alias("first_pos"), z.cast("int").alias("last_pos"))
    n, k, zero = F.col("n_tokens"), F.col("k"), F.lit(0)
    half = F.ceil(k / 2)
    shape = {"head": [span(zero, k)], "tail": [span(n - k, n)], "both": [span(zero, half), span(n - (k - half), n)]}[where]
    return rows.select("doc_id", "query_id", "b", "n_tokens", merge_spans(F.filter(F.array(*shape), lambda s: s["last_pos"] > s["first_pos"])).alias("spans"))


def random_scores(tokenized: DataFrame, questions: DataFrame) -> DataFrame:
    """Score vectors by md5: the floor that any method should beat."""
    rows = questions.select("doc_id", "query_id").join(tokenized.select("doc_id", "n_tokens"), "doc_id")
    value = F.transform(F.sequence(F.lit(0), F.col("n_tokens") - 1), lambda i: F.conv(F.substring(F.md5(F.concat_ws(":", F.col("query_id"), i.cast("string"))), 1, 7), 16, 10).cast("long"))
    return rows.select("doc_id", "query_id", value.alias("v"))


def fit_heatmap(gold: DataFrame, tokenized: DataFrame, bins: int = 20) -> DataFrame:
    """kind, bin, mass: where known answers lie, from the questions of even documents."""
    rows = gold.where("doc_id % 2 = 0").join(tokenized.select("doc_id", "n_tokens"), "doc_id")
    cell = rows.select("kind", "n_tokens", F.explode(F.sequence("first_pos", F.col("last_pos") - 1)).alias("pos")).select("kind", F.floor(F.col("pos") * bins / F.col("n_tokens")).cast("int").alias("bin"))
    return cell.groupBy("kind", "bin").agg(F.count("*").alias("mass"))


def apply_heatmap(heatmap: DataFrame, gold: DataFrame, tokenized: DataFrame, bins: int = 20) -> DataFrame:
    """Score vectors of the questions of odd documents from the heatmap of their kind."""
    book = heatmap.groupBy("kind").agg(F.map_from_entries(F.collect_list(F.struct("bin", "mass"))).alias("book"))
    rows = gold.where("doc_id % 2 = 1").join(tokenized.select("doc_id", "n_tokens"), "doc_id").join(book, "kind")
    v = F.transform(F.sequence(F.lit(0), F.col("n_tokens") - 1), lambda i: F.coalesce(F.try_element_at("book", F.floor(i * bins / F.col("n_tokens")).cast("int")), F.lit(0).cast("long")))
    return rows.select("doc_id", "query_id", v.alias("v"))
