"""Cost and accuracy measures over spans, prompts, answers and verdicts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def inside(spans: Column, first: Column, last: Column) -> Column:
    """Tokens of the spans that lie in [first, last)."""
    return F.aggregate(spans, F.lit(0), lambda s, x: s + F.greatest(F.lit(0), F.least(x["last_pos"], last) - F.greatest(x["first_pos"], first)))


def evidence(spans: DataFrame, gold: DataFrame) -> DataFrame:
    """recall and precision of the gold tokens for every selection; stand-in for answer accuracy."""
    joined = spans.join(gold.select("query_id", "first_pos", "last_pos"), "query_id")
    hit = inside(F.col("spans"), F.col("first_pos"), F.col("last_pos"))
    used = F.aggregate("spans", F.lit(0), lambda s, x: s + x["last_pos"] - x["first_pos"])
    return joined.select(*[c for c in spans.columns if c != "spans"], used.cast("long").alias("n_used"), hit.cast("long").alias("n_in"), (F.col("last_pos") - F.col("first_pos")).cast("long").alias("n_gold"))


def recall(found: DataFrame, *by: str) -> DataFrame:
    return found.groupBy(*by).agg(F.count("*").alias("n_queries"), F.round(F.avg(F.col("n_in") / F.col("n_gold")), 6).alias("recall"), F.round(F.avg(F.col("n_in") / F.col("n_used")), 6).alias("precision"))


def token_usage(found: DataFrame, *by: str) -> DataFrame:
    """Average tokens, share of the documents and the reduction against sending them whole."""
    return found.groupBy(*by).agg(F.round(F.avg("n_used"), 6).alias("avg_tokens"), F.round(F.sum("n_used") / F.sum("n_tokens"), 6).alias("share"), F.round(1 - F.sum("n_used") / F.sum("n_tokens"), 6).alias("reduction"))


def budget_adherence(found: DataFrame, *by: str) -> DataFrame:
    over = F.col("n_used") - F.ceil(F.col("b") * F.col("n_tokens"))
    return found.groupBy(*by).agg(F.min(over).alias("min_over"), F.max(over).alias("max_over"), F.round(F.avg(over), 6).alias("avg_over"))


def span_stats(spans: DataFrame, *by: str) -> DataFrame:
    total = F.aggregate("spans", F.lit(0), lambda s, x: s + x["last_pos"] - x["first_pos"])
    return spans.groupBy(*by).agg(F.round(F.avg(F.size("spans")), 6).alias("avg_spans"), F.round(F.sum(total) / F.sum(F.size("spans")), 6).alias("avg_length"))


def correct_share(found: DataFrame, *by: str, least: float = 0.5) -> DataFrame:
    """A question counts as answered when at least ``least`` of its gold tokens are in the context."""
    ok = F.col("n_in") >= least * F.col("n_gold")
    return found.groupBy(*by).agg(F.count("*").alias("n_queries"), F.round(F.avg(ok.cast("int")), 6).alias("accuracy"))


def survival_curve(values: DataFrame, value: str, *by: str) -> DataFrame:
    """Share of questions whose similarity exceeds x, for x = 0, 0.05, ..., 1."""
    grid = F.explode(F.transform(F.sequence(F.lit(0), F.lit(20)), lambda i: (i * 5).cast("int"))).alias("x")
    return values.select(*by, F.col(value).alias("_v"), grid).groupBy(*by, "x").agg(F.round(F.avg((F.col("_v") * 100 > F.col("x")).cast("int")), 6).alias("share"))


def dominance(curve: DataFrame, method: str, *by: str) -> DataFrame:
    """For ordered pairs of methods: share of thresholds at which the first is not below the second."""
    a = curve.select(*by, "x", F.col(method).alias("upper"), F.col("share").alias("s1"))
    b = curve.select(*by, "x", F.col(method).alias("lower"), F.col("share").alias("s2"))
    return a.join(b, [*by, "x"]).where("upper <> lower").groupBy(*by, "upper", "lower").agg(F.round(F.avg((F.col("s1") >= F.col("s2")).cast("int")), 6).alias("not_below"))


def marginal_gain(curve: DataFrame, value: str, *by: str) -> DataFrame:
    order = Window.partitionBy(*by).orderBy("b")
    return curve.withColumn("gain", F.round(F.col(value) - F.lag(value).over(order), 6))


def rank_methods(accuracy: DataFrame, *by: str) -> DataFrame:
    return accuracy.withColumn("place", F.rank().over(Window.partitionBy(*by).orderBy(F.desc("accuracy"))))


def rouge(answer: Column, gold: Column, n: int = 1) -> Column:
    """F1 of the n-gram bags of two token arrays."""
    def grams(t):
        return F.when(F.size(t) < n, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(t) - (n - 1), F.lit(1))), lambda i: F.lower(F.array_join(F.slice(t, i, F.lit(n)), " "))))

    a, g = grams(answer), grams(gold)
    count = lambda xs, x: F.size(F.filter(xs, lambda y: y == x))
    common = F.aggregate(F.array_intersect(a, g), F.lit(0), lambda s, x: s + F.least(count(a, x), count(g, x)))
    return F.when(F.size(a) + F.size(g) == 0, F.lit(0.0)).otherwise(2.0 * common / (F.size(a) + F.size(g)))
