"""URL filtering by association rules.

Explicit (host, path) rules label part of the pages.  FP-growth mines token sets that occur with
those labels; sets whose confidence and support pass become association rules, kept in an inverted
index from the rarest token of a rule to the rule.  Pages without an explicit rule are judged by
the strongest association rule they contain, and allowed when none fits.  The labelled pages' tokens
are written once, as mining reads them several times.

Defined cases: a null url or one without ``://`` has empty host and path, no explicit rule and the
verdict of its tokens (allow when it has none); repeated rows are judged alike; empty tables give
empty results.  The number of mined rules is bounded by ``max_rules``: their counts are aggregated
over all labelled pages, and only rules, never pages, reach the driver.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gistloom.llm.shared import LOWER, UPPER, materialize

RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
BLOCK_ITEM, ALLOW_ITEM = "=block", "=allow"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, "://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1), F.lit(""))


def explicit_rule(host: Column, path: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else null; the list is a parameter."""
    ranked = sorted(rules, key=lambda r: (-len(r[0] + r[1]), r))
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for domain, prefix, verdict in reversed(ranked):
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith(prefix)
        found = F.when(fits, F.struct(F.lit(domain + prefix).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def url_tokens(host: Column, path: Column, url: Column) -> Column:
    """Distinct tokens: host labels and their hyphen parts, path parts, keys of the query."""
    labels = F.filter(F.split(host, r"\."), lambda x: x != "")
    parts = F.filter(F.flatten(F.transform(labels, lambda x: F.split(x, "-"))), lambda x: x != "")
    steps = F.filter(F.split(path, "/"), lambda x: (x != "") & ~x.rlike("[0-9]"))
    keys = F.regexp_extract_all(F.coalesce(url, F.lit("")), F.lit("[?&]([A-Za-z_]+)="), F.lit(1))
    name = lambda kind, items: F.transform(items, lambda x: F.concat(F.lit(kind), x))
    return F.array_distinct(F.concat(name("h:", F.concat(labels, parts)), name("p:", steps), name("q:", keys)))


def mine_rules(labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.8, max_items: int = 3, max_rules: int = 10_000) -> list[tuple]:
    """(tokens, verdict, confidence, support) from (items, verdict), strongest first.

    Support is counted over all labelled rows.  Only sets of up to ``max_items`` tokens are rules;
    ``max_rules`` bounds what the driver holds, and passing it raises rather than dropping rules.
    """
    total = labelled.count()
    if not total:
        return []
    label = F.when(F.col("verdict") == "block", BLOCK_ITEM).otherwise(ALLOW_ITEM)
    # a token of nearly one page only cannot reach the support: it is pruned before the mining
    least = max(1, int(min_support * total))
    frequent = labelled.select(F.explode("items").alias("item")).groupBy("item").count().where(F.col("count") >= least).select("item")
    kept = [r[0] for r in frequent.limit(max_rules + 1).collect()]
    if len(kept) > max_rules:
        raise ValueError(f"over {max_rules} frequent URL tokens: raise min_support")
    vocabulary = F.array(*[F.lit(x) for x in sorted(kept)]).cast("array<string>")
    basket = labelled.select(F.concat(F.array_intersect("items", vocabulary), F.array(label)).alias("items"))
    parts = int(labelled.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    model = FPGrowth(itemsCol="items", minSupport=min_support, minConfidence=min_confidence, numPartitions=parts).fit(basket)
    sets = model.freqItemsets
    marks = F.array(F.lit(BLOCK_ITEM), F.lit(ALLOW_ITEM))
    tokens = F.array_sort(F.array_except("items", marks))
    split = sets.where(F.size("items") <= max_items + 1).select(tokens.alias("tokens"), F.array_intersect("items", marks).alias("mark"), "freq").where(F.size("tokens") > 0)
    with_label = split.where(F.size("mark") == 1).select("tokens", F.col("mark")[0].alias("mark"), F.col("freq").alias("joint"))
    alone = split.where(F.size("mark") == 0).select("tokens", F.col("freq").alias("body"))
    rules = with_label.join(alone, "tokens").where(F.col("joint") >= min_confidence * F.col("body"))
    rows = rules.select("tokens", "mark", (F.col("joint") / F.col("body")).alias("confidence"), F.col("joint").alias("support")).limit(max_rules + 1).collect()
    if len(rows) > max_rules:
        raise ValueError(f"over {max_rules} association rules: raise min_support or min_confidence")
    mined = [(tuple(r.tokens), r.mark[1:], r.confidence, r.support) for r in rows]
    strongest = sorted(mined, key=lambda r: (-r[2], -len(r[0]), -r[3], r[1] != "block", r[0]))
    sure: dict[tuple, float] = {}  # of the rules that stay, by tokens and verdict
    for tokens, verdict, confidence, _ in sorted(strongest, key=lambda r: len(r[0])):
        parts = (part for size in range(1, len(tokens)) for part in combinations(sorted(tokens), size))
        if all(sure.get((part, verdict), -1.0) < confidence for part in parts):  # else a part of it says the same as surely
            sure[tuple(sorted(tokens)), verdict] = confidence
    return [r for r in strongest if (tuple(sorted(r[0])), r[1]) in sure]


def match_rules(items: Column, mined: list[tuple]) -> Column:
    """Verdict of the strongest mined rule inside ``items``, by an inverted index.

    The index maps a rule's anchor, its rarest token among the rules, to the rules hung on it, so a
    page only looks at the rules of tokens that it has.
    """
    if not mined:
        return F.lit(None).cast("string")
    uses: dict[str, int] = {}
    for tokens, *_ in mined:
        for t in tokens:
            uses[t] = uses.get(t, 0) + 1
    index: dict[str, list] = {}
    for rank, (tokens, verdict, *_rest) in enumerate(mined):
        index.setdefault(min(tokens, key=lambda t: (uses[t], t)), []).append((rank, tokens, verdict))
    hung = [
        F.array(*[F.struct(F.lit(k).alias("rank"), F.array(*[F.lit(t) for t in tokens]).alias("tokens"), F.lit(v).alias("verdict")) for k, tokens, v in index[a]])
        for a in index
    ]
    book = F.map_from_arrays(F.array(*[F.lit(a) for a in index]), F.array(*hung))
    empty = F.array().cast("array<struct<rank:int,tokens:array<string>,verdict:string>>")
    reached = F.flatten(F.transform(items, lambda x: F.coalesce(F.try_element_at(book, x), empty)))
    fitting = F.filter(reached, lambda r: F.size(F.array_except(r["tokens"], items)) == 0)
    return F.array_min(F.transform(fitting, lambda r: F.struct(r["rank"], r["verdict"])))["verdict"]


def judge(pages: DataFrame, rules=RULES, **mining) -> DataFrame:
    """page_id, host, path, rule, verdict, learned (the verdict of the mined rules, or null)."""
    seen = pages.select("page_id", "url").withColumn("host", host_of(F.col("url"))).withColumn("path", path_of(F.col("url")))
    seen = seen.withColumn("_gl_rule", explicit_rule(F.col("host"), F.col("path"), rules))
    seen = seen.withColumn("_gl_items", url_tokens(F.col("host"), F.col("path"), F.col("url")))
    labelled = materialize(
        seen.where(F.col("_gl_rule").isNotNull()).select(F.col("_gl_items").alias("items"), F.col("_gl_rule.verdict").alias("verdict")), "basket")
    mined = mine_rules(labelled, **mining)
    seen = seen.withColumn("learned", match_rules(F.col("_gl_items"), mined))
    verdict = F.coalesce(F.col("_gl_rule.verdict"), F.col("learned"), F.lit("allow"))
    return seen.select("page_id", "host", "path", F.col("_gl_rule.rule").alias("rule"), verdict.alias("verdict"), "learned")
