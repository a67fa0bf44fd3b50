"""Quality rules as a bitmask ledger.

Every rule is evaluated once per document.  The ledger keeps the measurements and one bit per
failed rule; a policy is a named mask over those bits, so policies can be versioned, compared and
ablated without reading a text again.

Defined cases: a null or empty text has no words and fails ``few_words``; texts of any length are
measured whole; repeated rows give repeated ledger rows; an empty table gives an empty ledger.
Everything is one narrow projection: no shuffle, and no state that grows with the corpus.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gistloom.llm.shared import split_words, text_of

WINDOW = 8
# Name of each rule and the failing condition over the measurements, in bit order.
RULES = (
    ("few_words", "n_words < 20"),
    ("repeated_words", "100 * n_repeat_words > 30 * n_words"),
    ("symbols", "100 * n_symbols > 8 * word_chars"),
    ("repeated_lines", "100 * n_dup_lines > 30 * n_lines"),
    ("long_words", "word_chars > 15 * n_words"),
    ("short_words", "word_chars < 2 * n_words"),
    ("shouting", "100 * n_upper > 60 * word_chars"),
)
BITS = {name: 1 << k for k, (name, _) in enumerate(RULES)}
BASE = BITS["few_words"] | BITS["repeated_words"]
POLICIES = {"base": BASE, "v1": BASE | BITS["symbols"] | BITS["repeated_lines"], "v2": (1 << len(RULES)) - 1}


def let(value: Column, body) -> Column:
    """``body`` of ``value``, which is computed once."""
    return F.transform(F.array(value), body)[0]


def _covered(starts: Column) -> Column:
    """Words under the windows that begin at the sorted ``starts``."""
    step = lambda s, p: F.struct(
        (p + WINDOW).alias("end"), (s["sum"] + p + WINDOW - F.greatest(s["end"], p)).alias("sum")
    )
    return F.aggregate(starts, F.struct(F.lit(0).alias("end"), F.lit(0).alias("sum")), step, lambda s: s["sum"])


def _repeated_starts(pairs: Column) -> Column:
    """Sorted i of the pairs (h, i) whose h occurs twice or more."""
    same = lambda s, a, b: F.get(s, a)["h"] == F.get(s, b)["h"]

    def alike(s: Column) -> Column:
        places = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda j: F.coalesce(same(s, j, j + 1), F.lit(False)) | F.coalesce(same(s, j, j - 1), F.lit(False)))
        return F.array_sort(F.transform(places, lambda j: F.get(s, j)["i"]))

    return let(F.array_sort(pairs), alike)


def repeated_words(words: Column) -> Column:
    """Words inside any window of 8 words that the text has twice or more, first copies included."""
    starts = F.sequence(F.lit(1), F.size(words) - (WINDOW - 1))
    hashes = F.transform(starts, lambda i: F.xxhash64(F.slice(words, i, F.lit(WINDOW))))
    # different hashes are different windows; equal ones are compared word by word
    alike = lambda h: _repeated_starts(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    equal = lambda at: _repeated_starts(F.transform(at, lambda i: F.struct(F.slice(words, i + 1, F.lit(WINDOW)).alias("h"), i.alias("i"))))
    counted = let(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(_covered(equal(alike(h)))))
    return F.when(F.size(words) <= WINDOW, F.lit(0)).otherwise(counted).cast("long")


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """doc_id and the measurements that the rules read."""
    body = text_of(F.col(text))
    words = let(split_words(F.col(text)), lambda w: F.struct(
        F.size(w).cast("long").alias("n_words"), F.char_length(F.array_join(w, "")).cast("long").alias("word_chars"), repeated_words(w).alias("n_repeat_words")))
    lines = F.filter(F.split(body, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    rows = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    only = lambda kept: F.char_length(F.regexp_replace(body, f"[^{kept}]+", "")).cast("long")
    return docs.select("doc_id", words.alias("_gl_w"), rows.alias("_gl_l"), only("#*$%&|<>").alias("n_symbols"), only("A-Z").alias("n_upper")).select(
        "doc_id", "_gl_w.n_words", "_gl_w.word_chars", "n_symbols", "_gl_l.n_dup_lines", "_gl_w.n_repeat_words", "_gl_l.n_lines", "n_upper"
    )


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """Measurements and ``failures``: bit k is set when rule k fails."""
    bits = sum((F.when(F.expr(cond), F.lit(BITS[name])).otherwise(F.lit(0)) for name, cond in RULES), F.lit(0))
    return measure(docs, text).withColumn("failures", bits.cast("long"))


def apply_policy(rows: DataFrame, policy: str | int = "v2") -> DataFrame:
    mask = POLICIES[policy] if isinstance(policy, str) else policy
    return rows.withColumn("kept", F.col("failures").bitwiseAND(F.lit(mask)) == 0)


def ablate(rows: DataFrame, policies=POLICIES) -> DataFrame:
    """For each policy and rule: documents failing the rule, and kept if that rule alone were left out.

    Documents are first counted per failure mask, of which there are 2^rules at most.
    """
    masks = rows.groupBy("failures").agg(F.count("*").alias("n"))
    grid = [(v, m, name, BITS[name]) for v, m in policies.items() for name in BITS if m & BITS[name]]
    cases = rows.sparkSession.createDataFrame(grid, "policy string, mask long, rule string, bit long")
    hit = lambda mask: F.col("failures").bitwiseAND(mask) != 0
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0))
    return masks.join(F.broadcast(cases)).groupBy("policy", "rule").agg(
        total(hit(F.col("bit"))).alias("fails_rule"),
        total(~hit(F.col("mask"))).alias("kept"),
        total(~hit(F.col("mask").bitwiseAND(F.bitwise_not(F.col("bit"))))).alias("kept_without_rule"),
    )
