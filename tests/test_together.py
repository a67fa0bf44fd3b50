"""Documents judged in one task, against the plan of joins and against the old ways of its parts."""

import hashlib
import random
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_core import greedy
from test_experiments import corpus

from gistloom.functions.tokens import tokenize
from gistloom.operators import attention, together
from gistloom.plans import experiments as X
from gistloom.plans import reduce as R
from gistloom.plans import workloads as W


def short_corpus():
    rng = random.Random(9)
    words = ["alpha", "Beta", "gamma", "Straße", "İzmir", "price", "|", "of", "the", "harbour", "naïve", "日本"]
    docs = [(i, "\n".join(" ".join(rng.choice(words) for _ in range(rng.randint(3, 14))) for _ in range(20 + 4 * i))) for i in range(9)]
    return docs + [(20, None), (21, "")]


def long_corpus():
    """Some lines come back, so that questions with other ids have equal tokens."""
    docs = [(d, t) for d, t in corpus() if d < 2]
    line = "one line that is said over and over again in this text of ours"
    return docs + [(5, "\n".join([line] * 100)), (6, None)]


def judged_by_joins(docs, asked, golds, budgets, methods):
    tok = W.asked_documents(docs, asked)
    found = X.judged(X.contexts(tok, asked, R.vectors(tok, asked), budgets, methods), golds)
    return {(r.meth, r.query_id, str(r.b), r.n_tokens, r.n_used, r.n_in, r.n_gold) for r in found.collect()}


def judged_together(pages, budgets, methods):
    rows = X.judged_pages(pages, budgets, methods).collect()
    assert len(rows) == len({(r.meth, r.query_id, r.b) for r in rows})
    return {(r.meth, r.query_id, str(r.b), r.n_tokens, r.n_used, r.n_in, r.n_gold) for r in rows}


def test_science_judged_together_equals_the_joins(spark):
    docs = spark.createDataFrame(long_corpus(), "doc_id long, text string")
    asked, pages = X.science_questions(docs), together.ask(docs, X.science_of, 1999)
    one = pages.select(F.explode("questions").alias("q")).select("q.query_id", "q.kind", "q.tokens", "q.golds")
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, asked.select("query_id", "kind", "tokens", "golds").collect()))
    assert judged_together(pages, ("0.05", "0.4"), X.METHODS) == judged_by_joins(docs, asked, asked, ("0.05", "0.4"), X.METHODS)


def test_notices_judged_together_equal_the_joins(spark):
    docs = spark.createDataFrame(short_corpus(), "doc_id long, text string")
    asked = W.field_questions(docs, "notice")
    pages = together.ask(docs, lambda d, t: W.field_of(d, t, "notice"), 399)
    one = pages.select(F.explode("questions").alias("q")).select("q.query_id", "q.tokens", F.col("q.golds")[0]["first_pos"], F.col("q.golds")[0]["last_pos"])
    assert one.count() and sorted(map(tuple, one.collect())) == sorted(map(tuple, asked.select("query_id", "tokens", "first_pos", "last_pos").collect()))
    budgets = ("0.005", "0.01", "0.2")
    assert judged_together(pages, budgets, X.METHODS) == judged_by_joins(docs, asked, X.one_gold(asked), budgets, X.METHODS)


def test_no_page_has_a_question(spark):
    docs = spark.createDataFrame([(1, "too short"), (2, None)], "doc_id long, text string")
    assert X.judged_pages(together.ask(docs, X.science_of), ("0.1",)).collect() == []


def test_trimmed_windows_by_best_window_of_each_token():
    rng = random.Random(4)
    for n in (1, 2, 7, 50, 173):
        v = np.array([[rng.randint(0, 3) for _ in range(n)] for _ in range(3)] + [[5] * n], np.int64)
        for b, mask in zip(("0.005", "0.05", "0.4", "1"), together.trimmed(v, ("0.005", "0.05", "0.4", "1")), strict=True):
            for row, kept in zip(v, mask, strict=True):
                assert set(np.flatnonzero(kept)) == set(greedy(row.tolist(), b, "trim"))


def test_hashes_and_rounding():
    for names, n in ((["sci-first@12", "é@1"], 1234), (["x" * 49, ""], 120), (["x" * 60, "y"], 5), (["z"], 1), (["z"], 10001)):
        assert together.chance(names, n).tolist() == [[int(hashlib.md5(f"{name}:{i}".encode()).hexdigest()[:7], 16) for i in range(n)] for name in names]
    x = np.array([0.1234565, 0.5, 1 / 3, 0.9999995, 0.0000005, 2.5e-7])
    assert together.half_up(x, 6).tolist() == [int(Decimal(repr(float(v))).scaleb(6).to_integral_value(ROUND_HALF_UP)) for v in x]


def test_scores_of_a_pack_equal_the_audited_weights():
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(40)]
    for n in (1, 2, 255, 256):
        tokens = [rng.choice(vocabulary) for _ in range(n)]
        flags = np.array([rng.random() < 0.3 for _ in range(n)])
        asked = [[rng.choice(vocabulary) for _ in range(k)] for k in (5, 0, 16, 1)]
        got = attention._Pack(list("abcd"), asked).scores(attention.keys_of(tokens), flags, attention.ALL_LAYERS, attention.ALL_HEADS)
        for q, row in zip(asked, got, strict=True):
            want = sum((w.sum(0) for _, _, w, _, _ in attention.weights(attention.keys_of(tokens), flags, attention.keys_of(q))), np.zeros(n, np.int64))
            assert row.tolist() == want.tolist()


@pytest.mark.parametrize("size", [1, 3, 256])
def test_keys_of_chunks_are_made_at_once(size):
    tokens = [f"Token{i % 9}" for i in range(700)]
    apart = np.concatenate([attention.keys_of(tokens[s : s + size]) for s in range(0, 700, size)], 2)
    assert (attention.keys_of(tokens, range(0, 700, size)) == apart).all()


def test_rows_near_whole_numbers_are_divided_exactly(monkeypatch):
    tokens, asked = [f"t{i}" for i in range(99)], [["t1", "t2"], ["x"]]
    scores = lambda: attention._Pack(["a", "b"], asked).scores(attention.keys_of(tokens), np.arange(99) % 3 == 0, (0, 1), (1, 3))
    plain = scores()
    monkeypatch.setattr(attention, "CLOSE", 1.0)
    assert (scores() == plain).all()


def test_tokenize_keeps_more_columns(spark):
    df = spark.createDataFrame([(1, "a b", 5)], "doc_id long, text string, x int")
    assert tokenize(df, more=["x"]).first().x == 5
