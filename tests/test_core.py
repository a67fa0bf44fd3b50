"""Reducer against brute force, invariants and hand-made micro documents."""

import math
import random
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from gistloom.functions.tokens import tokenize
from gistloom.operators import attention, chunking, measures, scoring, selection
from gistloom.plans import reduce as R
from gistloom.plans import workloads as W


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(1)
    words = ["alpha", "beta", "gamma", "delta", "north", "south", "price", "|", "of", "the"]
    rows = [(i, "\n".join(" ".join(rng.choice(words) for _ in range(rng.randint(3, 9))) for _ in range(rng.randint(2, 60)))) for i in range(6)]
    return spark.createDataFrame([*rows, (50, ""), (51, None), (52, "solo")], "doc_id long, text string")


@pytest.fixture(scope="module")
def asked(spark):
    rows = [(i, f"{k}@{i}", q.split()) for i in range(6) for k, q in (("a", "price of north"), ("b", "alpha beta gamma delta"))] + [(52, "x@52", ["solo"])]
    return spark.createDataFrame(rows, "doc_id long, query_id string, tokens array<string>")


def test_chunks_partition_the_document(docs):
    t = {r.doc_id: r.tokens for r in tokenize(docs).collect()}
    got = {}
    for r in chunking.chunk(tokenize(docs), 16).orderBy("doc_id", "chunk_no").collect():
        assert r.n_chunk == len(r.tokens) <= 16 and r.start_pos == 16 * r.chunk_no
        got.setdefault(r.doc_id, []).extend(r.tokens)
    assert got == {k: v for k, v in t.items() if v}


def test_reuse_of_keys_changes_nothing(docs, asked):
    t = tokenize(docs)
    a, b = (R.vectors(t, asked, 16, reuse=x).collect() for x in (True, False))
    assert sorted(map(tuple, a), key=repr) == sorted(map(tuple, b), key=repr) and len(a) == 20
    n = {r.doc_id: r.n_tokens for r in t.collect()}
    assert all(len(r.v) == n[r.doc_id] for r in a)


def test_attention_is_a_causal_softmax():
    ctx, q = attention.keys_of("alpha beta | gamma".split()), attention.keys_of("beta of north".split())
    for layer, head, w, own, sink in attention.weights(ctx, np.array([True, False, True, False]), q):
        total = w.sum(1) + own.sum(1) + sink
        assert ((total <= 10**9) & (total > 10**9 - 10)).all()
        assert not np.triu(own, 1).any()
        e = [attention.TABLE[bin(int(q[layer, head, 1]) ^ int(c)).count("1")] for c in ctx[layer, head]]
        mine = [attention.TABLE[bin(int(q[layer, head, 1]) ^ int(q[layer, head, k])).count("1")] for k in (0, 1)]
        gain = [4, 1, 4, 1]
        den = sum(x * g for x, g in zip(e, gain, strict=True)) + sum(mine) + attention.SINK
        assert list(w[1]) == [x * g * 10**9 // den for x, g in zip(e, gain, strict=True)]


def test_short_tail_needs_the_chunk_scaling(spark):
    rows = [(1, "q", 0, 8, [125] * 8), (1, "q", 1, 2, [500] * 2)]
    s = spark.createDataFrame(rows, "doc_id long, query_id string, chunk_no int, n_chunk int, s array<long>")
    plain = scoring.reconstruct(scoring.scale_by_chunk(s, "none")).first().v
    scaled = scoring.reconstruct(scoring.scale_by_chunk(s)).first().v
    assert max(plain) in plain[8:] and plain[8] > plain[0] and len(set(scaled)) == 1


def test_long_query_flips_the_sign_without_normalising(spark):
    v = spark.createDataFrame([(1, "a", [30, 60]), (1, "b", [40, 80])], "doc_id long, query_id string, v array<long>")
    pairs = spark.createDataFrame([(1, "a", "b", "farthest")], "doc_id long, query_id string, contrast_id string, contrast_kind string")
    n = spark.createDataFrame([("a", 3), ("b", 6)], "query_id string, n int")
    assert min(scoring.differential(v, pairs, n).first().v) > 0 > max(scoring.differential(v, pairs, n, "none").first().v)


def test_mutual_pairs_mirror_and_lone_questions_fall_back(docs, asked):
    t = tokenize(docs)
    d = {r.query_id: r for r in R.contrasted(R.vectors(t, asked, 32), asked).collect()}
    for i in range(6):
        a, b = d[f"a@{i}"], d[f"b@{i}"]
        assert a.contrast_id == f"b@{i}" and all(x + y == 0 for x, y in zip(a.v, b.v, strict=True))
    assert d["x@52"].contrast_kind == "fixed"


def greedy(v, budget, overflow, share=Decimal("0.02")):
    n = len(v)
    left = math.ceil(Decimal(budget) * n)
    size = min(left, math.ceil(share * n))
    v = [sum(v[max(0, i - 2) : i + 3]) for i in range(n)]
    ranked = sorted(range(n - size + 1), key=lambda s: (-sum(v[s : s + size]), s))
    taken = set()
    for s in ranked:
        new = [i for i in range(s, s + size) if i not in taken]
        if len(new) > left:
            if overflow == "skip":
                continue
            if overflow == "trim":
                taken.update(new[:left])
            break
        taken.update(new)
        left -= len(new)
        if not left:
            break
    return sorted(taken)


@pytest.mark.parametrize("overflow", ["skip", "stop", "trim"])
def test_selection_matches_the_greedy(overflow):
    rng = random.Random(overflow)
    for _ in range(300):
        n = rng.randint(1, 150)
        v = np.array([rng.randint(-20, 40) for _ in range(n)])
        b = rng.choice(["0.005", "0.02", "0.1", "0.37", "1"])
        got = np.flatnonzero(selection.choose(selection.smooth(v), b, overflow, Decimal("0.05")))
        assert list(got) == greedy(list(map(int, v)), b, overflow, Decimal("0.05"))
        need = math.ceil(Decimal(b) * n)
        assert len(got) == need if overflow != "stop" else len(got) <= need


def test_budget_is_a_decimal(spark):
    r = spark.range(1).select(selection.budget_tokens(F.lit(100), F.lit("0.07")).alias("b"), selection.window_len(F.lit(100), F.lit("0.01")).alias("l")).first()
    assert (r.b, r.l) == (7, 1)


def test_merge_spans(spark):
    arr = F.array(*[F.struct(F.lit(a).alias("first_pos"), F.lit(b).alias("last_pos")) for a, b in ((10, 14), (3, 7), (0, 4), (14, 15))])
    assert [tuple(x) for x in spark.range(1).select(selection.merge_spans(arr).alias("m")).first().m] == [(0, 7), (10, 15)]


def test_whole_budget_gives_the_document(docs, asked):
    t = {r.doc_id: r.tokens for r in tokenize(docs).collect()}
    for r in R.reduce(docs, asked, "1").collect():
        assert r.prompt.split() == t[r.doc_id] and r.used == len(t[r.doc_id])


def test_outside_providers(docs, asked, spark):
    t = tokenize(docs)
    chunks = chunking.chunk(t, 16)
    flat = attention.LlmProvider(lambda: lambda ctx, q: [1.0 / len(ctx)] * len(ctx)).attend(chunks, asked)
    assert all(set(r.s) == {10**9 // r.n_chunk} for r in flat.collect())
    table = chunks.join(asked.select("doc_id", "query_id"), "doc_id").select("doc_id", "query_id", "chunk_no", F.lit(0).alias("layer"), F.lit(0).alias("head"), F.lit(0).alias("q_pos"), F.transform("tokens", lambda x: F.lit(0.5)).alias("weights"))
    assert all(set(r.s) == {5 * 10**8} for r in attention.PrecomputedProvider(table).attend(chunks, asked).collect())


def test_evidence_and_rouge(spark):
    s = spark.createDataFrame([("q", [(0, 4), (6, 9)])], "query_id string, spans array<struct<first_pos:int,last_pos:int>>")
    g = spark.createDataFrame([("q", 2, 8)], "query_id string, first_pos int, last_pos int")
    r = measures.evidence(s, g).first()
    assert (r.n_used, r.n_in, r.n_gold) == (7, 4, 6)
    t = lambda x: F.array(*[F.lit(w) for w in x.split()])
    assert abs(spark.range(1).select(measures.rouge(t("a b b c"), t("b b d")).alias("f")).first().f - 4 / 7) < 1e-9


def test_passages_are_found(spark, monkeypatch):
    d = spark.createDataFrame([(1, "x one two three four five six y"), (2, "one two three four five zzz"), (3, None)], "doc_id long, text string")
    p = spark.createDataFrame([(7, "one two three four five six")], "item_id long, text string")
    assert [(r.doc_id, r["at"]) for r in W.contained_passages(d, p).collect()] == [(1, 3)]
    rng = random.Random(12)
    word = lambda: rng.choice(["é", "bb", "c", "dd", "\U0001f600"])
    items = [(k, " ".join(word() for _ in range(rng.randint(5, 7)))) for k in range(40)] + [(90, "é bb c dd é"), (91, "é bb c dd é"), (92, ""), (93, None)]
    texts = [(k, " ".join(word() for _ in range(rng.randint(0, 300)))) for k in range(30)] + [(40, None), (41, "")]
    many, held = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    want = {(d, i, t.index(x) + 1) for d, t in texts for i, x in items if t and x and x in t}
    assert {(r.doc_id, r.item_id, r["at"]) for r in W.contained_passages(many, held).collect()} == want
    monkeypatch.setattr(W, "BROADCAST_PASSAGES", 0)
    probed = {(r.doc_id, r.item_id, r["at"]) for r in W.contained_passages(many, held).collect()}
    runs = {(d, i, a) for d, i, a in want for t in [f" {dict(texts)[d]} "] if f" {' '.join(dict(items)[i].split()[:5])} " in t}
    assert runs <= probed <= want


def test_plans_push_down_and_prune(spark):
    import __spark_entry__ as entry

    plan = entry.queries()["scan_parquet_pruned"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull" in plan and "l_comment" not in plan and "l_partkey" not in plan.split("== Physical Plan ==")[1]


def test_streams_equal_the_batch(spark):
    import __spark_entry__ as entry

    q = entry.queries()
    got = q["stream_tumbling"](spark, "/root/testdata/sf0.001").groupBy().sum("n").first()[0]
    assert got == spark.read.parquet("/root/testdata/sf0.001/events.parquet").count()


def test_no_masked_names_in_the_repository():
    import re
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    for f in [*root.glob("*.py"), *root.glob("gistloom/**/*.py"), root / "README.md"]:
        assert not re.search(r"NAME\d", f.read_text()), f


def test_table_workload_takes_every_order_and_column(spark):
    cols = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate string"
    rows = [(o, k, 10 * o + k, k, 1.0, 1.0, 0.0, 0.0, "A", "F", "d") for o in range(130) for k in range(6)]
    tables = W.order_tables(spark.createDataFrame(rows, cols))
    asked = W.table_questions(tables).groupBy("column_name").count().collect()
    assert {r.column_name: r["count"] for r in asked} == dict.fromkeys(W.COLUMNS, 780)


def test_searches_use_every_twentieth_vector_and_all_siblings(spark, tmp_path):
    from gistloom.plans.catalog import QUERIES

    vectors = [(i, [float(i % 7), 1.0, float(i % 5)], 0) for i in range(60)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    spark.createDataFrame([(i, i % 2, 0) for i in range(120)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    assert {r.q for r in QUERIES["embedding_cosine_search"](spark, str(tmp_path)).collect()} == {0, 20, 40}
    assert {r.siblings for r in QUERIES["join_siblings"](spark, str(tmp_path)).collect()} == {60}


def test_scores_are_computed_once_and_keys_stay_in_the_task(spark, docs, asked):
    """One attending and one selecting Python step; the former is read back from its table."""
    def steps(df):
        return df._jdf.queryExecution().executedPlan().toString().count("MapInArrow")

    t = tokenize(docs)
    assert steps(R.vectors(t, asked, 16)) == 1 and steps(R.reduce(docs, asked)) == 1
    assert "chunk_hash" not in R.vectors(t, asked, 16)._jdf.queryExecution().executedPlan().toString().split("MapInArrow")[0]


def test_packs_and_empty_questions(spark, docs):
    """More questions than a pack holds, and one without words, score as each does alone."""
    rows = [(i % 6, f"q{i}@{i % 6}", ["alpha", "price", f"w{i}"][: i % 4]) for i in range(60)]
    many = spark.createDataFrame(rows, "doc_id long, query_id string, tokens array<string>")
    chunks = chunking.chunk(tokenize(docs), 16)
    got = {(r.query_id, r.chunk_no): r.s for r in attention.PopcountProvider().attend(chunks, many).collect()}
    for c in chunks.collect():
        ctx = attention.keys_of(c.tokens)
        for d, q, tokens in rows:
            if d == c.doc_id:
                each = sum((w.sum(0) for _, _, w, _, _ in attention.weights(ctx, np.array(c.structural), attention.keys_of(tokens))), np.zeros(c.n_chunk, np.int64)) if tokens else np.zeros(c.n_chunk)
                assert list(each) == got[q, c.chunk_no]
    counts = attention.packs(many, 3).select(F.size("questions").alias("n")).collect()
    assert sum(r.n for r in counts) == 60 and len(counts) > 6


def test_scores_beyond_64_bits_are_ranked_exactly():
    big = 2**61
    v = np.array([big, big, 3, big, big, big, 1, 0], np.int64)
    flat = selection.smooth(v)
    assert flat.dtype == object and max(flat) > 2**63
    assert list(np.flatnonzero(selection.choose(v, "0.5", "skip", "0.25"))) == greedy_plain([int(x) for x in v], 4, 2)


def greedy_plain(v, left, size):
    taken: set = set()
    for s in sorted(range(len(v) - size + 1), key=lambda s: (-sum(v[s : s + size]), s)):
        new = [i for i in range(s, s + size) if i not in taken]
        if len(new) <= left:
            taken.update(new)
            left -= len(new)
    return sorted(taken)


def test_cosine_search_in_blocks_equals_all_pairs(spark, monkeypatch):
    """Copies, vectors without a cosine and other lengths rank as in a full comparison, whatever the blocks."""
    from gistloom.operators import nearest

    rng = random.Random(2)
    vectors = [(i, [round(rng.uniform(-1, 1), 2) for _ in range(4)]) for i in range(70)]
    vectors += [(100 + i, [0.5, 0.25, -0.5, 1.0]) for i in range(30)] + [(200, None), (201, [0.0] * 4), (202, [1.0, None, 2.0, 0.5]), (220, [1.0, 2.0]), (221, [2.0, 4.0])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<float>")
    monkeypatch.setattr(nearest, "ROWS", 16)
    monkeypatch.setattr(nearest, "QUERIES", 3)
    got = {(r.q, r.place): r.vec_id for r in nearest.search(df, df.where("vec_id % 20 = 0")).collect()}
    held = {i: None if v is None or None in v else [float(np.float32(x)) for x in v] for i, v in vectors}

    def cosine(a, b):
        if a is None or b is None or len(a) != len(b) or not any(a) or not any(b):
            return -9
        return round(sum(x * y for x, y in zip(a, b, strict=True)) / (sum(x * x for x in a) * sum(y * y for y in b)) ** 0.5, 6)

    want = {(q, k + 1): i for q in held if q % 20 == 0 for k, i in enumerate(sorted((i for i in held if i != q), key=lambda i: (-cosine(held[q], held[i]), i))[:5])}
    assert got == want
    plan = nearest.search(df, df.where("vec_id % 20 = 0"))._jdf.queryExecution().optimizedPlan().toString()
    assert "row_flat" in plan  # pairs are of blocks, not of rows
