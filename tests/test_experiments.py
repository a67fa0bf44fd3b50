"""Experiments without a statement of their own, and their parts, against brute force on small tables."""

import hashlib
import math
import random
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_core import greedy

from gistloom.operators import answers, attention, measures, retrieval, scoring
from gistloom.plans import catalog_experiments as CE
from gistloom.plans import experiments as X
from gistloom.plans import workloads as W

BUDGETS = ("0.1", "0.4")


def corpus():
    rng = random.Random(6)
    words = ["alpha", "beta", "gamma", "delta", "north", "south", "price", "|", "of", "the", "harbour", "copper"]
    docs = []
    for i in range(3):
        lines = [" ".join(rng.choice(words) for _ in range(rng.randint(6, 16))) for _ in range(110)]
        for at in rng.sample(range(110), 3):
            lines[at] += f" lantern{i}"
        docs.append((i, "\n".join(lines)))
    return docs + [(7, "too short for nine questions"), (8, None), (9, "")]


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    root = tmp_path_factory.mktemp("experiments")
    spark.createDataFrame(corpus(), "doc_id long, text string").write.parquet(f"{root}/documents.parquet")
    return str(root)


def reference_vector(tokens, flags, question):
    """Attention over chunks of 256, scaled by chunk length, in plain loops over the audited weights."""
    out = []
    for start in range(0, len(tokens), 256):
        part, s = tokens[start : start + 256], flags[start : start + 256]
        total = np.zeros(len(part), np.int64)
        for _, _, w, _, _ in attention.weights(attention.keys_of(part), np.array(s), attention.keys_of(question)):
            total += w.sum(0)
        out += [int(x) * len(part) for x in total]
    return out


def bag(tokens, dims=64):
    held = [0.0] * dims
    for t in tokens:
        held[int(hashlib.md5(t.lower().encode()).hexdigest()[:8], 16) % dims] += 1
    return np.array(held)


def similarity(a, b):
    return round(float(a @ b) / (math.sqrt(float(a @ a)) * math.sqrt(float(b @ b))), 9)


def expected_contexts(rows, tok, flags):
    """{(meth, query, budget): kept positions} of the reducer, one retrieval method, the head and chance."""
    by_doc = {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
    out = {}
    for d, asked in by_doc.items():
        v = {r.query_id: reference_vector(tok[d], flags[d], r.tokens) for r in asked}
        fixed = scoring.FIXED_CONTRAST.split()
        v_fixed = reference_vector(tok[d], flags[d], fixed)
        for r in asked:
            others = [(similarity(bag(r.tokens), bag(o.tokens)), o.query_id, o) for o in asked if o.query_id != r.query_id]
            far = min(others)[2]
            n = len(r.tokens)
            vectors = {
                "raw": v[r.query_id], "fixed": [a * len(fixed) - b * n for a, b in zip(v[r.query_id], v_fixed, strict=True)],
                "auto": [a * len(far.tokens) - b * n for a, b in zip(v[r.query_id], v[far.query_id], strict=True)],
                "random": [int(hashlib.md5(f"{r.query_id}:{i}".encode()).hexdigest()[:7], 16) for i in range(len(tok[d]))],
            }
            chunks = [(k, s, min(s + 128, len(tok[d]))) for k, s in enumerate(range(0, max(len(tok[d]) - 32 - 1, 0) + 1, 96))]
            ranked = sorted(chunks, key=lambda c: (-round(float(bag(r.tokens) @ bag(tok[d][c[1] : c[2]])) / (np.linalg.norm(bag(r.tokens)) * np.linalg.norm(bag(tok[d][c[1] : c[2]]))), 6), c[0]))
            for b in BUDGETS:
                need = math.ceil(Decimal(b) * len(tok[d]))
                for m, values in vectors.items():
                    out[m, r.query_id, b] = set(greedy(values, b, "trim"))
                out["head", r.query_id, b] = set(range(need))
                best = None
                for k in range(1, 9):
                    kept = {p for _, s, e in ranked[:k] for p in range(s, e)}
                    best = kept if best is None or len(kept) <= need else best
                out["rag_unigram", r.query_id, b] = best
    return out


def test_science_contexts_against_brute_force(spark, tables):
    docs = spark.read.parquet(f"{tables}/documents.parquet")
    asked = X.science_questions(docs)
    rows = asked.collect()
    assert sorted({r.kind for r in rows}) == ["chosen1", "chosen2", "chosen3", "count", "dispersed", "first", "last", "longest", "second"] and len(rows) == 27
    for r in rows:
        text = dict(corpus())[r.doc_id]
        lines = text.split("\n")
        if r.kind == "dispersed":
            with_term = [x for x in lines if f"lantern{r.doc_id}" in x.split()]
            assert r.tokens[-1] == f"lantern{r.doc_id}" and [g.last_pos - g.first_pos for g in r.golds] == [len(x.split()) for x in with_term]
        if r.kind == "count":
            assert len(r.golds) == len(lines)
        if r.kind == "longest":
            assert len(r.golds) == 1 and r.golds[0].last_pos - r.golds[0].first_pos == math.ceil(max(len(x.split()) for x in lines) / 2)
    tokenized = W.asked_documents(docs, asked)
    held = {r.doc_id: r for r in tokenized.collect()}
    tok, flags = {d: r.tokens for d, r in held.items()}, {d: r.structural for d, r in held.items()}
    from gistloom.plans import reduce as R

    few = asked.where("kind in ('first', 'dispersed', 'count', 'last')")
    methods = ("raw", "fixed", "auto", "rag_unigram", "head", "random")
    got = X.contexts(tokenized, few, R.vectors(tokenized, few), BUDGETS, methods)
    want = expected_contexts(few.collect(), tok, flags)
    seen = {(r.meth, r.query_id, str(r.b.normalize())): {p for x in r.spans for p in range(x.first_pos, x.last_pos)} for r in got.collect()}
    assert seen == want
    for r in X.judged(got, few).collect():
        gold = {p for g in next(x for x in rows if x.query_id == r.query_id).golds for p in range(g.first_pos, g.last_pos)}
        kept = want[r.meth, r.query_id, str(r.b.normalize())]
        assert (r.n_used, r.n_in, r.n_gold) == (len(kept), len(kept & gold), len(gold))


def test_registered_experiments_on_small_tables(spark, tables):
    """Every question appears for every method and budget; accuracies follow from the judged rows."""
    kinds = {r.kind: r.n_queries for r in CE.QUERIES["w2_kinds"](spark, tables).collect()}
    assert set(kinds.values()) == {3} and len(kinds) == 9
    grid = CE.QUERIES["w2_grid"](spark, tables).collect()
    assert len(grid) == len(X.METHODS) * len(X.BUDGETS) * 7 and sum(r.n_queries for r in grid) == 27 * len(X.METHODS) * len(X.BUDGETS)
    assert all(0 <= r.recall <= 1 and 0 <= r.accuracy <= 1 for r in grid)
    curve = CE.QUERIES["w8_science"](spark, tables).collect()
    by = {(r.meth, r.budget, r.x): r.share for r in curve}
    assert all(by[m, b, x] >= by[m, b, x + 5] for m, b, x in by if x < 100)


def test_answers_are_read_on_from_the_question(spark):
    cases = [("a b c d e f g", "x b c", ["d", "e", "f", "g"]), ("a b c", "c", []), ("q a b", "z b a", ["b"]), ("", "a", []), ("a b", "", []), ("b c x b c y", "b c", ["x", "b", "c", "y"])]
    rows = spark.createDataFrame([(c.split(), q.split(), a) for c, q, a in cases], "context array<string>, question array<string>, want array<string>")
    assert all(r.answer == r.want for r in answers.generate(rows).collect())
    outside = answers.generate(rows, answers.Outside(lambda: lambda c, q: list(reversed(c))[:1] + q[:1])).collect()
    assert all(r.answer == list(reversed(r.context))[:1] + r.question[:1] for r in outside)


def test_judges_by_hand(spark):
    def lcs(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x.lower() == y.lower() else max(t[i][j + 1], t[i + 1][j])
        return t[-1][-1]

    rng = random.Random(3)
    rows = [([rng.choice("abcdeA") for _ in range(rng.randint(0, 9))], [rng.choice("abcdeB") for _ in range(rng.randint(0, 9))]) for _ in range(80)] + [([], []), (["x", "The", "end"], ["the", "end"])]
    df = spark.createDataFrame(rows, "a array<string>, g array<string>")
    a, g = F.col("a"), F.col("g")
    for r in df.select("a", "g", answers.rouge_l(a, g).alias("l"), answers.cosine(a, g).alias("c"), answers.open_judge(a, g).alias("fits"), answers.overlap(a, g).alias("o")).collect():
        x, y = [t.lower() for t in r.a], [t.lower() for t in r.g]
        total = len(x) + len(y)
        assert r.l == (round(2 * lcs(x, y) / total, 6) if total else 0)
        dot = sum(x.count(t) * y.count(t) for t in set(x))
        norm = math.sqrt(sum(x.count(t) ** 2 for t in set(x)) * sum(y.count(t) ** 2 for t in set(y)))
        assert abs(r.c - (round(dot / norm, 6) if norm else 0)) < 1e-6 and r.o == len(set(x) & set(y))
        common = sum(min(x.count(t), y.count(t)) for t in set(x))
        inside = any(x[i : i + len(y)] == y for i in range(len(x) - len(y) + 1))
        assert r.fits == bool(y and (inside or 2 * common / total >= 0.5))


def test_table_reader_and_usage(spark):
    rows = [("g1", k, f"n{k}", k * 2) for k in range(1, 9)] + [("g2", 11, "m", 5), ("g2", 110, "o", 6)]
    source = spark.createDataFrame(rows, "grp string, id long, name string, size int")
    tables = X.entity_tables(source, "grp", "id", ("name", "size"))
    asked = X.entity_questions(tables, "id", ("name", "size"))
    assert asked.count() == 20
    places = asked.select("doc_id", "query_id").join(tables.select("doc_id", "row_no"), "doc_id").withColumn("place", (F.lit(9) - F.col("row_no")).cast("int"))
    got = {r.meth: r for r in X.table_accuracy(tables, asked, places, "id", 4).collect()}
    assert got["full_table"].accuracy == 1.0 and got["full_table"].row_usage == 1.0
    # by place the last rows come first: rows 5 to 8 of the first table and none of the second
    assert got["top_rows"].accuracy == 8 / 20 and got["head_rows"].accuracy == 12 / 20 and {r.n_queries for r in got.values()} == {20}


def test_units_fill_the_budget(spark):
    rows = [(1, "q", 0, 0, 10, 100, 40), (1, "q", 1, 10, 12, 40, 40), (1, "q", 2, 12, 16, 60, 40), (1, "q", 3, 16, 40, 24, 40)]
    units = spark.createDataFrame(rows, "doc_id long, query_id string, unit_no int, first_pos int, last_pos int, score long, n_tokens int")
    assert {r.unit_no for r in X.select_units(units, "0.15").collect()} == {1, 2}
    assert {r.unit_no for r in X.select_units(units, "1").collect()} == {0, 1, 2, 3}


def test_schema_check_names_every_fault(spark, tables):
    from gistloom.sources.checked import load_checked

    assert load_checked(spark, f"{tables}/documents.parquet", "text string").columns == ["text"]
    with pytest.raises(ValueError, match="lang is missing; doc_id is bigint, not int"):
        load_checked(spark, f"{tables}/documents.parquet", "doc_id int, lang string")


def test_sketches_stay_near_the_exact_counts(spark):
    from gistloom.plans.catalog import QUERIES

    events = spark.read.parquet("/root/testdata/sf0.01/events.parquet")
    exact = {r.event_type: r for r in events.groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.expr("percentile(value, 0.45)").alias("lo"), F.expr("percentile(value, 0.55)").alias("hi")).collect()}
    for r in QUERIES["agg_approx"](spark, "/root/testdata/sf0.01").collect():
        e = exact[r.event_type]
        assert abs(r.users - e.users) <= 0.1 * e.users and abs(r.users_hll - e.users) <= 0.1 * e.users and e.lo <= r.median <= e.hi


def test_output_modes_agree(spark):
    """Complete and update end with the batch result; append leaves out what the watermark still holds open."""
    from gistloom.streaming import questions as S

    d = "/root/testdata/sf0.001"
    batch = {(r.start, r.event_type): r.n for r in S.tumbling(spark.read.parquet(f"{d}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))).collect()}
    complete, update, append = (
        {(r.start, r.event_type): r.n for r in S.drain(S.tumbling(S.source(spark, d)), mode, keys).collect()} for mode, keys in (("complete", ()), ("update", ("start", "event_type")), ("append", ())))
    assert complete == update == batch and append.items() <= batch.items() and 0 < len(append)
    closing = max(k[0] for k in batch)
    assert all(k[0] < closing for k in append)


def test_state_expires_behind_the_watermark(spark, tmp_path):
    """A user who comes back after the expiry starts anew; without expiry the state stays."""
    from gistloom.streaming import questions as S

    for k, day in enumerate(("01", "03", "05")):
        rows = [(k, f"2024-01-{day} 00:00:00", 1, "a", 0.0)] + ([(90 + k, f"2024-01-{day} 12:00:00", 2, "b", 0.0)])
        spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(f"{tmp_path}/in/{k}")

    def run(ttl):
        stream = spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string, value double").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
        return {r.user_id: (r.hits, r.misses) for r in S.drain(S.cache_state(stream, ttl), "update", ("user_id",)).collect()}
    assert run(None) == {1: (2, 1), 2: (2, 1)}
    assert run("1 hour")[1][1] == 1 and run("1 hour")[1][0] < 2


def test_bucketed_tables_meet_without_an_exchange_and_are_dropped(spark):
    from gistloom.plans import catalog_ops
    from gistloom.plans.catalog import QUERIES

    before = {t.name for t in spark.catalog.listTables()}
    QUERIES["join_bucketed"](spark, "/root/testdata/sf0.001").collect()
    assert {t.name for t in spark.catalog.listTables()} == before
    d = "/root/testdata/sf0.001"
    try:
        spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", "o_orderstatus").write.bucketBy(4, "o_orderkey").saveAsTable("gl_test_orders")
        spark.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey").write.bucketBy(4, "l_orderkey").saveAsTable("gl_test_lines")
        plan = catalog_ops.bucketed_join(spark.table("gl_test_orders"), spark.table("gl_test_lines"))._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange") == 1  # of the aggregation
    finally:
        spark.sql("drop table if exists gl_test_orders")
        spark.sql("drop table if exists gl_test_lines")


def test_align_budgets_takes_the_largest_that_fits(spark):
    swept = spark.createDataFrame([(1, "q", k, 100, 12 * k, [(0, 12 * k)]) for k in range(1, 5)], "doc_id long, query_id string, k int, n_tokens int, n_used long, spans array<struct<first_pos:int,last_pos:int>>")
    got = {str(r.b.normalize()): r.spans[0].last_pos for r in X.align_budgets(swept, ("0.05", "0.3", "1")).collect()}
    assert got == {"0.05": 12, "0.3": 24, "1": 48}
    assert retrieval.LENGTH == 128 and measures.rank_methods is not None


def test_streams_read_tables_of_several_files(spark, tmp_path):
    """A table written as a folder streams all of its rows; a stream without files gives no rows."""
    from gistloom.streaming import questions as S

    turns = [(c, t, "user" if t % 2 else "assistant", f"words of turn {t} about copper {c}") for c in range(6) for t in range(4)]
    spark.createDataFrame(turns, "conv_id long, turn int, role string, text string").repartition(3).write.parquet(f"{tmp_path}/conversations.parquet")
    assert {(r.conv_id, r.turn) for r in S.drain(S.source(spark, str(tmp_path), "conversations")).collect()} == {(c, t) for c, t, _, _ in turns}
    asked = {r.query_id for r in CE.QUERIES["stream_reduce_questions"](spark, str(tmp_path)).select("query_id").collect()}
    assert asked == {f"u{t}@{c}" for c in range(6) for t in (1, 3)}
    (tmp_path / "none").mkdir()
    nothing = spark.readStream.schema("conv_id long, turn int, role string, text string").parquet(f"{tmp_path}/none")
    assert S.questions_in_batches(nothing, lambda rows: rows, CE.SPAN_ROWS).collect() == []


def test_rows_ranked_in_the_task_as_by_score_vectors(spark, tmp_path):
    """Places from the fused ranking equal those of summed score vectors, over chunk ends, ties and packs."""
    from gistloom.functions.tokens import tokenize
    from gistloom.operators import rows
    from gistloom.plans import reduce as R

    source = [(k % 2, 7 * k, f"name {k % 5}", k % 3) for k in range(90)]
    tables = X.entity_tables(spark.createDataFrame(source, "grp long, id long, name string, size int"), "grp", "id", ("name", "size"))
    asked = X.entity_questions(tables, "id", ("name", "size"))
    got = rows.rank_rows(X.packed_tables(tables, asked), 4).collect()
    lines = {}
    for r in tables.orderBy("doc_id", "row_no").collect():
        lines.setdefault(r.doc_id, []).append(r.line)
    docs = spark.createDataFrame([(d, "\n".join(x)) for d, x in lines.items()], "doc_id long, text string")
    vectors = {r.query_id: r.v for r in R.vectors(tokenize(docs), asked, fixed=False).collect()}
    gold = {r.query_id: r.gold_row for r in asked.collect()}
    assert len(got) == len(gold) == 180
    for r in got:
        ends = np.cumsum([0] + [len(x.split()) for x in lines[r.doc_id]])
        sums = [sum(vectors[r.query_id][a:z]) for a, z in zip(ends[:-1], ends[1:], strict=True)]
        order = sorted(range(len(sums)), key=lambda k: (-sums[k], k))
        assert [k + 1 for k in order[:4]] == r.best and order.index(gold[r.query_id] - 1) + 1 == r.gold_place
    given = X.table_accuracy(tables, asked, X.best_places(rows.rank_rows(X.packed_tables(tables, asked), 4)), "id", 4)
    assert {r.meth: r.n_queries for r in given.collect()} == {"top_rows": 180, "head_rows": 180, "full_table": 180}


def rows_by_hand(lines, asked):
    """Places of the rows of a table, best first: every weight of every chunk is made and added up by row."""
    tokens = [t for x in lines for t in x.split()]
    owner = np.repeat(np.arange(len(lines)), [len(x.split()) for x in lines])
    flags = np.array([i == 0 or not any(c.isalnum() for c in t) or bool(set(t) & set("|<>")) for x in lines for i, t in enumerate(x.split())])
    total = np.zeros(len(lines), np.int64)
    for a in range(0, len(tokens), 256):
        part = tokens[a : a + 256]
        for _, _, w, _, _ in attention.weights(attention.keys_of(part), flags[a : a + 256], attention.keys_of(asked)):
            np.add.at(total, owner[a : a + 256], w.sum(0) * len(part))
    return sorted(range(len(lines)), key=lambda k: (-total[k], k))


def test_sign_words_of_rows_are_those_of_the_provider():
    """Chunks and questions get the same words one by one, all at once and from the provider."""
    from gistloom.operators import rows

    texts = [['"A":', "\u00c9t\u00e9", "7", "7", ",", "Longword"], ["x"], [], ["7", "\u00df", "\u0130", "longer"]]
    whole = rows._keys(texts)
    assert whole.shape == (11, 12) and whole.dtype == np.uint32
    for text, at in zip(texts, np.split(whole, [6, 7, 7]), strict=True):
        want = attention.keys_of(text).reshape(12, -1)
        assert (rows.signs(text) == want).all() and (at.T == want).all()


def test_every_order_table_is_asked_and_ranked(spark, tmp_path):
    """table_k_sweep_all over whole small tables, some of whose rows hold the key of another row more often than it does."""
    from gistloom.plans.catalog import QUERIES

    cols = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz"
    told = lambda o, k: f'"l_partkey": {100 * o} ' * 3 if 3 < k <= 3 + 3 * o else "A"
    data = [(o, k, 100 * o + k, 7 * k, 2.0, 1.0, 0.0, 0.0, told(o, k), "F", None) for o in range(1, 5) for k in range(5 + 9 * o)]
    source = spark.createDataFrame(data, cols)
    source.write.parquet(f"{tmp_path}/lineitem.parquet")
    places = []
    for t in W.asked_tables(source).collect():
        places += [1 + rows_by_hand(t.lines, q.tokens).index(q.gold_row - 1) for q in t.questions]
    assert len(places) == 5 * len(data) and max(places) > 8
    got = {r.k: r.accuracy for r in QUERIES["table_k_sweep_all"](spark, str(tmp_path)).collect()}
    assert got == {k: round(sum(p <= k for p in places) / len(places), 6) for k in range(1, 9)} and got[1] < got[8] < 1


def entity_by_hand(tables, questions):
    """What the three methods of a w4 query give, from rows ranked by hand; tables and questions (gold row, tokens) by name."""
    ranks = [(rows_by_hand(lines, q).index(gold), gold, len(lines)) for name, lines in tables.items() for gold, q in questions[name]]
    size, given = sum(n for _, _, n in ranks), sum(min(4, n) for _, _, n in ranks)
    share = lambda hits: round(sum(hits) / len(ranks), 6)
    return {
        "top_rows": (len(ranks), share(place < 4 for place, _, _ in ranks), round(given / size, 6)),
        "head_rows": (len(ranks), share(gold < 4 for _, gold, _ in ranks), round(given / size, 6)),
        "full_table": (len(ranks), 1.0, 1.0),
    }


def test_w4_part_on_whole_tables(spark, tmp_path):
    """Tables of one and several chunks; names that repeat the key of the first row hide it from the best four."""
    from gistloom.plans.catalog import QUERIES

    name = lambda k: '"p_partkey": 0 "p_partkey": 0 "p_partkey": 0' if k in (9, 12, 15, 18, 21) else f"large ring {k % 4}"
    data = [(k, name(k), f"Brand#{k % 3 if k < 60 else 0}", "SMALL" if k % 2 else "Gro\u00dfe", k % 50, 1.0) for k in range(90)]
    spark.createDataFrame(data, "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    tables, asked = {}, {}
    for k, part, brand, kind, size, _ in data:
        lines = tables.setdefault(brand, [])
        asked.setdefault(brand, []).extend((len(lines), [f'"{c}":', '"p_partkey":', str(k)]) for c in ("p_name", "p_type", "p_size"))
        lines.append(f'{{ "p_partkey": {k} , "p_name": {part} , "p_type": {kind} , "p_size": {size} }}')
    want = entity_by_hand(tables, asked)
    assert want["top_rows"][0] == 270 and want["head_rows"][1] < want["top_rows"][1] < 1
    assert {r.meth: (r.n_queries, r.accuracy, r.row_usage) for r in QUERIES["w4_part"](spark, str(tmp_path)).collect()} == want


def test_w4_supplier_on_whole_tables(spark, tmp_path):
    """Tables of one row and of many; a name that repeats the key of another row hides it from the best four."""
    from gistloom.plans.catalog import QUERIES

    name = lambda k: '"s_suppkey": 2 "s_suppkey": 2 "s_suppkey": 2' if k in (5, 8, 11, 14) else f"Supplier#{k:09d}"
    data = [(k, name(k), k % 3 if k < 70 else k, 1.5) for k in range(72)]
    spark.createDataFrame(data, "s_suppkey long, s_name string, s_nationkey int, s_acctbal double").write.parquet(f"{tmp_path}/supplier.parquet")
    tables, asked = {}, {}
    for k, supplier, nation, _ in data:
        lines = tables.setdefault(nation, [])
        asked.setdefault(nation, []).append((len(lines), ['"s_name":', '"s_suppkey":', str(k)]))
        lines.append(f'{{ "s_suppkey": {k} , "s_name": {supplier} }}')
    want = entity_by_hand(tables, asked)
    assert len(tables) == 5 and want["top_rows"][0] == 72 and want["head_rows"][1] < want["top_rows"][1] < 1
    assert {r.meth: (r.n_queries, r.accuracy, r.row_usage) for r in QUERIES["w4_supplier"](spark, str(tmp_path)).collect()} == want


def test_tables_with_their_questions_come_from_one_exchange(spark):
    """Lines and questions equal those of the joined forms; part keys that a table holds twice are not asked."""
    cols = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate string"
    data = [(o, k, 10 * o + min(k, 4), k, float(k), 1.0, 0.0, 0.0, "A", "F", "d") for o in range(9) for k in range(5 + o % 3)] + [(None, k, k, k, 1.0, 1.0, 0.0, 0.0, "A", "F", "d") for k in range(7)]
    source = spark.createDataFrame(data, cols)
    whole = W.asked_tables(source)
    got = whole.select("doc_id", F.explode("questions").alias("q")).select("doc_id", "q.*").collect()
    tables = W.order_tables(source)
    assert {(r.doc_id, r.query_id, tuple(r.tokens), r.gold_row) for r in got} == {(r.doc_id, r.query_id, tuple(r.tokens), r.gold_row) for r in W.table_questions(tables).collect()} and len(got) == 6 * 4 * 5
    assert {r.doc_id: "\n".join(r.lines) for r in whole.collect()} == {r.doc_id: r.text for r in W.table_documents(tables).collect()}
    plan = W.asked_tables(source)._jdf.queryExecution().executedPlan().toString()  # not run, so without a final plan
    assert plan.count("Exchange") == 1 and "Window" not in plan and "Join" not in plan


def test_contrast_moves_only_vectors_that_are_contrasts(spark):
    """Differences by hand, a missing contrast keeps the vector, and the other side is cut to contrasts before it moves."""
    vectors = spark.createDataFrame([(1, "a", [5, 7]), (1, "b", [1, 2]), (1, "fixed@1", [3, 3]), (2, "c", [4, 4])], "doc_id long, query_id string, v array<long>")
    pairs = spark.createDataFrame([(1, "a", "b", "farthest"), (1, "b", "fixed@1", "fixed"), (2, "c", "gone", "fixed")], "doc_id long, query_id string, contrast_id string, contrast_kind string")
    lengths = spark.createDataFrame([("a", 2), ("b", 3), ("fixed@1", 12), ("c", 5)], "query_id string, n int")
    got = scoring.differential(vectors, pairs, lengths)
    assert {r.query_id: (r.contrast_id, list(r.v)) for r in got.collect()} == {"a": ("b", [5 * 3 - 1 * 2, 7 * 3 - 2 * 2]), "b": ("fixed@1", [1 * 12 - 3 * 3, 2 * 12 - 3 * 3]), "c": ("gone", [4, 4])}
    assert "LeftSemi" in got._jdf.queryExecution().optimizedPlan().toString()
