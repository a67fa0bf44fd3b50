"""Experiments: every method's context at every budget, questions of several kinds, and what they are judged by."""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gistloom.functions.tokens import structural, tokenize, words
from gistloom.operators import answers, measures, retrieval, rows, selection, together
from gistloom.operators.selection import SPANS
from gistloom.plans import reduce as R
from gistloom.plans import workloads as W
from gistloom.staging import materialize

REDUCERS = ("raw", "fixed", "auto")
EMBEDDERS = ("unigram", "trigram", "tfidf")
METHODS = (*REDUCERS, *(f"rag_{k}" for k in EMBEDDERS), "rag_bm25", "head", "random")
BUDGETS = ("0.05", "0.1", "0.2", "0.4")


def align_budgets(swept: DataFrame, budgets=BUDGETS) -> DataFrame:
    """Of a k sweep the largest context within each budget, else one chunk."""
    grid = F.array(*[F.lit(b).cast("decimal(9,6)") for b in budgets])
    rows = swept.withColumn("b", F.explode(grid))
    fits = F.col("n_used") <= selection.budget_tokens(F.col("n_tokens"), F.col("b"))
    best = F.max(F.when(fits | (F.col("k") == 1), F.struct("k", "n_used", "spans"))).alias("m")
    return rows.groupBy("doc_id", "query_id", "b").agg(best).select("doc_id", "query_id", "b", "m.spans")


def contexts(tok: DataFrame, asked: DataFrame, scores: DataFrame, budgets=BUDGETS, methods=METHODS) -> DataFrame:
    """meth, doc_id, query_id, b, n_tokens, spans of all methods; a method without a hit has no spans.

    ``scores`` are the vectors of the questions and of each document's fixed contrast.
    """
    chunks = retrieval.chunk_overlap(tok)
    parts = []
    for m in methods:
        if m in REDUCERS:
            got = selection.select_windows(R.contrasted(scores, asked, m), budgets, "trim")
        elif m == "random":
            got = selection.select_windows(retrieval.random_scores(tok, asked), budgets, "trim")
        elif m in ("head", "tail", "both"):
            got = fold(DataFrame.unionByName, [retrieval.fixed_region(tok, asked, b, m) for b in budgets])
        else:
            hits = retrieval.bm25(chunks, asked) if m == "rag_bm25" else retrieval.retrieve(chunks, asked, m.removeprefix("rag_"))
            got = align_budgets(retrieval.k_sweep(hits, chunks), budgets)
        parts.append(got.select(F.lit(m).alias("meth"), "doc_id", "query_id", "b", "spans"))
    grid = asked.select("doc_id", "query_id").join(tok.select("doc_id", "n_tokens"), "doc_id").select(
        "*", F.explode(F.array(*[F.lit(m) for m in methods])).alias("meth")).select("*", F.explode(F.array(*[F.lit(b).cast("decimal(9,6)") for b in budgets])).alias("b"))
    found = grid.join(fold(DataFrame.unionByName, parts), ["meth", "doc_id", "query_id", "b"], "left")
    return found.withColumn("spans", F.coalesce("spans", F.array().cast(SPANS)))


def judged(found: DataFrame, golds: DataFrame) -> DataFrame:
    """Tokens used, evidence tokens among them and all evidence tokens; ``golds`` has query_id and an array of spans."""
    rows = found.join(golds.select("query_id", "golds"), "query_id")
    hit = F.aggregate("golds", F.lit(0), lambda s, g: s + measures.inside(F.col("spans"), g["first_pos"], g["last_pos"]))
    size = F.aggregate("golds", F.lit(0), lambda s, g: s + g["last_pos"] - g["first_pos"])
    keep = [c for c in found.columns if c != "spans"]
    return rows.select(*keep, selection.used_tokens(F.col("spans")).cast("long").alias("n_used"), hit.cast("long").alias("n_in"), size.cast("long").alias("n_gold"))


def one_gold(asked: DataFrame) -> DataFrame:
    span = F.struct(F.col("first_pos").cast("int").alias("first_pos"), F.col("last_pos").cast("int").alias("last_pos"))
    return asked.select("query_id", F.array(span).alias("golds"))


def summary(found: DataFrame, *by: str) -> DataFrame:
    """n_queries, accuracy (half of the evidence kept), recall, avg_tokens."""
    ok = (F.col("n_in") >= 0.5 * F.col("n_gold")).cast("int")
    return found.groupBy(*by).agg(
        F.count("*").alias("n_queries"), F.round(F.avg(ok), 6).alias("accuracy"), F.round(F.avg(F.col("n_in") / F.col("n_gold")), 6).alias("recall"), F.round(F.avg("n_used"), 6).alias("avg_tokens"))


def answered(found: DataFrame, tok: DataFrame, asked: DataFrame, answerer=answers.extractive) -> DataFrame:
    """meth, query_id, b, context, question, gold (first tokens of the evidence) and answer."""
    rows = found.join(tok.select("doc_id", "tokens"), "doc_id").join(asked.select("query_id", F.col("tokens").alias("question"), "first_pos", "last_pos"), "query_id")
    gold = F.slice("tokens", F.col("first_pos").cast("int") + 1, F.least(F.col("last_pos") - F.col("first_pos"), F.lit(answers.LENGTH)).cast("int"))
    prompts = rows.select("meth", "query_id", "b", answers.context_tokens(F.col("tokens"), F.col("spans")).alias("context"), "question", gold.alias("gold"))
    return answers.generate(prompts, answerer)


# ---- questions of several kinds on long documents ---------------------------------------------------

LONG_TOKENS, LONG_LINES = 1000, 12
TERM_CHARS, TERM_MOST = 5, 8


def science_questions(docs: DataFrame) -> DataFrame:
    """doc_id, query_id, kind, tokens, golds: nine questions on every document of 1,000 tokens and 12 lines.

    Cloze questions on the first, second, last and longest line and three lines by md5 order; the term
    that comes back most among rare ones, with the evidence dispersed over its lines; and the number
    of lines, with evidence at the head of each.
    """
    long = docs.where(F.size(words(F.col("text"))) >= LONG_TOKENS)
    doc = Window.partitionBy("doc_id")
    lines = W.lines_of(long).withColumn("n", F.count("*").over(doc)).where(F.col("n") >= LONG_LINES)
    lines = (
        lines.withColumn("no", F.row_number().over(doc.orderBy("ln")))
        .withColumn("by_size", F.row_number().over(doc.orderBy(F.desc(F.size("ts")), "ln")))
        .withColumn("by_hash", F.row_number().over(doc.orderBy(F.md5(F.concat_ws("-", F.col("doc_id").cast("string"), F.col("ln").cast("string"))), "ln")))
    )
    kinds = F.filter(F.array(
        F.when(F.col("no") == 1, "first"), F.when(F.col("no") == 2, "second"), F.when(F.col("no") == F.col("n"), "last"), F.when(F.col("by_size") == 1, "longest"),
        F.when(F.col("by_hash") <= 3, F.concat(F.lit("chosen"), F.col("by_hash").cast("string")))), lambda k: k.isNotNull())
    half = F.floor(F.size("ts") / 2).cast("int")
    span = lambda a, z: F.struct(a.cast("int").alias("first_pos"), z.cast("int").alias("last_pos"))
    name = lambda kind: F.concat(F.lit("sci-"), kind, F.lit("@"), F.col("doc_id").cast("string"))
    cloze = lines.select("doc_id", "ts", "off", F.explode(kinds).alias("kind")).select(
        "doc_id", name(F.col("kind")).alias("query_id"), "kind", F.slice("ts", 1, F.least(half, F.lit(W.QUESTION_WORDS))).alias("tokens"),
        F.array(span(F.col("off") + half, F.col("off") + F.size("ts"))).alias("golds"))
    whole = lines.select("doc_id", "ln", "ts", span(F.col("off"), F.col("off") + F.size("ts")).alias("line"), span(F.col("off"), F.col("off") + 1).alias("head"))
    held = whole.select("doc_id", "line", F.explode(F.array_distinct(F.transform("ts", F.lower))).alias("term")).where(F.char_length("term") >= TERM_CHARS)
    terms = held.groupBy("doc_id", "term").agg(F.count("*").alias("k"), F.array_sort(F.collect_list("line")).alias("golds")).where(F.col("k").between(2, TERM_MOST))
    best = terms.groupBy("doc_id").agg(F.min(F.struct((-F.col("k")).alias("k"), "term", "golds")).alias("m"))
    dispersed = best.select("doc_id", name(F.lit("dispersed")).alias("query_id"), F.lit("dispersed").alias("kind"), F.array(*[F.lit(w) for w in ("Which", "lines", "mention")], F.col("m.term")).alias("tokens"), F.col("m.golds").alias("golds"))
    heads = whole.groupBy("doc_id").agg(F.array_sort(F.collect_list("head")).alias("golds"))
    count = heads.select("doc_id", name(F.lit("count")).alias("query_id"), F.lit("count").alias("kind"), F.array(*[F.lit(w) for w in ("How", "many", "lines", "has", "the", "text")]).alias("tokens"), "golds")
    return cloze.unionByName(dispersed).unionByName(count)


def science_of(doc_id: int, text: str) -> list[dict]:
    """``science_questions`` of one document."""
    every = W.read_lines(text)
    lines = [x for x in every if len(x[1]) >= W.LINE_TOKENS]
    if sum(len(ts) for _, ts, _ in every) < LONG_TOKENS or len(lines) < LONG_LINES:
        return []
    chosen = W.by_md5(doc_id, lines)[:3]
    asked = [("first", lines[0]), ("second", lines[1]), ("last", lines[-1]), ("longest", min(lines, key=lambda x: (-len(x[1]), x[0]))), *[(f"chosen{i + 1}", x) for i, x in enumerate(chosen)]]
    out = [W.cloze_of(f"sci-{kind}@{doc_id}", kind, ts, off) for kind, (_, ts, off) in asked]
    span = lambda a, z: {"first_pos": a, "last_pos": z}
    held: dict[str, list] = {}
    for _, ts, off in lines:
        for term in {t for t in map(str.lower, ts) if len(t) >= TERM_CHARS}:
            held.setdefault(term, []).append(span(off, off + len(ts)))
    rare = [(-len(golds), term) for term, golds in held.items() if 2 <= len(golds) <= TERM_MOST]
    if rare:
        term = min(rare)[1]
        out.append({"query_id": f"sci-dispersed@{doc_id}", "kind": "dispersed", "tokens": ["Which", "lines", "mention", term], "golds": held[term]})
    heads = [span(off, off + 1) for _, _, off in lines]
    out.append({"query_id": f"sci-count@{doc_id}", "kind": "count", "tokens": ["How", "many", "lines", "has", "the", "text"], "golds": heads})
    return out


def judged_pages(pages: DataFrame, budgets=BUDGETS, methods=METHODS) -> DataFrame:
    """``judged`` over ``contexts``, with the kind of each question, for pages that hold all their questions (``together.ask``).

    No score vector or context leaves the task that reads the document.  Pages are written once if
    the methods need counts over all of them.
    """
    corpus = None
    if {"rag_bm25", "rag_tfidf"} & set(methods):
        pages = materialize(pages, "pages")
        counts = materialize(together.counted(pages), "terms")
        corpus = together.corpus_of(counts)
        pages = together.with_frequencies(pages, counts) if "rag_bm25" in methods else pages
    more = [c for c in pages.columns if c not in ("doc_id", "text")]
    return together.judge(tokenize(pages, more=more), budgets, methods, corpus)


# ---- tables other than orders -----------------------------------------------------------------------

def entity_tables(rows: DataFrame, group: str, key: str, columns: tuple[str, ...]) -> DataFrame:
    """doc_id, row_no, key, line and the cells: one table for each value of ``group``, rows by key."""
    cell = lambda c: F.concat(F.lit(f'"{c}": '), F.col(c).cast("string"))
    line = F.concat(F.lit("{ "), F.concat_ws(" , ", *[cell(c) for c in (key, *columns)]), F.lit(" }"))
    no = F.row_number().over(Window.partitionBy(group).orderBy(key))
    return rows.select(F.crc32(F.col(group).cast("string").cast("binary")).alias("doc_id"), no.alias("row_no"), F.col(key).cast("string").alias("key"), line.alias("line"), *[F.col(c).cast("string").alias(c) for c in columns])


def entity_questions(tables: DataFrame, key: str, columns: tuple[str, ...]) -> DataFrame:
    """The value of each column in each row, asked by key; the gold row is known."""
    cells = F.array(*[F.struct(F.lit(c).alias("column_name"), F.col(c).alias("gold_value")) for c in columns])
    rows = tables.select("doc_id", "row_no", "key", F.explode(cells).alias("x"))
    asked = F.array(F.concat(F.lit('"'), F.col("x.column_name"), F.lit('":')), F.lit(f'"{key}":'), F.col("key"))
    name = F.concat_ws("-", F.lit("e"), F.col("doc_id").cast("string"), F.col("row_no").cast("string"), F.col("x.column_name"))
    return rows.select("doc_id", name.alias("query_id"), asked.alias("tokens"), F.col("row_no").alias("gold_row"), F.col("x.gold_value").alias("gold_value"), F.col("x.column_name").alias("column_name"), "key")


def packed_tables(tables: DataFrame, asked: DataFrame) -> DataFrame:
    """doc_id, tokens, structural, sizes (tokens of each row) with packs of the table's questions."""
    held = tables.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("row_no", "line"))), lambda x: x["line"]).alias("lines"))
    return rows.meet(tokenized_tables(held), rows.packs(asked))


def tokenized_tables(held: DataFrame) -> DataFrame:
    """doc_id, lines and more as doc_id, tokens, structural, sizes and more; a row is one line."""
    by_line = F.transform("lines", lambda x: F.transform(words(x), lambda t, i: F.struct(t.alias("t"), structural(t, i == 0).alias("s"))))
    more = [c for c in held.columns if c not in ("doc_id", "lines")]
    cut = held.select("doc_id", by_line.alias("p"), *more)
    flat = cut.select("doc_id", F.flatten("p").alias("f"), F.transform("p", lambda x: F.size(x)).alias("sizes"), *more)
    return flat.select("doc_id", F.col("f.t").alias("tokens"), F.col("f.s").alias("structural"), "sizes", *more)


def best_places(ranked: DataFrame) -> DataFrame:
    """doc_id, query_id, row_no, place of the best rows."""
    return ranked.select("doc_id", "query_id", F.posexplode("best").alias("at", "row_no")).select("doc_id", "query_id", "row_no", (F.col("at") + 1).alias("place"))


def read_cell(lines: Column, key_name: str, key: Column, column: Column) -> Column:
    """The answer a reader of JSON-like rows gives: the column's value in the first row with the key."""
    mine = F.filter(lines, lambda x: F.contains(F.concat(x, F.lit(" ")), F.concat(F.lit(f'{{ "{key_name}": '), key, F.lit(" "))))
    cell = F.concat(F.lit('"'), column, F.lit('": '))
    parts = F.split(F.regexp_replace(F.get(mine, 0), "^\\{ | \\}$", ""), " , ")
    return F.get(F.transform(F.filter(parts, lambda p: F.startswith(p, cell)), lambda p: F.substr(p, F.char_length(cell) + 1)), 0)


def table_accuracy(tables: DataFrame, asked: DataFrame, places: DataFrame, key: str, most: int) -> DataFrame:
    """meth, n_queries, accuracy, row_usage of the first ``most`` rows by score, the first ones by order, and the full table.

    No question carries the rows of its table: the first rows are given once a table, and the full
    table answers with the first row that has the key.
    """
    lines = tables.select("doc_id", "row_no", "line")
    in_order = lambda rows: F.transform(F.array_sort(F.collect_list(rows)), lambda x: x["line"])
    row = F.struct("row_no", "line")
    top = places.where(F.col("place") <= most).select("doc_id", "query_id", "row_no").join(lines, ["doc_id", "row_no"]).groupBy("doc_id", "query_id").agg(in_order(row).alias("top_rows"))
    head = lines.groupBy("doc_id").agg(F.count("*").alias("n_rows"), in_order(F.when(F.col("row_no") <= most, row)).alias("head_rows"))
    name = F.regexp_extract("line", f'^\\{{ "{key}": ([^ ]+) ', 1)
    first = lines.select("doc_id", name.alias("key"), row.alias("r")).groupBy("doc_id", "key").agg(F.min("r").alias("r")).select("doc_id", "key", F.array("r.line").alias("found"))
    every = asked.select("doc_id", "query_id", "key", "column_name", "gold_value").join(head, "doc_id").join(top, ["doc_id", "query_id"], "left").join(first, ["doc_id", "key"], "left")
    none = F.array().cast("array<string>")
    given = [("top_rows", F.coalesce("top_rows", none), F.size(F.coalesce("top_rows", none))), ("head_rows", F.col("head_rows"), F.size("head_rows")), ("full_table", F.coalesce("found", none), F.col("n_rows"))]
    told = every.select("key", "column_name", "gold_value", "n_rows", F.explode(F.array(*[F.struct(F.lit(m).alias("meth"), rows.alias("lines"), n.cast("long").alias("n_given")) for m, rows, n in given])).alias("x"))
    told = told.select("key", "column_name", "gold_value", "n_rows", "x.*")
    right = F.coalesce(read_cell(F.col("lines"), key, F.col("key"), F.col("column_name")) == F.col("gold_value"), F.lit(False)).cast("int")
    return told.groupBy("meth").agg(F.count("*").alias("n_queries"), F.round(F.avg(right), 6).alias("accuracy"), F.round(F.sum("n_given") / F.sum("n_rows"), 6).alias("row_usage"))


# ---- units under a budget ---------------------------------------------------------------------------

def select_units(units: DataFrame, budget: str = "0.1") -> DataFrame:
    """Units (doc_id, query_id, unit_no, first_pos, last_pos, score, n_tokens) by mean score, as long as the budget holds all before."""
    size = F.col("last_pos") - F.col("first_pos")
    order = Window.partitionBy("doc_id", "query_id").orderBy(F.desc("density"), "unit_no")
    ranked = units.withColumn("density", F.col("score") / size).withColumn("total", F.sum(size).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return ranked.where(F.col("total") <= selection.budget_tokens(F.col("n_tokens"), F.lit(budget))).drop("density", "total")
