"""Experiment workloads on the given tables: questions, gold spans, rivals and tables of rows."""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gistloom.functions.tokens import WORD, tokenize, words
from gistloom.shipping import ship

QUESTION_WORDS = 16
LINE_TOKENS = 6
FIELDS = {"science": (9, 1000, 10**9, 12), "notice": (6, 200, 500, 6)}  # questions, tokens of the document, lines at least
FIELD_PREFIX = {"science": "s", "notice": "n"}
PROBE = 5
_TOKENS = re.compile(WORD).findall
BROADCAST_PASSAGES, BROADCAST_BYTES = 200_000, 64 << 20


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def contained_passages(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """doc_id, item_id, text, passage, at: passages that occur in a document, at their first place.

    Passages within a counted bound of rows and bytes are searched all at once, by an automaton that
    reads every text once; more of them by an equi-join on hashes of five-token runs, whose hits are
    compared as text.  There is no cross join in either.
    """
    held = passages.select("item_id", F.col("text").alias("passage")).where(F.char_length("passage") > 0)
    size = held.agg(F.count("*").alias("rows"), F.coalesce(F.sum(F.octet_length("passage")), F.lit(0)).alias("bytes")).first()
    if size.rows <= BROADCAST_PASSAGES and size.bytes <= BROADCAST_BYTES:
        return _found_by_automaton(docs, [(r.item_id, r.passage) for r in held.collect()])
    return _found_by_probe(docs, held)


def _found_by_automaton(docs: DataFrame, passages: list[tuple[int, str]]) -> DataFrame:
    names = ["doc_id", "item_id", "text", "passage", "at"]

    def run(batches):
        import ahocorasick

        ids: dict[str, list] = {}
        for item, passage in passages:
            ids.setdefault(passage, []).append(item)
        machine = ahocorasick.Automaton()
        for passage in ids:
            machine.add_word(passage, passage)
        machine.make_automaton()
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                first: dict[str, int] = {}
                for end, passage in machine.iter(text or "") if ids else ():
                    first.setdefault(passage, end - len(passage) + 2)
                rows += [(doc, item, text, passage, at) for passage, at in first.items() for item in ids[passage]]
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, item_id long, text string, passage string, at int")


def _found_by_probe(docs: DataFrame, passages: DataFrame) -> DataFrame:
    probe = passages.select("item_id", "passage", F.xxhash64(F.slice(words(F.col("passage")), 1, PROBE)).alias("probe"))
    toks = docs.select("doc_id", words(F.col("text")).alias("t"))
    runs = F.when(F.size("t") > 0, F.transform(F.sequence(F.lit(1), F.greatest(F.size("t") - (PROBE - 1), F.lit(1))), lambda i: F.xxhash64(F.slice("t", i, F.lit(PROBE))))).otherwise(F.array().cast("array<long>"))
    hits = toks.select("doc_id", F.explode(runs).alias("probe")).join(probe, "probe").select("doc_id", "item_id", "passage").distinct()
    return hits.join(docs.select("doc_id", "text"), "doc_id").withColumn("at", F.expr("position(passage, text)")).where("at > 0")


def _cloze(lines: DataFrame, prefix: str, kind: str) -> DataFrame:
    half = F.floor(F.size("ts") / 2).cast("int")
    name = F.concat(F.lit(prefix), F.col("ln").cast("string"), F.lit("@"), F.col("doc_id").cast("string"))
    return lines.select("doc_id", name.alias("query_id"), F.lit(kind).alias("kind"), F.slice("ts", 1, F.least(half, F.lit(QUESTION_WORDS))).alias("tokens"),
                        (F.col("off") + half).cast("int").alias("first_pos"), (F.col("off") + F.size("ts")).cast("int").alias("last_pos"))


def lines_of(docs: DataFrame, least: int = LINE_TOKENS) -> DataFrame:
    """doc_id, ln, ts, off: lines with at least ``least`` tokens and the tokens before them."""
    lines = docs.select("doc_id", F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("ln", "l")).select("doc_id", "ln", words(F.col("l")).alias("ts"))
    before = Window.partitionBy("doc_id").orderBy("ln").rowsBetween(Window.unboundedPreceding, -1)
    return lines.withColumn("off", F.coalesce(F.sum(F.size("ts")).over(before), F.lit(0))).where(F.size("ts") >= least)


def passage_questions(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """First half of a contained passage asks for its second half; two cloze questions on lines of the same document."""
    found = contained_passages(docs, passages)
    bt = words(F.col("passage"))
    half = F.floor(F.size("bt") / 2).cast("int")
    asked = found.withColumn("bt", bt).withColumn("before", F.size(words(F.substring("text", F.lit(1), F.col("at") - 1)))).where(half > 0)
    name = F.concat(F.lit("p"), F.col("item_id").cast("string"), F.lit("@"), F.col("doc_id").cast("string"))
    main = asked.select("doc_id", name.alias("query_id"), F.lit("passage").alias("kind"), F.slice("bt", 1, half).alias("tokens"), (F.col("before") + half).alias("first_pos"), (F.col("before") + F.size("bt")).alias("last_pos"))
    lines = lines_of(docs.join(found.select("doc_id").distinct(), "doc_id", "left_semi"))
    both = Window.partitionBy("doc_id")
    ends = lines.withColumn("lo", F.min("ln").over(both)).withColumn("hi", F.max("ln").over(both))
    return main.unionByName(_cloze(ends.where("ln = lo"), "f", "first_line")).unionByName(_cloze(ends.where("ln = hi and hi > lo"), "l", "last_line"))


def hard_questions(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """Weakly similar questions: every fourth token of the passage's first half."""
    q = passage_questions(docs, passages).where("kind = 'passage'")
    thin = F.filter("tokens", lambda t, i: i % 4 == 0)
    return q.withColumn("tokens", thin).withColumn("query_id", F.concat(F.lit("h"), "query_id"))


def field_questions(docs: DataFrame, kind: str) -> DataFrame:
    """Cloze questions on lines chosen by md5: nine per long document, six per short one."""
    count, low, high, least = FIELDS[kind]
    sized = docs.where(F.size(words(F.col("text"))).between(low, high))
    lines = lines_of(sized)
    enough = Window.partitionBy("doc_id")
    order = Window.partitionBy("doc_id").orderBy(F.md5(F.concat_ws("-", F.col("doc_id").cast("string"), F.col("ln").cast("string"))))
    picked = lines.withColumn("n", F.count("*").over(enough)).withColumn("r", F.row_number().over(order)).where((F.col("n") >= least) & (F.col("r") <= count))
    return _cloze(picked, FIELD_PREFIX[kind], kind)


def field_of(doc_id: int, text: str, kind: str) -> list[dict]:
    """``field_questions`` of one document, with its golds as spans."""
    count, low, high, least = FIELDS[kind]
    lines = read_lines(text)
    if not low <= sum(len(ts) for _, ts, _ in lines) <= high:
        return []
    lines = [x for x in lines if len(x[1]) >= LINE_TOKENS]
    picked = by_md5(doc_id, lines)[:count] if len(lines) >= least else []
    return [cloze_of(f"{FIELD_PREFIX[kind]}{ln}@{doc_id}", kind, ts, off) for ln, ts, off in picked]


def read_lines(text: str) -> list[tuple[int, list[str], int]]:
    """Number, tokens and tokens before of every line."""
    out, off = [], 0
    for ln, line in enumerate(text.split("\n")):
        ts = _TOKENS(line)
        out.append((ln, ts, off))
        off += len(ts)
    return out


def by_md5(doc_id: int, lines: list) -> list:
    return sorted(lines, key=lambda x: (hashlib.md5(f"{doc_id}-{x[0]}".encode()).hexdigest(), x[0]))


def cloze_of(name: str, kind: str, ts: list[str], off: int) -> dict:
    half = len(ts) // 2
    return {"query_id": name, "kind": kind, "tokens": ts[: min(half, QUESTION_WORDS)], "golds": [{"first_pos": off + half, "last_pos": off + len(ts)}]}


def conversation_documents(turns: DataFrame) -> DataFrame:
    """doc_id, text: the non-user turns of a conversation; questions are the user turns."""
    said = turns.where("role <> 'user'").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("t"))
    return said.select(F.col("conv_id").alias("doc_id"), F.array_join("t.text", "\n").alias("text"))


def conversation_questions(turns: DataFrame) -> DataFrame:
    user = turns.where("role = 'user'")
    name = F.concat(F.lit("u"), F.col("turn").cast("string"), F.lit("@"), F.col("conv_id").cast("string"))
    return user.select(F.col("conv_id").alias("doc_id"), name.alias("query_id"), F.lit("turn").alias("kind"), words(F.col("text")).alias("tokens"))


ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def order_tables(lineitem: DataFrame, tables: int | None = None, least: int = 6) -> DataFrame:
    """table_id, row_no and the columns of all orders with enough rows, or of the first ``tables``; rows in a total order."""
    ids = lineitem.groupBy("l_orderkey").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("l_orderkey")
    if tables is not None:
        ids = F.broadcast(ids.orderBy("l_orderkey").limit(tables))
    kept = lineitem.join(ids, "l_orderkey")
    order = Window.partitionBy("l_orderkey").orderBy(*ORDER)
    return kept.withColumn("row_no", F.row_number().over(order)).withColumnRenamed("l_orderkey", "table_id")


COLUMNS = ("l_suppkey", "l_linenumber", "l_quantity", "l_returnflag", "l_linestatus")


def row_text(cell=F.col) -> Column:
    """A row as JSON-like tokens, each cell a token of its own and each value another; ``cell`` gives a column."""
    cells = [F.concat(F.lit(f'"{c}": '), cell(c).cast("int").cast("string") if c == "l_quantity" else cell(c).cast("string")) for c in ("l_partkey", *COLUMNS)]
    return F.concat(F.lit("{ "), F.concat_ws(" , ", *cells), F.lit(" }"))


def asked_tables(lineitem: DataFrame, least: int = 6) -> DataFrame:
    """doc_id, lines, questions (query_id, tokens, gold_row) of all orders with enough rows: ``order_tables`` and all ``table_questions`` by one exchange."""
    held = lineitem.where("l_orderkey is not null").groupBy("l_orderkey").agg(F.collect_list(F.struct(*ORDER)).alias("r"))
    tables = held.where(F.size("r") >= least).select(F.col("l_orderkey").alias("doc_id"), F.array_sort("r").alias("r"))

    def asked(x, i):
        key, row = x["l_partkey"].cast("string"), (i + 1).cast("int")
        name = lambda no: F.concat_ws("-", F.lit("t"), F.col("doc_id").cast("string"), row.cast("string"), F.lit(str(no)))
        each = [F.struct(name(no).alias("query_id"), F.array(F.lit(f'"{c}":'), F.lit('"l_partkey":'), key).alias("tokens"), row.alias("gold_row")) for no, c in enumerate(COLUMNS)]
        once = F.size(F.filter("r", lambda y: y["l_partkey"].eqNullSafe(x["l_partkey"]))) == 1
        return F.when(once, F.array(*each)).otherwise(F.slice(F.array(*each), 1, 0))

    lines = F.transform("r", lambda x: row_text(lambda c: x[c]))
    return tables.select("doc_id", lines.alias("lines"), F.flatten(F.transform("r", asked)).alias("questions")).where(F.size("questions") > 0)


def table_documents(tables: DataFrame) -> DataFrame:
    """doc_id, text with one row a line, in table order."""
    rows = tables.select("table_id", "row_no", row_text().alias("line")).groupBy("table_id").agg(F.array_sort(F.collect_list(F.struct("row_no", "line"))).alias("r"))
    return rows.select(F.col("table_id").alias("doc_id"), F.array_join("r.line", "\n").alias("text"))


def table_questions(tables: DataFrame, most: int | None = None) -> DataFrame:
    """"Value of a column where l_partkey is v", for part keys that a table holds once; the gold row is known.  All, or the first ``most``."""
    once = Window.partitionBy("table_id", "l_partkey")
    single = tables.withColumn("c", F.count("*").over(once)).where("c = 1")
    cells = F.array(*[F.struct(F.lit(k).alias("no"), F.lit(c).alias("column_name"), (F.col(c).cast("int") if c == "l_quantity" else F.col(c)).cast("string").alias("gold_value")) for k, c in enumerate(COLUMNS)])
    rows = single.select("table_id", "row_no", "l_partkey", F.explode(cells).alias("x")).select("table_id", "row_no", "l_partkey", "x.*")
    kept = rows if most is None else rows.orderBy("no", "table_id", "row_no").limit(most)
    name = F.concat_ws("-", F.lit("t"), F.col("table_id").cast("string"), F.col("row_no").cast("string"), F.col("no").cast("string"))
    asked = F.array(F.concat(F.lit('"'), F.col("column_name"), F.lit('":')), F.lit('"l_partkey":'), F.col("l_partkey").cast("string"))
    return kept.select(F.col("table_id").alias("doc_id"), name.alias("query_id"), asked.alias("tokens"), "column_name", F.col("row_no").alias("gold_row"), "gold_value")


def asked_documents(docs: DataFrame, questions: DataFrame) -> DataFrame:
    """Tokenised documents that have a question: the others are not read further."""
    return tokenize(docs.join(questions.select("doc_id").distinct(), "doc_id", "left_semi"))
