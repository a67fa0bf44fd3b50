"""Exact set-similarity join on word shingles by a token-group matrix.

1. Documents with equal shingle sets form a class; one representative of each goes on.
2. Matrix tokens are the shingles of a fixed hash range; the range is the wider the lower the
   threshold.  A set that meets the threshold with another misses at most (1 - threshold) of its
   shingles there, so a lower bound (``need``) of its tokens must be shared.  Small sets, and those
   with too few shingles in the range for a bound, name all their shingles.
3. Only tokens that two sets name enter the matrix, and only sets whose shared tokens reach their
   bound stay.  For these the matrix is made again from all their shingles, with the full bound; the
   rarest shared tokens (all but the ``need`` - 1 most frequent, in one global order) route: two
   similar sets have a routing token in common.
4. Groups: a set joins the community of the most connected holder (pivot) of its routing tokens,
   and communities are dealt into groups of bounded size, each of which also holds its pivot.
   Inside a group all members are compared at once, and the union of its shingles is stored.
5. A set asks the groups that share a routing token with it and hold a larger component than its own.
   The stored union bounds its overlap with all their members; only groups that the bound lets
   through are opened, and their members compared with the sets that ask.
6. Links are contracted to connected components by min-label propagation with pointer jumping.

No pair is ever a row: groups answer with labels or with one link for two components.  What a task
holds at once is a bounded number of groups with a bounded portion of the sets that ask them (the
longest single set apart).  Copies are never expanded, so classes of any size cost one row a document.

Shingles are 64-bit hashes; a class is a pair of 64-bit sums over its set.

Defined cases: null, empty and blank texts have no shingles and link with nothing; fewer words
than the width are one shingle; repeated rows are one class; a row without doc_id belongs to its
class only; an empty table gives an empty result.  doc_id identifies a text.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gistloom.llm import kernels as K
from gistloom.llm.shared import aside, discard, materialize, release

GROUP_ROWS = 80
GROUP_SHINGLES = 200_000
PORTION_SHINGLES = 40_000  # of the sets that ask one group
SLOT_SHINGLES = 1_000_000
ROUND_SHARE = 128  # of 256 parts of the hash range that one round of token matching takes at most
WHOLE = 64  # sets up to this size name all their shingles
BROADCAST_IDS = 2_000_000
U = np.uint64


class Signer:
    """Matrix tokens of a sorted shingle set, and how many of them a similar set names at least."""

    def __init__(self, percent: int):
        self.percent = percent
        self.range = U(min(256, 640 * (100 - percent) // 100 or 1))  # of 256
        self.whole = 100 * WHOLE // percent  # partners of sets up to WHOLE reach this size

    def _read(self, s: np.ndarray) -> tuple[np.ndarray, int]:
        missing = (100 - self.percent) * len(s) // 100
        if len(s) <= WHOLE:
            return s, len(s) - missing
        inside = s[(K.mix(s) & U(255)) < self.range]
        bound = len(inside) - missing
        if bound < 1:
            # a similar set names everything too, or the range alone bounds its share from below
            return s, 1
        return (s if len(s) <= self.whole else inside), bound

    def tokens(self, s: np.ndarray) -> np.ndarray:
        return self._read(s)[0]

    def need(self, s: np.ndarray) -> int:
        return self._read(s)[1] if len(s) else 0


def _list_array(lists: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int32)
    flat = np.concatenate(lists).view(np.int64) if lists else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))


def _flush(rows: list, columns: list[str]) -> pa.RecordBatch:
    parts = list(zip(*rows, strict=True))
    arrays = [_list_array(list(p)) if isinstance(p[0], np.ndarray) else pa.array(p, pa.int64()) for p in parts]
    return pa.RecordBatch.from_arrays(arrays, columns)


def digests(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """doc_id, n_shingles, a 128-bit digest of the shingle set, its matrix tokens and how many a partner must share."""
    columns = ["doc_id", "n_shingles", "d1", "d2", "need", "tokens"]

    def run(batches):
        signer = Signer(percent)
        for batch in batches:
            rows, size = [], 0
            for i, s in zip(batch.column(0).to_pylist(), K.shingle_sets(batch.column(1), width), strict=True):
                one = int(K.mix(s).sum(dtype=U).view(np.int64)) if len(s) else 0
                two = int(K.mix(s ^ K.GOLDEN).sum(dtype=U).view(np.int64)) if len(s) else 0
                tokens, need = signer._read(s)
                rows.append((i, len(s), one, two, need, tokens))
                size += len(tokens)
                if size > 1_000_000:
                    yield _flush(rows, columns)
                    rows, size = [], 0
            if rows:
                yield _flush(rows, columns)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, n_shingles long, d1 long, d2 long, need long, tokens array<long>")


def sets_of(docs: DataFrame, width: int) -> DataFrame:
    """(rep, n, shingles) of each document."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_pylist()
            rows, size = [], 0
            for i, s in zip(ids, K.shingle_sets(batch.column(1), width), strict=True):
                rows.append((i, len(s), s))
                size += len(s)
                if size > 1_000_000:
                    yield _flush(rows, ["rep", "n", "shingles"])
                    rows, size = [], 0
            if rows:
                yield _flush(rows, ["rep", "n", "shingles"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "rep long, n long, shingles array<long>")


def _only(docs: DataFrame, ids: DataFrame, limit: int) -> DataFrame:
    """Documents whose doc_id is among ``ids`` (column _gl_rep): broadcast under a counted bound, else shuffled."""
    small = F.broadcast(ids) if ids.count() <= limit else ids
    return docs.join(small, F.col("doc_id") == F.col("_gl_rep"), "left_semi")


def components(edges: DataFrame) -> DataFrame:
    """(node, label): the smallest node that each node of the edges (a, b) reaches."""
    both = materialize(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "edges")
    labels = materialize(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("a"), F.min("b")).alias("label")), "labels")
    while True:
        heard = both.join(labels.select(F.col("node").alias("_gl_n"), "label"), F.col("b") == F.col("_gl_n")).groupBy("a").agg(F.min("label").alias("near"))
        step = labels.select("node", "label").join(heard, F.col("node") == F.col("a"), "left").select("node", F.col("label").alias("old"), F.least("label", F.coalesce("near", "label")).alias("label"))
        jump = labels.select(F.col("node").alias("_gl_n"), F.col("label").alias("far"))
        nxt = materialize(step.join(jump, F.col("label") == F.col("_gl_n"), "left").select("node", "old", F.least("label", F.coalesce("far", "label")).alias("label")), "labels")
        discard(labels)
        labels = nxt
        if not nxt.where("old <> label").limit(1).count():
            discard(both)
            return nxt.select("node", "label")


def _merge(labels: np.ndarray, groups) -> None:
    """Give all members of each group the smallest label among them."""
    for g in groups:
        seen = np.unique(labels[g])
        if len(seen) > 1:
            labels[np.isin(labels, seen)] = seen[0]


def link_members(ids: np.ndarray, sets: list[np.ndarray], percent: int) -> np.ndarray:
    """Smallest id that each member reaches by links inside the group."""
    labels, sizes = np.array(ids), np.array([len(s) for s in sets])
    for lo, counts in K.overlaps(sets, sets):
        rows = sizes[lo : lo + len(counts), None]
        linked = 100 * counts >= percent * (rows + sizes[None, :] - counts)
        _merge(labels, (np.flatnonzero(x) for x in linked))
    return labels


def qualifying(union: np.ndarray, sets: list[np.ndarray], percent: int) -> np.ndarray:
    """Which sets can be similar to a member of a group: those that its union overlaps far enough."""
    ends = np.cumsum([len(s) for s in sets])
    flat = np.concatenate(sets)
    at = np.searchsorted(union, flat)
    at[at == len(union)] = 0
    hits = np.concatenate([[0], np.cumsum(union[at] == flat)])
    size = np.diff(np.concatenate([[0], ends]))
    return 100 * (hits[ends] - hits[ends - size]) >= percent * size


def link_across(ids_a, sets_a, comp_a, ids_b, sets_b, comp_b, percent: int) -> list[tuple[int, int]]:
    """Links of sets to the members of a group, one for each pair of components at most."""
    sizes_a, sizes_b = np.array([len(s) for s in sets_a]), np.array([len(s) for s in sets_b])
    found: dict = {}
    for lo, counts in K.overlaps(sets_a, sets_b):
        linked = 100 * counts >= percent * (sizes_a[lo : lo + len(counts), None] + sizes_b[None, :] - counts)
        for r, c in zip(*np.nonzero(linked), strict=True):
            if comp_a[lo + r] != comp_b[c]:
                found.setdefault((comp_a[lo + r], comp_b[c]), (int(ids_a[lo + r]), int(ids_b[c])))
    return list(found.values())


def _as_sets(column: pa.ChunkedArray) -> list[np.ndarray]:
    flat = column.combine_chunks()
    if isinstance(flat, pa.ChunkedArray):
        flat = pa.concat_arrays(flat.chunks)
    ends, values = np.asarray(flat.offsets), np.asarray(flat.values).view(U)
    return [values[ends[i] : ends[i + 1]] for i in range(len(flat))]


def token_matrix(named: DataFrame, rounds: int) -> list[DataFrame]:
    """(rep, need, tok, df) of the tokens that two representatives or more name, in a table a round.

    ``named`` holds (rep, need, tokens).  Tokens are matched in rounds by residue, so that the shuffle
    files of one round only are on disk at a time.
    """
    matrix = []
    for turn in range(rounds):
        rows = named.select("rep", "need", F.explode("tokens").alias("tok"))
        rows = rows.where(F.pmod("tok", F.lit(rounds)) == turn) if rounds > 1 else rows
        shared = rows.groupBy("tok").agg(F.count("*").alias("df")).where("df > 1")
        matrix.append(materialize(rows.join(shared.hint("shuffle_hash"), "tok").select("rep", "need", "tok", "df"), "matrix"))
        release(named.sparkSession)
    return matrix


def covered(matrix: DataFrame) -> DataFrame:
    """_gl_rep of the sets whose shared tokens reach their bound."""
    return matrix.groupBy("rep").agg(F.count("*").alias("c"), F.max("need").alias("need")).where("c >= need").select(F.col("rep").alias("_gl_rep"))


def routing_tokens(matrix: DataFrame) -> DataFrame:
    """(rep, tok, w) of the sets whose shared tokens reach their bound, with all but their need - 1 most frequent tokens."""
    by = Window.partitionBy("rep")
    told = matrix.withColumns({
        "c": F.count("*").over(by), "w": F.sum("df").over(by), "no": F.row_number().over(by.orderBy("df", "tok"))})
    return told.where("c >= need and no <= c - need + 1").select("rep", "tok", "w")


def _cut(table: pa.Table, *keys: str) -> tuple[pa.Table, np.ndarray, list[int]]:
    """The table sorted by integer keys, and the first and last row of each run of equal keys."""
    table = table.sort_by([(k, "ascending") for k in keys])
    new = np.zeros(max(len(table), 1), bool)
    new[0] = True
    for k in keys:
        v = table[k].to_numpy()
        new[1:] |= v[1:] != v[:-1]
    cut = np.flatnonzero(new)
    return table, cut, [*cut[1:], len(table)]


def similarity_components(docs: DataFrame, width: int = 5, percent: int = 80, rounds: int | None = None) -> DataFrame:
    """doc_id, n_shingles, class_id, component_id of every document row."""
    spark = docs.sparkSession
    rounds = rounds or max(1, -(-2 * int(Signer(percent).range) // ROUND_SHARE))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    read = materialize(digests(docs, width, percent), "digests")
    known = materialize(read.drop("tokens"), "known")
    classes = known.where("n_shingles > 0").groupBy("d1", "d2").agg(F.min("doc_id").alias("_gl_rep"))
    reps = materialize(classes.where(F.col("_gl_rep").isNotNull()), "classes")
    chosen = _only(read, reps.select("_gl_rep"), BROADCAST_IDS).select(F.col("doc_id").alias("rep"), "need", "tokens")
    matrix = token_matrix(chosen, rounds)
    near = materialize(covered(reduce(DataFrame.union, matrix)), "near")
    discard(read, *matrix)
    sets = materialize(sets_of(_only(docs.select("doc_id", "text"), near, BROADCAST_IDS), width).dropDuplicates(["rep"]), "sets")
    release(spark)
    whole = sets.select("rep", (F.col("n") - F.floor(F.col("n") * (100 - percent) / 100)).alias("need"), F.col("shingles").alias("tokens"))
    matrix = token_matrix(whole, rounds)
    routes = materialize(routing_tokens(reduce(DataFrame.union, matrix)), "routes")
    discard(near, *matrix)
    release(spark)

    # communities, and the groups that they are dealt into
    pivots = routes.groupBy("tok").agg(F.max(F.struct(F.col("w"), (-F.col("rep")).alias("minus"))).alias("p"), F.count("*").alias("holders")).where("holders > 1")
    home = materialize(
        routes.join(pivots, "tok").groupBy("rep").agg(F.max("p").alias("p")).select("rep", (-F.col("p.minus")).alias("pivot")), "home")
    sized = home.join(sets.select("rep", "n"), "rep")
    spread = sized.groupBy("pivot").agg(
        F.greatest(F.ceil(F.count("*") / GROUP_ROWS), F.ceil(F.sum("n") / GROUP_SHINGLES)).cast("int").alias("groups"))
    member = materialize(
        sized.join(spread, "pivot").select("rep", F.struct("pivot", F.pmod(F.xxhash64("rep"), F.col("groups").cast("long")).cast("int").alias("part")).alias("gid"))
        .select("rep", F.xxhash64("gid.pivot", "gid.part").alias("gid"), F.col("gid.pivot").alias("pivot")), "member")

    def slots(shingles: int) -> int:
        return max(4 * parts, shingles // SLOT_SHINGLES)

    # inside the groups; every group of a community also holds the pivot, which ties them together
    guests = member.select(F.col("pivot").alias("rep"), "gid").distinct()
    seats = member.select("rep", "gid").union(guests).distinct()
    total = sets.agg(F.sum("n")).first()[0] or 0

    def inside(table: pa.Table) -> pa.Table:
        table, first, last = _cut(table, "gid")
        ids, held, gid = table["rep"].to_numpy(), _as_sets(table["shingles"]), table["gid"].to_numpy()
        labels = [link_members(ids[i:j], held[i:j], percent) for i, j in zip(first, last, strict=True)]
        unions = [np.unique(np.concatenate(held[i:j])) for i, j in zip(first, last, strict=True)]
        none = [np.zeros(0, U)] * len(ids)
        return pa.table({
            "gid": pa.array(np.concatenate([gid, gid[first]]), pa.int64()), "a": pa.array(np.concatenate([ids, np.zeros(len(first), np.int64)]), pa.int64()),
            "b": pa.array(np.concatenate([*labels, np.zeros(len(first), np.int64)]), pa.int64()), "tokens": _list_array(none + unions)})

    grouped = seats.join(sets.select("rep", "shingles"), "rep").withColumn("slot", F.pmod(F.xxhash64("gid"), F.lit(slots(total)))).groupBy("slot")
    inner = materialize(grouped.applyInArrow(inside, "gid long, a long, b long, tokens array<long>"), "inner")
    release(spark)
    unions = inner.where(F.size("tokens") > 0).select("gid", F.col("tokens").alias("shingles"))
    links = inner.where("size(tokens) = 0 and a <> b").select("a", "b")
    labels = components(links)

    # between groups: a set asks groups that share a routing token and hold a larger component than its own
    comps = home.select("rep").join(labels, F.col("rep") == F.col("node"), "left").select("rep", F.coalesce("label", "rep").alias("comp"))
    counts = comps.groupBy("comp").agg(F.count("*").alias("members"))
    placed = materialize(
        member.select("rep", "gid").join(comps, "rep").join(counts, "comp").select("rep", "gid", "comp", F.struct("members", "comp").alias("rank")), "placed")
    routed = routes.select("rep", "tok").join(placed, "rep")
    live = routed.groupBy("tok").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("tok")
    routed = materialize(routed.join(live, "tok"), "routed")
    posting = routed.groupBy("tok", "gid").agg(F.max("rank").alias("top")).select("tok", F.col("gid").alias("asked"), "top")
    asks = materialize(routed.join(posting, "tok").where("gid <> asked and top > rank").select("rep", "comp", "asked").distinct(), "asks")
    release(spark)

    def portions(asks: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Sets that ask, and the groups asked, each dealt into portions of bounded size with their slot."""
        queries = asks.join(sets, "rep")
        load = asks.join(sets.select("rep", "n"), "rep").groupBy("asked").agg(F.sum("n").alias("n"))
        load = load.select("asked", F.ceil(F.col("n") / PORTION_SHINGLES).cast("long").alias("portions"), "n")
        sent = load.agg(F.sum("n"), F.sum("portions")).first()
        wide = F.lit(slots((sent[0] or 0) + (sent[1] or 0) * PORTION_SHINGLES))
        dealt = queries.join(load.select("asked", "portions"), "asked").withColumn("portion", F.pmod(F.xxhash64("rep"), F.col("portions")))
        opened = load.select("asked", F.explode(F.sequence(F.lit(0).cast("long"), F.col("portions") - 1)).alias("portion"))
        slot = F.pmod(F.xxhash64("asked", "portion"), wide).alias("slot")
        ask_rows = dealt.select(slot, F.xxhash64("asked", "portion").alias("cell"), F.lit(1).alias("side"), "asked", "rep", "comp", "shingles")
        return ask_rows, opened.select(slot, F.xxhash64("asked", "portion").alias("cell"), F.lit(0).alias("side"), "asked")

    def bound(table: pa.Table) -> pa.Table:
        table, first, last = _cut(table, "cell", "side")
        held, side, keep = _as_sets(table["shingles"]), table["side"].to_numpy(), np.zeros(len(table), bool)
        cell = table["cell"].to_numpy()
        for i, j in zip(first, last, strict=True):
            if side[i] == 1 and i and cell[i - 1] == cell[i]:
                keep[i:j] = qualifying(held[i - 1], held[i:j], percent)
        return table.select(["rep", "comp", "asked"]).filter(pa.array(keep))

    queries, opened = portions(asks)
    stored = opened.join(unions, F.col("asked") == F.col("gid")).select("slot", "cell", "side", "asked", F.lit(0).cast("long").alias("rep"), F.lit(0).cast("long").alias("comp"), "shingles")
    passed = materialize(queries.union(stored).groupBy("slot").applyInArrow(bound, "rep long, comp long, asked long"), "passed")
    release(spark)

    def across(table: pa.Table) -> pa.Table:
        table, first, last = _cut(table, "cell", "side")
        ids, comp, held = table["rep"].to_numpy(), table["comp"].to_numpy(), _as_sets(table["shingles"])
        cell, out = table["cell"].to_numpy(), []
        for k in range(1, len(first)):
            i, mid, j = first[k - 1], first[k], last[k]
            if cell[i] == cell[mid]:
                out += link_across(ids[mid:j], held[mid:j], comp[mid:j], ids[i:mid], held[i:mid], comp[i:mid], percent)
        return pa.table({"a": pa.array([x[0] for x in out], pa.int64()), "b": pa.array([x[1] for x in out], pa.int64())})

    queries, opened = portions(passed)
    members = opened.join(placed, F.col("asked") == F.col("gid")).join(sets, "rep").select("slot", "cell", "side", "asked", "rep", "comp", "shingles")
    outer = materialize(queries.union(members).groupBy("slot").applyInArrow(across, "a long, b long"), "outer")
    release(spark)
    chains = labels.select(F.col("node").alias("a"), F.col("label").alias("b"))
    final = components(outer.union(chains)).select(F.col("node").alias("_gl_n"), F.col("label").alias("_gl_label"))
    discard(sets, inner, routes, routed, asks, passed)
    with_class = known.join(reps.select(F.col("d1").alias("_gl_1"), F.col("d2").alias("_gl_2"), F.col("_gl_rep").alias("class_id")), (F.col("d1") == F.col("_gl_1")) & (F.col("d2") == F.col("_gl_2")) & (F.col("n_shingles") > 0), "left")
    return with_class.join(final, F.col("class_id") == F.col("_gl_n"), "left").select(
        "doc_id", "n_shingles", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("_gl_label", "class_id", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """One document of each component, that of the smallest doc_id; rows without doc_id or words stay."""
    docs, back = aside(docs, "doc_id", "text")
    found = similarity_components(docs, width, percent)
    extra = found.where("n_shingles > 0 and doc_id <> component_id").select(F.col("doc_id").alias("_gl_gone")).distinct()
    return back(docs.join(extra, F.col("doc_id") == F.col("_gl_gone"), "left_anti"))
