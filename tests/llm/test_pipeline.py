"""The pipeline, stage by stage, against brute force on small tables in a folder of its own."""

import random

import pytest
from test_operators import WORD, brute_components, brute_hits, brute_lines, labelled, text

import corpus_pipeline
from gistloom.llm import toxicity


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    root = tmp_path_factory.mktemp("tables")
    docs, labels = labelled(spark)
    rng = random.Random(8)
    passage = "\n".join(text(rng, 12) for _ in range(5))
    items = [(k, text(rng, 30, 30)) for k in range(4)]
    more = []
    for k in range(12):
        more.append((2000 + k, text(rng, 40) + "\n" + passage + "\n" + text(rng, 20), "en", f"s{k % 3}", 0, ""))
    near = text(rng, 120, 120).split(" ")
    for k in range(5):
        v = list(near)
        v[10 * k] = "other"
        more.append((3000 + k, " ".join(v), "en", "s1", 0, ""))
    more += [(4000 + k, text(rng, 15, 15) + " " + t, "en", None, 0, "") for k, t in items]
    more += [(5000, None, "en", "s0", 0, ""), (5001, "", "en", "s0", 0, ""), (5002, more[0][1], "en", "s0", 0, "")]
    docs.unionByName(spark.createDataFrame(more, docs.schema)).write.parquet(f"{root}/documents.parquet")
    labels.write.parquet(f"{root}/labels.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{root}/benchmark.parquet")
    return str(root), items


def test_every_stage(spark, tables):
    root, items = tables
    docs = spark.read.parquet(f"{root}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{root}/labels.parquet"))
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text for r in docs.collect()}
        columns = docs.columns
        path = f"{root}/out-{name}"
        stage(spark, docs, root).write.parquet(path)
        docs = spark.read.parquet(path)
        after = {r.doc_id: r.text for r in docs.collect()}
        if name == "toxicity":
            ids = sorted(before)
            bad = {i for i, p in zip(ids, model.proba([before[i] or "" for i in ids]), strict=True) if p >= 0.7}
            assert bad and after == {i: t for i, t in before.items() if i not in bad}
        elif name == "line_dedup":
            gone = brute_lines(list(before.items()), 10)
            want = {i: (t if i not in gone else "\n".join(x for p, x in enumerate(t.split("\n")) if p not in set(gone[i]))) for i, t in before.items()}
            assert gone and after == {i: t for i, t in want.items() if i not in gone or WORD.search(t)}
        elif name == "ngram_jaccard":
            want = brute_components(list(before.items()), 5, 80)
            assert set(after) == {i for i, (n, c) in want.items() if n == 0 or i == c} < set(before)
        elif name == "decontamination":
            assert set(after) == {i for i, t in before.items() if not brute_hits(t, items)[4]} < set(before)
        else:
            rows = docs.collect()
            assert set(after) <= set(before) and all(r.mix_taken > 0 and r.mix_copies in (1, 2, 3) and 0 <= r.mix_position <= 1 for r in rows)
            total = sum(len(WORD.findall(t or "")) for t in before.values())
            assert abs(sum(r.mix_taken for r in rows) - total) <= 4
        if name != "source_mix":
            assert docs.columns == columns
