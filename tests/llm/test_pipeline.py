import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from driftview.llm import decontaminate, lines, mixing, near_dup, queries, toxicity


def test_stages_against_their_operators(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    bench, labels = (spark.read.parquet(f"{data}/{t}.parquet") for t in ("benchmark", "labels"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "near_dup", "decontamination", "mixing"]
    kept = docs
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        before = kept
        kept = stage(spark, before, data).cache()
        ids = {r[0] for r in before.select("doc_id").collect()}
        left = {r[0] for r in kept.select("doc_id").collect()}
        assert left <= ids and len(left) == kept.count()
        if k < 4:
            assert kept.columns == docs.columns
        if k == 0:
            assert ids - left == {r["doc_id"] for r in toxicity.toxicity(before, labels).collect() if r["predicted"]}
        if k == 1:
            assert left == ids
            texts = {r["doc_id"]: r["text"] for r in lines.drop_shared_lines(before).collect()}
            assert all(texts[r["doc_id"]] == r["text"] and r["n_chars"] == len(r["text"]) for r in kept.collect())
        if k == 2:
            assert left == {r["class_id"] for r in near_dup.near_duplicates(before).collect()}
        if k == 3:
            assert ids - left == {r["doc_id"] for r in decontaminate.contamination(before, bench).collect()}
        if k == 4:
            taken = {r["doc_id"]: r["taken"] for r in mixing.fair_mix(before).collect()}
            assert {r["doc_id"]: r["taken"] for r in kept.collect()} == {d: t for d, t in taken.items() if t}


def test_run_and_registration(spark, data):
    assert corpus_pipeline.run(spark, data).count() > 0
    names = queries.queries()
    assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)) and "pipeline" in names


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages_on_odd_rows(spark, data, odd, name):
    stage = dict(corpus_pipeline.STAGES)[name]
    clashing = odd.select("*", F.lit("s").alias("Size"), F.lit(1).alias("target"), F.lit(2).alias("__rejected_"), F.lit(3).alias("line_counts"))
    kept = stage(spark, clashing, data)
    added = ["size_", "target_", "taken"] if name == "mixing" else []
    assert kept.columns == clashing.columns + added
    rows = kept.collect()
    # rows with a null id stay, and of the others those with words of their own
    assert [r["text"] for r in rows if r["doc_id"] is None] == ["no id here"]
    assert {3, 4, 6} <= {r["doc_id"] for r in rows}
    assert sum(r["doc_id"] == 4 for r in rows) == (1 if name == "near_dup" else 2)
    assert stage(spark, clashing.limit(0), data).collect() == []


def test_rows_without_an_id_are_mixed_each_by_its_own_size(spark, data, frame):
    docs = frame([(None, "a b c"), (None, "a b c d e"), (1, "x"), (1, "x y"), (2, None)])
    rows = corpus_pipeline.mixed(spark, docs, data).collect()
    assert sorted((r["doc_id"] or 0, r["size"], r["taken"]) for r in rows) == [(0, 3, 3), (0, 5, 5), (1, 1, 1), (1, 2, 2)]
