"""Texts are not shuffled to be told apart by a list of ids, however Spark judges the list's size."""

from pyspark.sql import functions as F

from driftview.llm import near_dup


def test_documents_that_others_represent_are_left_out_in_place(spark):
    docs = spark.range(1000).select(F.col("id").alias("doc_id"), F.lit("a text").alias("text"))
    classes = docs.select("doc_id", (F.col("doc_id") - F.col("doc_id") % 4).alias("class_id"))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        kept = near_dup.keep_one(docs, classes)
        plan = kept._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastHashJoin" in plan and "hashpartitioning" not in plan
        assert [r[0] for r in kept.select("doc_id").orderBy("doc_id").collect()] == list(range(0, 1000, 4))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_longer_lists_are_joined_all_the_same(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "BROADCAST_PAIRS", 10)
    docs = spark.range(1000).select(F.col("id").alias("doc_id"), F.lit("a text").alias("text"))
    classes = docs.select("doc_id", (F.col("doc_id") - F.col("doc_id") % 4).alias("class_id"))
    assert near_dup.keep_one(docs, classes).count() == 250
