import datetime as dt
import random

import pytest
from pyspark.sql import functions as F

from driftview.functions import features as fx
from driftview.operators.asof import asof_join
from driftview.plans.declare import run_statement
from driftview.queries_sql import TermCounts
from driftview.session import shared_path
from driftview.streaming.attach import running_waste


@pytest.mark.parametrize("seconds", [3600, 10**9])
def test_as_of_join_against_brute_force(spark, seconds):
    rng, zero = random.Random(4), dt.datetime(2024, 1, 1)
    at = lambda: zero + dt.timedelta(seconds=rng.randrange(40_000))
    left = [(k, rng.choice(["hot", "hot", "b", "c", None]), at() if k % 9 else None) for k in range(200)] + [(500, "hot", zero), (500, "hot", zero)]
    right = [(rng.choice(["hot", "b", None]), at(), rng.choice([1.0, 2.0, None])) for k in range(120)] + [("hot", zero, 3.0), ("hot", zero, 4.0)]
    a = spark.createDataFrame(left, "id long, who string, ts timestamp")
    b = spark.createDataFrame(right, "who string, ts timestamp, v double")

    def last(who, t):
        rows = [(x, v is not None, v or 0.0) for w, x, v in right if who is not None and t is not None and w == who and x <= t]
        return (max(rows)[2] if max(rows)[1] else None) if rows else None

    key = lambda r: tuple(str(x) for x in r)
    got = sorted(((r["id"], r["who"], r["v_asof"]) for r in asof_join(a, b, "who", "ts", ["v"], bucket_seconds=seconds).collect()), key=key)
    assert got == sorted(((k, w, last(w, t)) for k, w, t in left), key=key)
    assert asof_join(a, b.limit(0), "who", "ts", ["v"]).where("v_asof is not null").count() == 0
    assert asof_join(a.limit(0), b, "who", "ts", ["v"]).count() == 0


def test_approximate_distinct_and_quantiles(spark):
    rows = spark.range(50_000).select((F.col("id") % 7000).alias("k"), (F.col("id") * 37 % 50_000).alias("x"))
    n, q = rows.agg(F.approx_count_distinct("k", 0.02), F.percentile_approx("x", 0.25, 10_000)).first()
    assert abs(n - 7000) < 500 and abs(q - 12_500) < 50


def test_running_waste_over_batches(spark):
    rng = random.Random(2)
    rows = [(k % 3, k, rng.random() * 10 if k % 11 else None) for k in range(90)]
    path = shared_path(spark, "costs")
    for lo in range(0, 90, 30):
        spark.createDataFrame(rows[lo : lo + 30], "key long, seq long, cost double").coalesce(1).write.mode("append").parquet(path)
    out = shared_path(spark, "waste")
    stream = spark.readStream.schema("key long, seq long, cost double").option("maxFilesPerTrigger", 1).parquet(path)
    running_waste(stream, 25.0).writeStream.option("checkpointLocation", shared_path(spark, "cp")).trigger(availableNow=True).format("parquet").start(out).awaitTermination()
    got = {(r["key"], r["seq"]): (r["waste"], r["reclusters"]) for r in spark.read.parquet(out).collect()}
    for key in range(3):
        waste, bought = 0.0, 0
        for k, seq, cost in rows:
            if k == key:
                waste, bought = (0.0, bought + 1) if waste >= 25.0 else (waste + (cost or 0.0), bought)
                assert got[key, seq] == (pytest.approx(waste), bought)


def test_table_function_of_terms(spark):
    spark.udtf.register("terms_of", TermCounts)
    rows = spark.sql("SELECT t.* FROM VALUES ('The cat the hat'), (NULL), ('') AS d(x), LATERAL terms_of(x) t").collect()
    assert [(r["term"], r["n"]) for r in rows] == [("cat", 1), ("hat", 1), ("the", 2)]


def test_kernels_by_declaration(spark):
    rng = random.Random(1)
    rows = [(k, rng.uniform(-1, 1), rng.uniform(-1, 1)) for k in range(300)]
    spark.createDataFrame(rows, "id long, a double, b double").createOrReplaceTempView("ring")
    spark.createDataFrame([(k, "in" if a * a + b * b < 0.5 else "out") for k, a, b in rows], "id long, kind string").createOrReplaceTempView("ring_marks")
    spark.createDataFrame([("in",), ("out",)], "kind string").createOrReplaceTempView("ring_kinds")
    text = "DEFINE MODEL VIEW ring_view OVER ring KEY id LABELS ring_kinds(kind) EXAMPLES ring_marks(id, kind) FEATURES {}(a, b) USING svm"
    truth = {k: a * a + b * b >= 0.5 for k, a, b in rows}
    share = {}
    for kernel in ("dense_columns", "polynomial_kernel", "gaussian_kernel"):
        view = run_statement(spark, text.format(kernel))
        share[kernel] = sum((r["class"] == 1) == truth[r["id"]] for r in view.view().collect()) / 300
    assert share["polynomial_kernel"] > share["dense_columns"] + 0.1 and share["gaussian_kernel"] > share["dense_columns"] + 0.1


def test_a_method_is_chosen_for_sparse_texts(spark, data):
    spark.read.parquet(f"{data}/documents.parquet").createOrReplaceTempView("chosen_docs")
    spark.sql("SELECT doc_id AS id, lang = 'en' AS english FROM chosen_docs").createOrReplaceTempView("chosen_marks")
    spark.sql("SELECT DISTINCT english FROM chosen_marks").createOrReplaceTempView("chosen_kinds")
    view = run_statement(spark, "DEFINE MODEL VIEW chosen OVER chosen_docs KEY doc_id LABELS chosen_kinds(english) EXAMPLES chosen_marks(id, english) FEATURES tf_bag_of_terms(text, dim=4096)")
    assert view.trainer.loss in ("hinge", "logistic")


def test_hashes_of_terms(spark):
    row = spark.sql("SELECT 'cat' AS t").select(fx.slot(F.col("t"), 100, "md5").alias("a"), fx.slot(F.col("t"), 100).alias("b")).first()
    assert row["a"] == int("d077f244", 16) % 100 and 0 <= row["b"] < 100
