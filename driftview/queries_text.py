"""The text experiments: short and whole texts, an examples table, raw counts, cold starts and lazy reads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.operators import measures
from driftview.operators.band import HolderPair
from driftview.operators.baselines import NaiveView
from driftview.operators.view import ClassificationView, Options
from driftview.plans import replay, workloads
from driftview.queries import TECHNIQUES, _start
from driftview.registry import query


def _run(w: workloads.Workload, each: int = 8, **options: object) -> ClassificationView:
    view, rest = _start(w, w.kept_entities(), buckets=8, **options)
    each = max(each, len(rest) // 10)
    for k in range(0, len(rest), each):
        view.update(rest[k : k + each])
    return view


def _titles(spark: SparkSession, sf_dir: str) -> workloads.Workload:
    return workloads.text_language(spark, sf_dir, 7, **workloads.IN_SQL)


def _texts(spark: SparkSession, sf_dir: str, norm: str | None = "l2") -> workloads.Workload:
    return workloads.text_language(spark, sf_dir, None, norm, **workloads.IN_SQL)


@query
def title_view_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(_titles(spark, sf_dir)).view()


@query
def title_view_hybrid(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _run(_titles(spark, sf_dir), arch="hybrid", policy="lazy")
    return view.label_of_many(view.entities.select("id")).select("id", "class")


@query
def text_view_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(_texts(spark, sf_dir)).view()


@query
def text_view_slim(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(_texts(spark, sf_dir), layout="slim", refine=True).view()


@query
def text_lazy_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _run(_texts(spark, sf_dir), policy="lazy")
    return spark.createDataFrame([(c, view.count_members(c)) for c in (1, -1)], "class int, n long")


@query
def text_cold_start(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = _texts(spark, sf_dir)
    view = ClassificationView(w.kept_entities(), w.trainer, w.dim, Options(buckets=8))
    batch = w.batch()
    for k in range(0, len(batch), 25):
        view.update(batch[k : k + 25])
    return view.view()


@query
def text_raw_counts_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Word counts as they are: norms are large, bands wide, and the view is right all the same."""
    return _run(_texts(spark, sf_dir, None)).view()


@query
def quality_labels_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.text_quality(spark, sf_dir, **workloads.IN_SQL).learn_all(8, buckets=8).view()


@query
def toxic_labels_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.text_quality(spark, sf_dir, **workloads.IN_SQL, label="toxic").learn_all(8, buckets=8).view()


@query
def text_band_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows in the band for each round since the warm model, of texts normalized and not."""
    out = []
    for name, norm in (("l2", "l2"), ("raw", None)):
        w = _texts(spark, sf_dir, norm)
        entities, models = w.kept_entities(), w.trail()
        largest = vectors.max_norm(entities, 2)
        out += [(name, b.round, b.n_band) for b in replay.band_counts(entities, models, 0, largest, HolderPair())[1:]]
    return spark.createDataFrame(out, "norm string, round int, n_band long")


@query
def text_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of keys, margins and vectors (4 a slot, 8 a value), with a buffer of 1 %."""
    out = None
    for name, w in (("title7", _titles(spark, sf_dir)), ("full_text", _texts(spark, sf_dir))):
        sums = w.entities.agg(F.count("*").alias("n"), F.sum(12 * F.size("f.idx")).cast("long").alias("vectors"))
        rows = sums.select(F.lit(name).alias("dataset"), "n", (16 * F.col("n")).alias("margin_map"), "vectors", F.round((8 * F.col("n") + F.col("vectors")) / (16 * F.col("n")), 6).alias("ratio"))
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def text_technique_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wrong rows of every technique, policy and operation over short and whole texts: 60 cells, all 0."""
    rows = []
    for dataset, w in (("title7", _titles(spark, sf_dir)), ("full_text", _texts(spark, sf_dir))):
        entities, batch = w.kept_entities(), w.batch()
        warm = w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim)
        ids = workloads.random_ids(entities, 300)
        for policy in ("eager", "lazy"):
            for technique in TECHNIQUES:
                kind, _, arch = technique.partition("_")
                view = NaiveView(entities, w.trainer, warm, policy, arch) if kind == "naive" else ClassificationView(entities, w.trainer, w.dim, Options(policy=policy, arch=arch or "hybrid", buckets=4), warm)
                view.update(batch[w.warm : w.warm + 20])
                view.update(batch[w.warm + 20 :])
                exact = entities.select("id", vectors.sign_class(vectors.score(entities, view.model)).cast("int").alias("class"))
                single = view.label_of_many(ids).select("id", "class").join(exact.withColumnRenamed("class", "truth"), "id").where("class <> truth")
                members = view.all_members(1).exceptAll(exact.where("class = 1").select("id")).unionByName(exact.where("class = 1").select("id").exceptAll(view.all_members(1)))
                for operation, wrong in (("update", measures.diff_with_exact(view.view(), exact)), ("single", single), ("all", members)):
                    rows.append((dataset, technique, policy, operation, wrong.count()))
                view.close()
    return spark.createDataFrame(rows, "dataset string, technique string, policy string, operation string, n_wrong long")
