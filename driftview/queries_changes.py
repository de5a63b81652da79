"""Views whose entities change, views that start cold, and views of several classes."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions import features as fx
from driftview.functions import vectors
from driftview.learn import multiclass
from driftview.learn.model import Model
from driftview.operators.multiclass_view import MulticlassView, gather_labels, lead_lost, train
from driftview.operators.policy import best_by_sigma, best_schedule, ratio_bound, schedule_cost, simulate
from driftview.operators.view import ClassificationView, Options
from driftview.plans import workloads
from driftview.plans.declare import run_statement
from driftview.queries import CLASSES, SIGMA, _costs, _start
from driftview.registry import query
from driftview.session import materialize
from driftview.sources.tables import table


def _named(view: ClassificationView) -> ClassificationView:
    """A view under a name of its own in the session."""
    view.name = f"view_{uuid.uuid4().hex[:8]}"
    view.publish()
    return view


def _longer(rows: DataFrame) -> DataFrame:
    return rows.select("id", F.transform("f", lambda x: x * 2).alias("f"))


@query
def deleted_entities_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The view by name, right after entities were removed."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w)
    _named(view).update(rest[:20])
    view.delete_entities(w.entities.where("id % 7 = 3").select("id"))
    return spark.table(view.name)


@query
def lazy_arrivals_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A lazy view by name, right after a tenth of the entities arrived."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w, w.entities.where("id % 10 <> 9"), policy="lazy")
    _named(view).update(rest[:16])
    view.add_entities(_longer(w.entities.where("id % 10 = 9")))
    return spark.table(view.name)


@query
def readded_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities leave, and come back with vectors twice as long."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w)
    view.update(rest[:20])
    view.delete_entities(w.entities.where("id % 7 = 3").select("id"))
    view.update(rest[20:30])
    view.add_entities(_longer(w.entities.where("id % 7 = 3")))
    view.update(rest[30:])
    return view.view()


@query
def nan_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every eleventh row has a value that is not a number: such rows are set aside, and the rest is right."""
    w = workloads.planted_lineitem(spark, sf_dir)
    odd = w.entities.select("id", F.when(F.col("id") % 11 == 5, F.transform("f", lambda x, k: F.when(k == 1, F.lit(float("nan"))).otherwise(x))).otherwise(F.col("f")).alias("f"))
    view, rest = _start(w, odd)
    for k in range(0, len(rest), 8):
        view.update(rest[k : k + 8])
    return view.view()


@query
def cold_start_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view that knows no example at first; all of them come as updates."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view = ClassificationView(w.entities, w.trainer, w.dim)
    batch = w.batch()
    for k in range(0, len(batch), 20):
        view.update(batch[k : k + 20])
    return view.view()


@query
def competitive_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rule's cost over the best schedule's in hindsight, over ten rounds, beside the bound that holds for any costs."""
    costs, whole = _costs(spark, sf_dir, 10)
    rows = []
    for share in (0.05, 0.1, 0.25, 1.0):
        s = whole * share
        best, rule = best_schedule(costs, s)[0], schedule_cost(costs, s, simulate(costs, s))
        rows.append((share, round(rule / best, 6), round(ratio_bound(SIGMA / share, 1.0), 6)))
    return spark.createDataFrame(rows, "share double, ratio double, bound double")


@query
def alpha_by_sigma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best alpha and its ratio for each order, of which a scan reads the largest line and a reclustering writes all: with many lines they tend to 1 and 2."""
    total = F.sum("l_quantity")
    orders = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.when(total > 0, F.max("l_quantity") / total).alias("s"))
    alpha, ratio = best_by_sigma(F.col("s"))
    return orders.select("l_orderkey", F.round("s", 6).alias("sigma"), F.round(alpha, 6).alias("alpha"), F.round(ratio, 6).alias("ratio"))


# --- several classes


def _flag_batch(spark: SparkSession, sf_dir: str) -> tuple[workloads.Workload, list]:
    """The dense workload with the return flag as the label, and its examples."""
    w = workloads.planted_lineitem(spark, sf_dir)
    source = w.source.withColumn("label", F.col("l_returnflag"))
    examples = source.select("id", "label").orderBy("id").limit(w.warm + w.measured)
    rows = w.feature.transform(source.join(F.broadcast(examples.select("id")), "id", "left_semi"), "id")
    return w, gather_labels(rows, examples)


def _classes_run(spark: SparkSession, sf_dir: str, **options: object) -> MulticlassView:
    w, batch = _flag_batch(spark, sf_dir)
    warm = train(w.trainer, [Model.zero(w.dim)] * len(CLASSES), batch[: w.warm], CLASSES)
    view = MulticlassView(w.entities, w.trainer, w.dim, CLASSES, Options(**options), warm)
    for k in range(w.warm, len(batch), 8):
        view.update(batch[k : k + 8])
    return view


@query
def multiclass_view_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classes_run(spark, sf_dir).view()


@query
def multiclass_view_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classes_run(spark, sf_dir, arch="memory").view()


@query
def multiclass_view_lazy(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _classes_run(spark, sf_dir, policy="lazy")
    return spark.createDataFrame([(c, view.count_members(c)) for c in CLASSES], "class string, n long")


@query
def multiclass_band_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows whose lead does not settle their class, for each round since the warm models: one scan."""
    w, batch = _flag_batch(spark, sf_dir)
    stored = train(w.trainer, [Model.zero(w.dim)] * len(CLASSES), batch[: w.warm], CLASSES)
    entities = w.entities
    largest = float(vectors.max_norm(entities, 2))
    lost, rounds, models = np.full(len(CLASSES), -np.inf), [], stored
    for e in batch[w.warm :]:
        models = train(w.trainer, models, [e], CLASSES)
        lost = np.maximum(lost, lead_lost(stored, models, largest, 2.0))
        rounds.append(lost.tolist())
    scores = entities.select(multiclass.scores(entities, stored).alias("scores"))
    ordered = F.sort_array("scores", asc=False)
    rows = scores.select((ordered[0] - ordered[1]).alias("lead"), F.array_position("scores", F.array_max("scores")).cast("int").alias("leader"))
    sums = [F.count_if(F.col("lead") <= F.element_at(F.lit(x), F.col("leader"))).alias(f"n{k}") for k, x in enumerate(rounds, 1)]
    got = rows.agg(*sums).first()
    return spark.createDataFrame([(k, got[f"n{k}"]) for k in range(1, len(rounds) + 1)], "round int, n_band long")


@query
def multiclass_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten classes over unit vectors, maintained over all updates."""
    w = workloads.embeddings_binary(spark, sf_dir)
    labels = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "label")
    batch = gather_labels(w.entities, labels.orderBy("id").limit(w.warm + w.measured))
    classes = list(range(10))
    view = MulticlassView(w.entities, w.trainer, w.dim, classes, Options(buckets=8), train(w.trainer, [Model.zero(w.dim)] * 10, batch[: w.warm], classes))
    for k in range(w.warm, len(batch), 20):
        view.update(batch[k : k + 20])
    return view.view()


@query
def multiclass_languages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Right and wrong documents by language, of a maintained view of four classes over whole texts."""
    w = workloads.text_language(spark, sf_dir, **workloads.IN_SQL)
    entities = materialize(w.entities, "languages")
    truth = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    batch = gather_labels(entities, truth.orderBy("id").limit(w.warm + w.measured))
    classes = ["de", "en", "es", "fr"]
    view = MulticlassView(entities, w.trainer, w.dim, classes, Options(buckets=8), train(w.trainer, [Model.zero(w.dim)] * 4, batch[: w.warm], classes))
    for k in range(w.warm, len(batch), 20):
        view.update(batch[k : k + 20])
    return view.view().join(truth, "id").groupBy("label", "class").agg(F.count("*").alias("n"))


@query
def declared_multiclass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view over three labels, declared in text."""
    w = workloads.planted_lineitem(spark, sf_dir)
    name = f"flags_{uuid.uuid4().hex[:8]}"
    w.source.createOrReplaceTempView(f"{name}_items")
    w.source.select("id", F.col("l_returnflag").alias("flag")).orderBy("id").limit(w.warm + w.measured).createOrReplaceTempView(f"{name}_examples")
    w.source.select(F.col("l_returnflag").alias("kind")).distinct().createOrReplaceTempView(f"{name}_labels")
    fx.register_feature("scaled_prices", lambda: fx.DenseColumns(*workloads.LINEITEM))
    run_statement(spark, f"DEFINE MODEL VIEW {name} OVER {name}_items KEY id LABELS {name}_labels(kind) EXAMPLES {name}_examples(id, flag) FEATURES scaled_prices() USING svm")
    return spark.table(name)
