"""Every method, variant, baseline, measure and workload as a query over the given tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions import features as fx
from driftview.functions import vectors
from driftview.learn import closed_form, multiclass, select
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators import measures
from driftview.operators.band import HolderPair, in_band, water_marks
from driftview.operators.baselines import FullRetrain, NaiveView, batch_solver
from driftview.operators.policy import best_schedule, fixed_rule, monotonicity_report, run_policy, schedule_cost, simulate
from driftview.operators.store import band_distance
from driftview.operators.view import ClassificationView, Options, gather
from driftview.plans import replay, workloads
from driftview.plans.declare import run_statement
from driftview.registry import ALL, Query, query
from driftview.session import materialize, shared_path
from driftview.sources.tables import keyed_lineitem, strip_tags, table
from driftview.streaming.attach import attach_stream, user_sessions, user_windows, window_vector

#: Rounds of a policy's replay, and what a scan costs over a recluster in the rows clock.
SIGMA = 0.25


def queries() -> dict[str, Query]:
    from driftview import queries_changes, queries_sql, queries_text  # noqa: F401, PLC0415  they use what is defined here

    return dict(ALL)


# --- features


@query
def tf_bag_of_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = fx.TermFrequency("text", norm="l1").long_form(table(spark, sf_dir, "documents"), "doc_id")
    return rows.select("id", "term", F.round("val", 9).alias("val"))


@query
def title7_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.TermFrequency("text", norm=None, first_tokens=7).long_form(table(spark, sf_dir, "documents"), "doc_id")


@query
def tfidf_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = fx.TfIdf.long_form(table(spark, sf_dir, "documents"), "doc_id", "text")
    return rows.select("id", "term", F.round("val", 6).alias("val"))


@query
def page_text_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").withColumn("body", strip_tags(F.col("html")))
    return fx.TermFrequency("body", norm=None).long_form(pages, "page_id")


@query
def onehot_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fx.OneHot(("p_brand", "p_type", "p_size")).long_form(table(spark, sf_dir, "part"), "p_partkey")


@query
def dense_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for w in (workloads.planted_lineitem(spark, sf_dir), workloads.embeddings_binary(spark, sf_dir)):
        norms = [F.round(F.max(vectors.norm(F.col("f"), q)), 6).alias(n) for n, q in (("m1", 1), ("m2", 2), ("minf", float("inf")))]
        rows = w.entities.agg(F.lit(w.name).alias("dataset"), *norms)
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def text_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest norms of word counts as they are, and over their sum or length: why texts are normalized."""
    counts = fx.TermFrequency("text", norm=None).long_form(table(spark, sf_dir, "documents"), "doc_id")
    per = counts.groupBy("id").agg(F.sum("val").alias("l1"), F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("l2"), F.max("val").alias("linf"))
    return per.agg(F.round(F.max("l2"), 6).alias("raw_l2"), F.round(F.max(F.col("l2") / F.col("l1")), 6).alias("l1_l2"), F.round(F.max(F.col("linf") / F.col("l1")), 6).alias("l1_linf"), F.round(F.max(F.col("linf") / F.col("l2")), 6).alias("l2_linf"))


@query
def polynomial2_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.planted_lineitem(spark, sf_dir)
    f = F.col("f")
    rows = fx.Polynomial2(w.feature).transform(w.source, "id")
    return rows.select("id", F.size(f).alias("dim"), F.round(f[5], 6).alias("f0f1"), F.round(f[13], 6).alias("f3f3"), F.round(vectors.norm(f, 1), 6).alias("total"))


#: Rows with which the Fourier map's products are compared, and its dimensions.
ANCHORS, COSINES = 8, 64


@query
def random_fourier_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and largest error of the map's products against the kernel, of all rows with the first ANCHORS."""
    w = workloads.planted_lineitem(spark, sf_dir)
    return fx.kernel_error(w.feature, fx.RandomFourier(w.feature, dim=COSINES, gamma=1.0), w.source, "id", ANCHORS)


@query
def dataset_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    dense = [workloads.planted_lineitem(spark, sf_dir), workloads.embeddings_binary(spark, sf_dir)]
    out = measures.dataset_stats(dense[0].entities, dense[0].name).unionByName(measures.dataset_stats(dense[1].entities, dense[1].name))
    for name, first in (("title7", 7), ("full_text", None)):
        terms = fx.TermFrequency("text", norm=None, first_tokens=first).long_form(table(spark, sf_dir, "documents"), "doc_id")
        per = terms.groupBy("id").agg(F.count("*").alias("nz"))
        documents = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")).join(per, "id", "left").agg(F.count("*").alias("n_entities"), F.round(F.avg(F.coalesce("nz", F.lit(0))), 6).alias("mean_nonzero"))
        vocabulary = terms.agg(F.count_distinct("term").alias("n_features"))
        out = out.unionByName(documents.crossJoin(vocabulary).select(F.lit(name).alias("dataset"), "n_entities", "n_features", "mean_nonzero"))
    return out


# --- training


def _trail_frame(spark: SparkSession, models: list[Model]) -> DataFrame:
    rows = [(k, *[round(x, 6) + 0.0 for x in m.w.tolist()], round(float(m.b), 6) + 0.0) for k, m in enumerate(models)]
    return spark.createDataFrame(rows, "round int, w0 double, w1 double, w2 double, w3 double, b double")


def _sgd_trail(spark: SparkSession, sf_dir: str, loss: str) -> DataFrame:
    return _trail_frame(spark, workloads.planted_lineitem(spark, sf_dir, SgdTrainer(loss, 0.1, 0.05)).trail())


@query
def sgd_trail_hinge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sgd_trail(spark, sf_dir, "hinge")


@query
def sgd_trail_logistic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sgd_trail(spark, sf_dir, "logistic")


@query
def sgd_trail_squared(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sgd_trail(spark, sf_dir, "squared")


def _one_feature(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = keyed_lineitem(spark, sf_dir)
    return rows.select(F.col("ent_id").alias("id"), (F.col("l_extendedprice") / 105000.0).alias("x"), F.col("label"), F.when(F.col("label") > 0, 1.0).otherwise(2.0).alias("weight"))


@query
def least_squares_fits(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _one_feature(spark, sf_dir)
    fits = [("ols", closed_form.normal_equations(rows, ["x"], "label")), ("ridge", closed_form.normal_equations(rows, ["x"], "label", l2=10.0)), ("weighted", closed_form.normal_equations(rows, ["x"], "label", weight="weight"))]
    return spark.createDataFrame([(n, round(float(m.w[0]), 6), round(m.b, 6)) for n, m in fits], "method string, w double, b double")


@query
def loo_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of all rows, each under the least-squares model trained without it."""
    rows = closed_form.press_rows(_one_feature(spark, sf_dir), ["x"], "label")
    return rows.select("id", F.round("score", 6).alias("score"))


@query
def loo_errors_by_method(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leave-one-out errors of least squares and ridge over all rows, in closed form: two passes each."""
    rows = _one_feature(spark, sf_dir)
    out = None
    for name, l2 in (("ols", 0.0), ("ridge", 10.0)):
        scored = closed_form.press_rows(rows, ["x"], "label", l2)
        wrong = F.when(F.when(F.col("score") >= 0, 1).otherwise(-1) != F.col("label"), 1).otherwise(0)
        errors = scored.agg(F.lit(name).alias("method"), F.count("*").alias("n"), F.sum(wrong.cast("long")).alias("n_wrong"))
        out = errors if out is None else out.unionByName(errors)
    return out


@query
def loo_by_retraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leave-one-out errors of the gradient methods over all examples, each left out in turn."""
    batch = [(f, y) for _, f, y in workloads.planted_lineitem(spark, sf_dir).batch()]
    rows = [(name, len(batch), round(error * len(batch))) for name, error in select.loo_errors(batch, 4, ("svm", "logistic"))]
    return spark.createDataFrame(rows, "method string, n long, n_wrong long")


@query
def method_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All methods by their leave-one-out error over all examples."""
    return select.select_method(spark, [(f, y) for _, f, y in workloads.planted_lineitem(spark, sf_dir).batch()], 4)


@query
def hinge_loo_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The leave-one-out error of a support vector machine over all examples, by retraining, and its bound from one fit."""
    batch = workloads.planted_lineitem(spark, sf_dir).batch()
    x, y = np.array([f for _, f, _ in batch]), np.array([float(t) for *_, t in batch])
    exact = closed_form.loo_bruteforce(lambda a, b: _dual_model(a, b), x, y)
    return spark.createDataFrame([(float(exact), closed_form.loo_hinge_bound(x, y))], "exact double, bound double")


def _dual_model(x: np.ndarray, y: np.ndarray) -> Model:
    _, w = closed_form.dual_hinge(x, y)
    return Model(w[:-1], -float(w[-1]))


# --- the view: eager


def _run(spark: SparkSession, sf_dir: str, each: int = 8, **options: object) -> ClassificationView:
    """A view of the dense workload after all its updates, in batches."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w, **options)
    for k in range(0, len(rest), each):
        view.update(rest[k : k + each])
    return view


def _start(w: workloads.Workload, entities: DataFrame | None = None, **options: object) -> tuple[ClassificationView, list]:
    batch = w.batch()
    model = Model.zero(w.dim)
    for _, f, y in batch[: w.warm]:
        model = w.trainer.step(model, f, y)
    view = ClassificationView(w.entities if entities is None else entities, w.trainer, w.dim, Options(**options), model)
    view.examples = batch[: w.warm]
    return view, batch[w.warm :]


@query
def eager_view_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir).view()


@query
def eager_view_pairwise(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, band="pairwise").view()


@query
def eager_view_linf_l1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, pair=HolderPair.for_norm("l1")).view()


@query
def eager_view_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, arch="memory").view()


@query
def eager_view_slim_refined(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, layout="slim", refine=True).view()


@query
def naive_eager_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.planted_lineitem(spark, sf_dir)
    batch = w.batch()
    naive = NaiveView(w.entities, w.trainer, w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim))
    for k in range(w.warm, len(batch), 20):
        naive.update(batch[k : k + 20])
    return naive.view()


@query
def naive_lazy_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.embeddings_binary(spark, sf_dir)
    batch = w.batch()
    naive = NaiveView(w.entities, w.trainer, w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim), "lazy")
    naive.update(batch[w.warm :])
    return naive.view()


@query
def full_retrain_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every fifth example deleted and every seventh of all given the other class: training starts anew."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w)
    view.update(rest)
    order = [k for k, *_ in w.batch()]
    labels = {k: y for k, _, y in w.batch()}
    view.delete_examples([k for n, k in enumerate(order, 1) if n % 5 == 0])
    view.relabel({k: -labels[k] for n, k in enumerate(order, 1) if n % 7 == 0 and n % 5})
    return view.view()


@query
def full_retrain_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.planted_lineitem(spark, sf_dir)
    batch = w.batch()
    naive = FullRetrain(w.entities, w.trainer, w.dim, batch[: w.warm])
    naive.update(batch[w.warm :])
    return naive.view()


def _trailed(spark: SparkSession, sf_dir: str) -> tuple[workloads.Workload, DataFrame, list[Model], float, int]:
    """The dense workload, its entities, its models, the largest norm and the number of entities."""
    w = workloads.planted_lineitem(spark, sf_dir)
    entities = w.entities
    n, largest = entities.agg(F.count("*"), F.max(vectors.norm(F.col("f"), 2))).first()
    return w, entities, w.trail(), float(largest), n


@query
def eager_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, *_ = _trailed(spark, sf_dir)
    return replay.round_classes(entities, models)


@query
def water_marks_by_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, _, models, largest, _ = _trailed(spark, sf_dir)
    rows = [(j, *[round(float(x), 6) + 0.0 for x in rest]) for j, *rest in water_marks(models, 0, largest, 2.0)]
    return spark.createDataFrame(rows, "round int, low double, high double, lw double, hw double")


@query
def band_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, largest, _ = _trailed(spark, sf_dir)
    return spark.createDataFrame([(b.round, b.n_band, b.n_above) for b in replay.band_counts(entities, models, 0, largest, HolderPair())], "round int, n_band long, n_above long")


@query
def sandwich_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, certain, possible) of the positive class at the last round, of entities that may be in it."""
    _, entities, models, largest, _ = _trailed(spark, sf_dir)
    *_, lw, hw = water_marks(models, 0, largest, 2.0)[-1]
    eps = entities.select("id", vectors.score(entities, models[0]).alias("eps"))
    return eps.where(F.col("eps") >= F.lit(lw)).select("id", (F.col("eps") >= F.lit(hw)).cast("int").alias("certain"))


def _ledger(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return replay.ledger_frame(spark, [(i, s, round(lw, 6) + 0.0, round(hw, 6) + 0.0, n, round(c, 6), round(a, 6), r) for i, s, lw, hw, n, c, a, r in rows])


@query
def round_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, largest, n = _trailed(spark, sf_dir)
    return _ledger(spark, replay.replay_rounds(entities, models, lambda _, a, s: a >= s, largest, n, SIGMA))


@query
def lazy_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A read of the positive class after each update, with the rule on what reads waste."""
    _, entities, models, largest, n = _trailed(spark, sf_dir)
    positive = {r["round"]: r["n_positive"] for r in replay.round_classes(entities, models).collect()}
    return _ledger(spark, replay.replay_rounds(entities, models, lambda _, a, s: a >= s, largest, n, SIGMA, lazy=positive))


@query
def band_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, largest, n = _trailed(spark, sf_dir)
    bands = replay.band_counts(entities, models, 0, largest, HolderPair())[1:]
    counts = spark.createDataFrame([(b.round, b.n_band) for b in bands], "round int, n_band long")
    flips = replay.round_classes(entities, models).select("round", "n_flipped")
    return measures.band_stats(counts.join(flips, "round").withColumn("reclustered", F.lit(False)), n)


# --- the view: lazy and hybrid


@query
def lazy_members_positive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, policy="lazy").all_members(1)


@query
def lazy_members_negative(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(spark, sf_dir, policy="lazy", band="current").all_members(-1)


@query
def lazy_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _run(spark, sf_dir, policy="lazy")
    return spark.createDataFrame([(1, view.count_members(1)), (-1, view.count_members(-1))], "class int, n long")


READS = 15_000


@query
def hybrid_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _run(spark, sf_dir, arch="hybrid", policy="lazy")
    return view.label_of_many(workloads.random_ids(view.entities, READS)).select("id", "class")


@query
def hybrid_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    view = _run(spark, sf_dir, arch="hybrid", policy="lazy")
    return measures.source_stats(view.label_of_many(workloads.random_ids(view.entities, READS)))


@query
def buffer_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where random reads are answered, for bands that hold 1, 10 and 50 % and buffers of several sizes.

    A band reaches as far on either side of 0 as it takes, in steps of 0.0001.
    """
    _, entities, models, _, n = _trailed(spark, sf_dir)
    eps = materialize(entities.select("id", vectors.score(entities, models[-1]).alias("eps")), "margins")
    steps = eps.groupBy(F.floor(F.abs("eps") * 10000).alias("step")).count().orderBy("step").collect()  # as many rows as steps
    reads = eps.join(workloads.random_ids(eps, READS).select("id"), "id", "left_semi")
    out = None
    for share in (1, 10, 50):
        total, reach = 0, 0.0
        for r in steps:
            total, reach = total + r["count"], (r["step"] + 1) / 10000
            if total * 100 >= n * share:
                break
        met = reads.withColumn("open", in_band(F.col("eps"), -reach, reach))
        for size in (0.5, 1, 5, 10, 20, 50, 100):
            kept = eps.withColumn("d", band_distance(F.col("eps"), -reach, reach)).orderBy("d", "id").limit(int(n * size / 100)).select("id", F.lit(1).alias("kept"))
            source = F.when(~F.col("open"), "map").when(F.col("kept").isNotNull(), "buffer").otherwise("disk")
            rows = met.join(kept, "id", "left").select(source.alias("source")).groupBy("source").agg(F.count("*").alias("n"))
            rows = rows.select(F.lit(share).alias("band_share"), F.lit(float(size)).alias("buffer_share"), "source", "n")
            out = rows if out is None else out.unionByName(rows)
    return out


@query
def hybrid_memory(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes with keys and doubles of 8 bytes, and a buffer of 1 %."""
    rows = []
    for w in (workloads.planted_lineitem(spark, sf_dir), workloads.embeddings_binary(spark, sf_dir)):
        n = w.source.count()
        m = measures.memory_stats(n, n // 100, 8, 8 * w.dim)
        rows.append((w.name, n, m["margin_map"], m["hybrid"], m["whole"], round(m["ratio"], 6)))
    return spark.createDataFrame(rows, "dataset string, n long, margin_map long, hybrid long, whole long, ratio double")


@query
def most_uncertain(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, *_ = _trailed(spark, sf_dir)
    rows = entities.select("id", vectors.score(entities, models[-1]).alias("eps"))
    return rows.orderBy(F.abs("eps"), "id").limit(100).select("id", F.round("eps", 6).alias("eps"))


@query
def new_entities_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tenth of the entities arrives between updates, with vectors twice as long."""
    w = workloads.planted_lineitem(spark, sf_dir)
    old, new = w.entities.where("id % 10 <> 9"), w.entities.where("id % 10 = 9").select("id", F.transform("f", lambda x: x * 2).alias("f"))
    view, rest = _start(w, old)
    view.update(rest[:16])
    view.add_entities(new)
    view.update(rest[16:32])
    view.update(rest[32:])
    return view.view()


@query
def deleted_entities_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w)
    view.update(rest[:20])
    view.delete_entities(w.entities.where("id % 7 = 3").select("id"))
    view.update(rest[20:])
    return view.view()


# --- policies in hindsight


@query
def cost_family(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, largest, _ = _trailed(spark, sf_dir)
    return replay.cost_family(entities, models, largest)


def _costs(spark: SparkSession, sf_dir: str, rounds: int | None = None) -> tuple[list[list[float]], float]:
    _, entities, models, largest, n = _trailed(spark, sf_dir)
    models = models if rounds is None else models[: rounds + 1]
    return replay.costs_of(replay.cost_family(entities, models, largest), len(models)), n / SIGMA


@query
def monotonicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    report = monotonicity_report(_costs(spark, sf_dir)[0])
    return spark.createDataFrame([tuple(report.values())], "pairs long, later_costs_more long, cost_falls long")


@query
def offline_optimum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best schedule's cost over the first ten rounds at several costs of reclustering, and the rule's."""
    costs, whole = _costs(spark, sf_dir, 10)
    rows = [(share, round(best_schedule(costs, whole * share)[0], 6), round(schedule_cost(costs, whole * share, simulate(costs, whole * share)), 6)) for share in (0.05, 0.1, 0.25, 1.0)]
    return spark.createDataFrame(rows, "share double, best double, rule double")


@query
def policy_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    costs, s = _costs(spark, sf_dir)
    rules = {"never": fixed_rule("never"), "always": fixed_rule("always"), "every_10": fixed_rule("every", 10), "rent_or_buy": lambda _, a: a >= s}
    rows = []
    for name, rule in rules.items():
        run = run_policy(costs, s, rule)
        rows.append((name, sum(r[4] for r in run), round(sum(r[2] for r in run), 6)))
    return spark.createDataFrame(rows, "policy string, n_reclusters long, total_cost double")


# --- classes, quality, SQL


CLASSES = ("A", "N", "R")


def _flags(spark: SparkSession, sf_dir: str) -> tuple[workloads.Workload, DataFrame, list[Model]]:
    w = workloads.planted_lineitem(spark, sf_dir)
    source = w.source.withColumn("label", F.col("l_returnflag"))
    examples = source.select("id", "label").orderBy("id").limit(w.warm + w.measured)
    rows = w.feature.transform(source.join(F.broadcast(examples.select("id")), "id", "left_semi"), "id").join(examples, "id").orderBy("id").collect()
    return w, source, multiclass.train_ovr([(np.array(r["f"]), r["label"]) for r in rows], CLASSES, w.trainer, w.dim)


@query
def ovr_multiclass(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, _, models = _flags(spark, sf_dir)
    return multiclass.classify(w.entities, models, CLASSES)


@query
def chain_multiclass(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, _, models = _flags(spark, sf_dir)
    return multiclass.classify_chain(w.entities, models, CLASSES)


@query
def ovr_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, source, models = _flags(spark, sf_dir)
    return multiclass.confusion(multiclass.classify(w.entities, models, CLASSES), source.select("id", "label"), CLASSES)


@query
def largest_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = multiclass.largest_class(table(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("label")))
    b = multiclass.largest_class(table(spark, sf_dir, "lineitem"), "l_returnflag")
    return spark.createDataFrame([("embeddings", a), ("lineitem", b)], "dataset string, label string")


def _exact_view(spark: SparkSession, sf_dir: str) -> tuple[workloads.Workload, DataFrame]:
    w = workloads.planted_lineitem(spark, sf_dir)
    return w, _run(spark, sf_dir, each=20).view()


@query
def quality_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, view = _exact_view(spark, sf_dir)
    return measures.quality(view, w.source)


def _text_quality(w: workloads.Workload) -> DataFrame:
    view, rest = _start(w, w.kept_entities(), buckets=8)
    each = max(20, len(rest) // 10)
    for k in range(0, len(rest), each):
        view.update(rest[k : k + each])
    return measures.quality(view.view(), w.source)


@query
def quality_title7(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.text_language(spark, sf_dir, 7, **workloads.IN_SQL)
    return _text_quality(w)


@query
def quality_full_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.text_language(spark, sf_dir, **workloads.IN_SQL)
    return _text_quality(w)


@query
def quality_examples_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.text_quality(spark, sf_dir, **workloads.IN_SQL)
    return measures.quality(w.learn_all(20, buckets=8).view(), w.labelled)


@query
def batch_solvers(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.planted_lineitem(spark, sf_dir)
    train = w.entities.join(F.broadcast(w.examples()), "id")
    out = None
    for name in ("linear_svc", "logistic", "linear"):
        view, _ = batch_solver(name, train, w.entities)
        rows = measures.quality(view, w.source).withColumn("method", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def view_joined_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, view = _exact_view(spark, sf_dir)
    view.createOrReplaceTempView("priced")
    w.source.select("id", "l_orderkey").createOrReplaceTempView("priced_items")
    table(spark, sf_dir, "orders").createOrReplaceTempView("priced_orders")
    return spark.sql("SELECT o_orderpriority AS priority, class, count(*) AS n FROM priced JOIN priced_items USING (id) JOIN priced_orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority, class")


@query
def view_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, view = _exact_view(spark, sf_dir)
    rows = view.join(w.source.select("id", "l_returnflag", "l_linestatus"), "id")
    return rows.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum((F.col("class") == 1).cast("long")).alias("n_positive"))


@query
def view_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, view = _exact_view(spark, sf_dir)
    rows = view.join(w.source.select("id", "l_returnflag"), "id")
    return rows.withColumn("class", F.col("class").cast("string")).rollup("l_returnflag", "class").agg(F.count("*").alias("n"))


@query
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, entities, models, *_ = _trailed(spark, sf_dir)
    vectors.register_sql(spark)
    entities.createOrReplaceTempView("sql_entities")
    m = models[-1]
    w = ", ".join(f"{x!r}D" for x in m.w.tolist())
    return spark.sql(f"SELECT mv_class(eps) AS class, count(*) AS n, round(max(m2), 6) AS largest FROM (SELECT mv_score(f, array({w}), {float(m.b)!r}D) AS eps, mv_norm(f, 2) AS m2 FROM sql_entities) GROUP BY 1")


@query
def declared_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view declared in text, trained by the default method on its examples table."""
    w = workloads.planted_lineitem(spark, sf_dir)
    w.source.createOrReplaceTempView("declared_items")
    w.examples().createOrReplaceTempView("declared_examples")
    w.source.select(F.col("label").alias("kind")).distinct().createOrReplaceTempView("declared_labels")
    fx.register_feature("scaled_prices", lambda: fx.DenseColumns(*workloads.LINEITEM))
    view = run_statement(spark, "DEFINE MODEL VIEW declared OVER declared_items KEY id LABELS declared_labels(kind) EXAMPLES declared_examples(id, label) FEATURES scaled_prices() USING svm")
    return spark.table(view.name)


# --- streams and events


@query
def stream_update_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Updates arrive as files of a stream, one batch each."""
    w = workloads.planted_lineitem(spark, sf_dir)
    view, rest = _start(w)
    path = shared_path(spark, "arrivals")
    for k in range(0, len(rest), 10):
        spark.createDataFrame([(key, y) for key, _, y in rest[k : k + 10]], "id long, label int").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema("id long, label int").option("maxFilesPerTrigger", 1).parquet(path)
    attach_stream(view, stream, "examples", shared_path(spark, "progress")).awaitTermination()
    return view.view()


#: A model over the vectors of event windows.
EVENT_MODEL = Model(np.array([1.0, 1.0]), 0.7)


def _classified(rows: DataFrame) -> DataFrame:
    f = rows.withColumn("f", window_vector(F.col("n"), F.col("total")))
    return f.select("user_id", F.unix_timestamp("start").alias("start"), "n", F.round("total", 4).alias("total"), vectors.sign_class(vectors.score(f, EVENT_MODEL)).alias("class"))


@query
def event_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classified(user_windows(table(spark, sf_dir, "events"), "6 hours"))


@query
def event_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classified(user_windows(table(spark, sf_dir, "events"), "6 hours", "3 hours"))


@query
def event_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _classified(user_sessions(table(spark, sf_dir, "events"), "2 hours"))


# --- all techniques


TECHNIQUES = ("naive_disk", "naive_memory", "incremental_disk", "incremental_memory", "hybrid")


@query
def technique_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wrong rows of every technique, policy and operation: 30 cells, all 0."""
    w = workloads.planted_lineitem(spark, sf_dir)
    entities = materialize(w.entities, "matrix")
    batch = w.batch()
    warm = w.trainer.fit([(f, y) for _, f, y in batch[: w.warm]], w.dim)
    ids = workloads.random_ids(entities, 1000)
    final = w.trail(batch)[-1]
    exact = materialize(entities.select("id", vectors.sign_class(vectors.score(entities, final)).cast("int").alias("class")), "exact")
    rows = []
    for policy in ("eager", "lazy"):
        for technique in TECHNIQUES:
            kind, _, arch = technique.partition("_")
            if kind == "naive":
                view = NaiveView(entities, w.trainer, warm, policy, arch)
            else:
                view = ClassificationView(entities, w.trainer, w.dim, Options(policy=policy, arch=arch or "hybrid", buckets=8), warm)
            view.update(batch[w.warm : w.warm + 20])
            view.update(batch[w.warm + 20 :])
            wrong = measures.diff_with_exact(view.view(), exact).count()
            single = view.label_of_many(ids).select("id", "class").join(exact.withColumnRenamed("class", "truth"), "id").where("class <> truth").count()
            members = abs(view.all_members(1).join(exact.where("class = 1"), "id", "left_semi").count() - exact.where("class = 1").count()) + view.all_members(1).join(exact.where("class = 1"), "id", "left_anti").count()
            rows += [(technique, policy, "update", wrong), (technique, policy, "single", single), (technique, policy, "all", members)]
    return spark.createDataFrame(rows, "technique string, policy string, operation string, n_wrong long")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_ledger(spark, sf_dir)


__all__ = ["flagship", "gather", "queries"]
