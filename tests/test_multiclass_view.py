import numpy as np
import pytest
from pyspark.sql import functions as F

from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators.measures import diff_with_exact
from driftview.operators.multiclass_view import MulticlassView, lead_lost, train
from driftview.operators.view import Options
from driftview.plans.declare import run_statement
from driftview.session import materialize

TRAINER = SgdTrainer("hinge", 0.3, 1e-3)
CENTRES = {"a": (3, 0, 0), "b": (-3, 3, 1), "c": (0, -4, -1), "d": (0, 0, 4)}


@pytest.fixture(scope="module")
def clouds(spark):
    rng = np.random.default_rng(3)
    rows = [(k, (np.array(CENTRES[c]) + rng.normal(0, 1.0, 3)).tolist(), c) for k, c in enumerate("abcd" * 100)]
    entities = materialize(spark.createDataFrame(rows, "id long, f array<double>, label string").select("id", "f"), "clouds")
    return entities, [(k, np.array(f), c) for k, f, c in rows]


def start(clouds, spark, **options):
    entities, batch = clouds
    warm = train(TRAINER, [Model.zero(3)] * 4, batch[:120], "abcd")
    return MulticlassView(entities, TRAINER, 3, list("abcd"), Options(buckets=4, **options), warm, name=f"clouds_{len(options)}"), batch[120:]


def exactly(view):
    assert diff_with_exact(view.view(), view.exact()).count() == 0


@pytest.mark.parametrize("options", [{}, {"arch": "memory"}, {"policy": "lazy"}, {"policy": "lazy", "arch": "memory"}], ids=str)
def test_every_round_equals_a_full_relabel(clouds, spark, options):
    view, rest = start(clouds, spark, **options)
    for k in range(0, 60, 12):
        view.update(rest[k : k + 12])
        exactly(view)
        assert view.count_members("b") == view.exact().where("class = 'b'").count()
        assert diff_with_exact(spark.table(view.name), view.exact()).count() == 0
    assert any(0 < s.n_band < 400 for s in view.history) and view.all_members("c").count() == view.exact().where("class = 'c'").count()
    ids = clouds[0].select("id").limit(30)
    assert diff_with_exact(view.label_of_many(ids), view.exact().join(ids, "id", "left_semi")).count() == 0


def test_leads_are_never_overestimated(clouds, spark):
    _, batch = clouds
    x = np.array([f for _, f, _ in batch])
    stored = train(TRAINER, [Model.zero(3)] * 4, batch[:120], "abcd")
    current = train(TRAINER, stored, batch[120:140], "abcd")
    before, after = (np.stack([x @ m.w - m.b for m in ms], 1) for ms in (stored, current))
    lead = np.sort(before, 1)[:, -1] - np.sort(before, 1)[:, -2]
    lost = lead_lost(stored, current, np.sqrt((x * x).sum(1)).max(), 2.0)
    kept = lead > lost[before.argmax(1)]
    assert kept.any() and (after.argmax(1) == before.argmax(1))[kept].all()


def test_entities_arrive_change_and_leave(clouds, spark):
    view, rest = start(clouds, spark)
    view.update(rest[:12])
    view.add_entities(spark.createDataFrame([(900, [5.0, 0.0, 0.0]), (3, [9.0, 9.0, 9.0]), (901, [float("nan"), 1.0, 1.0]), (None, [1.0, 1.0, 1.0])], "id long, f array<double>"))
    exactly(view)
    view.delete_entities(spark.createDataFrame([(0,), (7,)], "id long"))
    view.update(rest[12:24])
    exactly(view)
    ids = {r["id"] for r in spark.table(view.name).collect()}
    assert ids == set(range(400)) - {0, 7} | {900}


def test_cold_start_ties_go_to_the_smaller_class(clouds, spark):
    view = MulticlassView(clouds[0], TRAINER, 3, list("abcd"), Options(buckets=4))
    assert {r["class"] for r in view.view().collect()} == {"a"}
    view.update(clouds[1][:20])
    exactly(view)
    with pytest.raises(ValueError):
        MulticlassView(clouds[0], TRAINER, 3, ["a"])


def test_sparse_vectors(clouds, spark):
    entities, batch = clouds
    sparse = materialize(entities.select("id", F.struct(F.array(*map(F.lit, range(3))).alias("idx"), F.col("f").alias("val")).alias("f")), "sparse")
    rows = [(k, (np.arange(3), f), c) for k, f, c in batch]
    view = MulticlassView(sparse, TRAINER, 3, list("abcd"), Options(buckets=4), train(TRAINER, [Model.zero(3)] * 4, rows[:120], "abcd"))
    view.update(rows[120:150])
    exactly(view)


def test_a_declared_view_of_four_labels(clouds, spark):
    entities, batch = clouds
    entities.select("id", *[F.col("f")[k].alias(c) for k, c in enumerate("xyz")]).createOrReplaceTempView("cloud_points")
    spark.createDataFrame([(k, c) for k, _, c in batch[:200]], "id long, kind string").createOrReplaceTempView("cloud_marks")
    spark.createDataFrame([(c,) for c in "abcd"], "kind string").createOrReplaceTempView("cloud_kinds")
    view = run_statement(spark, "DEFINE MODEL VIEW clouds_by_kind OVER cloud_points KEY id LABELS cloud_kinds(kind) EXAMPLES cloud_marks(id, kind) FEATURES dense_columns(x, y, z) USING svm")
    truth = {k: c for k, _, c in batch}
    right = [r["class"] == truth[r["id"]] for r in spark.table("clouds_by_kind").collect()]
    assert len(right) == 400 and np.mean(right) > 0.85
    view.add_examples(spark.createDataFrame([(k, c) for k, _, c in batch[200:240]], "id long, label string"))
    exactly(view)
