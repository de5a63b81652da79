"""Examples beyond what the driver holds: they stay in a table, and all of them are learned from."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from driftview.functions import vectors
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators import measures, view
from driftview.operators.measures import diff_with_exact
from driftview.operators.view import ClassificationView, ExampleTable, Options
from driftview.plans import workloads


@pytest.fixture
def few(monkeypatch):
    """A driver that holds ten examples."""
    monkeypatch.setattr(view, "MAX_BATCH", 10)


def by_definition(spark, data, label, held=view.MAX_BATCH):
    """Classes under the model that takes a step for each labelled document, in order of id."""
    w = workloads.text_quality(spark, data, **workloads.IN_SQL, label=label)
    model = Model.zero(w.dim)
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(view, "MAX_BATCH", held)
        batch = w.batch()
    for _, f, y in batch:
        model = w.trainer.step(model, f, y)
    entities = w.kept_entities()
    assert model.round == w.labelled.count()
    return w, entities.select("id", vectors.sign_class(vectors.score(entities, model)).cast("int").alias("class"))


def test_quality_examples_table_of_more_examples_than_the_driver_holds(spark, data, monkeypatch):
    w, exact = by_definition(spark, data, "quality")
    expected = measures.quality(exact, w.labelled).collect()
    monkeypatch.setattr(view, "MAX_BATCH", 10)
    assert entry.queries()["quality_examples_table"](spark, data).collect() == expected


def test_quality_labels_view_of_more_examples_than_the_driver_holds(spark, data, few):
    _, exact = by_definition(spark, data, "quality", 1000)
    assert diff_with_exact(entry.queries()["quality_labels_view"](spark, data), exact).count() == 0


def test_toxic_labels_view_of_more_examples_than_the_driver_holds(spark, data, few):
    _, exact = by_definition(spark, data, "toxic", 1000)
    assert diff_with_exact(entry.queries()["toxic_labels_view"](spark, data), exact).count() == 0


@pytest.mark.parametrize("sparse", [False, True])
def test_a_view_over_a_table_of_examples(spark, few, sparse):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(200, 3))
    y = np.where(x @ [1.0, -2.0, 0.5] >= 0, 1, -1).tolist()
    entities = spark.createDataFrame([(k, f.tolist()) for k, f in enumerate(x)], "id long, f array<double>")
    if sparse:
        entities = entities.select("id", F.struct(F.array(F.lit(0), F.lit(1), F.lit(2)).alias("idx"), F.col("f").alias("val")).alias("f"))
    examples = spark.createDataFrame([(k, y[k]) for k in range(60)], "id long, label int")
    trainer = SgdTrainer("hinge", 2.0, 0.01)

    def model(pairs):
        return trainer.fit([(x[k], label) for k, label in pairs], 3)

    v = ClassificationView.create(entities, examples.where("id < 40"), trainer, 3, Options(buckets=4), name="many")
    v.add_examples(examples.where("id >= 40"))
    assert all(isinstance(e, ExampleTable) for e in v.examples) and v.published()["n_examples"] == 60
    steps = [lambda: None, lambda: v.delete_examples([3, 50]), lambda: v.relabel({0: -y[0], 45: -y[45]})]
    pairs = {k: y[k] for k in range(60)}
    changes = [{}, {3: None, 50: None}, {0: -y[0], 45: -y[45]}]
    for step, change in zip(steps, changes, strict=True):
        step()
        pairs = {k: label for k, label in (pairs | change).items() if label is not None}
        expected = model(pairs.items())
        assert np.allclose(v.model.w, expected.w) and abs(v.model.b - expected.b) < 1e-9
        assert diff_with_exact(v.view(), v.exact()).count() == 0
    assert v.published()["n_examples"] == 58
