import numpy as np
import pytest
from pyspark.sql import functions as F

from driftview.learn.sgd import SgdTrainer
from driftview.operators import driver_view
from driftview.operators.driver_view import DriverView
from driftview.operators.measures import diff_with_exact
from driftview.operators.view import Options
from driftview.session import materialize

TRAINER = SgdTrainer("hinge", 2.0, 0.01)


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 3))
    y = np.where(x @ [1.0, -2.0, 0.5] + 0.2 >= 0, 1, -1)
    entities = materialize(spark.createDataFrame([(k * 7 % 400, f.tolist()) for k, f in enumerate(x)], "id long, f array<double>"), "small")
    return entities, [(k * 7 % 400, x[k], int(y[k])) for k in range(80)]


def start(small, **options):
    entities, batch = small
    return DriverView(entities, TRAINER, 3, Options(buckets=4, **options), TRAINER.fit([(f, y) for _, f, y in batch[:40]], 3), name=f"driver_{options.get('policy', 'eager')}"), batch[40:]


@pytest.mark.parametrize("policy", ["eager", "lazy"])
def test_every_round_equals_a_full_relabel(small, spark, policy):
    view, rest = start(small, policy=policy)
    for k in range(0, 40, 4):
        view.update(rest[k : k + 4])
        exact = {r["id"]: r["class"] for r in view.exact().collect()}
        assert view.count_members(1) == sum(c == 1 for c in exact.values()) and view.count_members(-1) == sum(c == -1 for c in exact.values())
        assert [view.label_of(i) for i in range(0, 400, 13)] == [exact[i] for i in range(0, 400, 13)]
        assert diff_with_exact(spark.table(view.name), view.exact()).count() == 0
    assert view.label_of(10**6) is None
    if policy == "eager":
        assert any(s.n_band < 400 and not s.reclustered for s in view.history) and sum(s.n_flipped for s in view.history) > 0


def test_entities_arrive_and_leave(small, spark):
    view, rest = start(small)
    view.update(rest[:8])
    view.delete_entities(spark.createDataFrame([(3,), (5,), (10**7,)], "id long"))
    assert view.label_of(3) is None and view.count_members(1) + view.count_members(-1) == 398
    view.update(rest[8:16])
    assert diff_with_exact(view.view(), view.exact()).count() == 0
    view.add_entities(spark.createDataFrame([(3, [1.0, 1.0, 1.0]), (900, [float("nan"), 1.0, 1.0])], "id long, f array<double>"))
    assert view.label_of(3) is not None and view.label_of(900) is None and view.count_members(1) + view.count_members(-1) == 399
    view.update(rest[16:24])
    assert diff_with_exact(view.view(), view.exact()).count() == 0


def test_what_is_too_large_or_not_dense_is_refused(small, spark, monkeypatch):
    with pytest.raises(ValueError):
        start(small, layout="slim")
    sparse = small[0].select("id", F.struct(F.array(*map(F.lit, range(3))).alias("idx"), F.col("f").alias("val")).alias("f"))
    with pytest.raises(ValueError):
        DriverView(sparse, TRAINER, 3)
    monkeypatch.setattr(driver_view, "MAX_BYTES", 1000)
    with pytest.raises(ValueError):
        start(small)
    monkeypatch.undo()
    assert DriverView(small[0].limit(0), TRAINER, 3).count_members(1) == 0
