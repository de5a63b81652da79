import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from driftview.learn.model import Model, sign
from driftview.operators.band import HolderPair, WaterMarks, certain_class, deviation_interval, norm, water_marks


def test_worked_example_of_scores():
    m = Model(np.array([-1.0, 1.0]), 0.5)
    assert m.score(np.array([3.0, 4.0])) == 0.5 and sign(m.score(np.array([3.0, 4.0]))) == 1
    assert sign(0.0) == 1 and sign(-1e-12) == -1


def test_worked_state_of_the_clustered_table(spark):
    rows = spark.createDataFrame([(10, 0.4), (1, 0.2), (34, 0.1), (5, 0.01), (3, -0.2), (18, -0.5)], "id long, eps double")
    got = {r["id"]: r["c"] for r in rows.select("id", certain_class(F.col("eps"), -0.22, 0.15).alias("c")).collect()}
    assert got == {10: 1, 1: 1, 34: None, 5: None, 3: None, 18: -1}


def test_entity_on_the_hyperplane_is_not_called_negative(spark):
    rows = spark.createDataFrame([(1, 0.0)], "id long, eps double")
    assert rows.select(certain_class(F.col("eps"), 0.0, 0.0).alias("c")).first()["c"] == 1
    # margin equal to the low mark may be exactly 0 under the new model
    assert rows.select(certain_class(F.col("eps"), 0.0, 0.5).alias("c")).first()["c"] is None


def test_pairs():
    assert HolderPair.for_norm("l1") == HolderPair(math.inf, 1.0)
    assert HolderPair(3.0, 1.5)
    with pytest.raises(ValueError):
        HolderPair(2.0, 3.0)


vectors = st.lists(st.floats(-5, 5), min_size=3, max_size=3)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(vectors, st.floats(-3, 3)), min_size=2, max_size=6), st.lists(vectors, min_size=1, max_size=10), st.sampled_from(["l1", "l2", "linf"]))
def test_outside_the_band_classes_are_right_and_bands_are_nested(trail, entities, kind):
    models = [Model(np.array(w), b, k) for k, (w, b) in enumerate(trail)]
    pair = HolderPair.for_norm(kind)
    largest = max(norm(np.array(f), pair.q) for f in entities)
    last = None
    for j, low, high, lw, hw in water_marks(models, 0, largest, pair.p, slack=1e-9):
        assert lw <= low + 1e-9 and hw >= high - 1e-9
        if last:
            assert lw <= last[0] and hw >= last[1]
        last = (lw, hw)
        for f in entities:
            eps = models[0].score(np.array(f))
            now = sign(models[j].score(np.array(f)))
            if eps >= hw:
                assert now == 1
            if eps < lw:
                assert now == -1


def test_a_larger_norm_redoes_the_bounds_from_all_moves():
    marks = WaterMarks()
    marks.push(1.0, 0.0)
    marks.push(0.1, 2.0)
    assert marks.bounds(1.0) == (-1.0, 2.1)
    assert marks.bounds(10.0) == (-10.0, 10.0)


def test_intervals():
    s, c = Model(np.array([1.0, 0.0]), 0.5), Model(np.array([1.0, 2.0]), 0.75)
    assert deviation_interval(s, c, 3.0, 2.0) == (0.25 - 6.0, 0.25 + 6.0)
    assert deviation_interval(s, s, 3.0, 2.0) == (0.0, 0.0)
