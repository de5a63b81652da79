import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

from driftview.llm.toxicity import Examples, features, fit_nnpu, toxicity
from tests.llm.conftest import words

BAD = ("vileword", "nastyword", "foulword")


def corpus(n=600, seed=3):
    rng = random.Random(seed)
    rows, labels = [], []
    for k in range(n):
        w = words(seed * 1000 + k, rng.randrange(20, 200), 800)
        toxic = k % 7 == 0
        if toxic:
            for _ in range(max(2, len(w) // 40)):
                w.insert(rng.randrange(len(w)), rng.choice(BAD) + rng.choice(["", "s", "ing"]))
        rows.append((k, " ".join(w)))
        labels.append((k, int(toxic)))
    return rows, labels


def test_held_out_accuracy(spark, frame):
    rows, labels = corpus()
    marked = spark.createDataFrame([(k, y, 0) for k, y in labels if k % 3], "doc_id long, toxic int, quality int")
    found = {r["doc_id"]: r for r in toxicity(frame(rows), marked).collect()}
    truth = dict(labels)
    assert all(r["held_out"] == (zlib.crc32(str(k).encode()) % 5 == 0) for k, r in found.items())
    held = [k for k, r in found.items() if r["held_out"]]
    right = np.mean([found[k]["predicted"] == truth[k] for k in held])
    assert right > 0.95
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in found.values())
    assert np.mean([found[k]["predicted"] for k in held if not truth[k]]) < 0.02


def test_a_third_of_the_texts_is_toxic(spark, frame):
    rng, rows, labels = random.Random(5), [], []
    for k in range(600):
        w, toxic = words(k, 80, 800), k % 10 < 3
        for _ in range(4 * toxic):
            w.insert(rng.randrange(80), rng.choice(BAD))
        rows.append((k, " ".join(w)))
        labels.append((k, int(toxic)))
    marked = spark.createDataFrame([x for x in labels if x[0] % 3], "doc_id long, toxic int")
    held = [r for r in toxicity(frame(rows), marked).collect() if r["held_out"]]
    assert np.mean([r["predicted"] == dict(labels)[r["doc_id"]] for r in held]) > 0.95


def test_held_out_labels_are_not_read(spark, frame):
    rows, labels = corpus(300)
    first = spark.createDataFrame(labels, "doc_id long, toxic int")
    flipped = spark.createDataFrame([(k, 1 - y if zlib.crc32(str(k).encode()) % 5 == 0 else y) for k, y in labels], "doc_id long, toxic int")
    a, b = ({r["doc_id"]: r["score"] for r in toxicity(frame(rows), x).collect()} for x in (first, flipped))
    assert a == pytest.approx(b, abs=1e-9)


def test_risk_is_corrected_for_positives_among_the_unlabelled():
    rng = np.random.default_rng(1)
    x = rng.normal(0, 1, (900, 1))
    y = np.arange(900) < 300
    x[:, 0] += np.where(y | (np.arange(900) >= 780), 4.0, 0.0)  # a fifth of the unlabelled are positive
    n = len(x)
    data = Examples(np.arange(0, 2 * n + 1, 2), np.tile([0, 1], n), np.column_stack([x[:, 0] - 2, np.ones(n)]).ravel(), y)
    w, b = fit_nnpu(data, 0.2, 2)
    positive = (x[:, 0] - 2) * w[0] + w[1] + b > 0
    assert np.mean(positive[780:]) > 0.9 and np.mean(positive[300:780]) < 0.1


def test_features_have_length_one():
    who, what, value, n = features(pa.array(["a b c", "", None, "word word word"]))
    assert n == 4 and set(who) == {0, 3}
    assert np.bincount(who, value**2, 4).round(9).tolist() == [1, 0, 0, 1]


def test_odd_rows(spark, odd, frame):
    labels = spark.createDataFrame([(3, 1), (3, 0), (None, 1), (4, None), (99, 1)], "doc_id long, toxic int")
    rows = toxicity(odd, labels).collect()
    assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
    none = toxicity(odd, spark.createDataFrame([], "doc_id long, toxic int")).collect()
    assert all(r["predicted"] == 0 for r in none)
    assert toxicity(frame([]), labels).collect() == []
