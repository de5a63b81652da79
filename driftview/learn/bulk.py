"""Training over examples that do not fit on the driver: whole-batch steps, one aggregation each."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn.model import Model


def slope(loss: str, y: Column, z: Column) -> Column:
    """The loss's derivative by the score."""
    if loss == "hinge":
        return F.when(y * z < 1, -y.cast("double")).otherwise(F.lit(0.0))
    if loss == "logistic":
        return -y / (1.0 + F.exp(F.least(F.lit(700.0), y * z)))
    if loss == "squared":
        return z - y
    raise ValueError(loss)


def gradient(examples: DataFrame, model: Model, loss: str) -> tuple[np.ndarray, float, int]:
    """Mean slope by weights and by bias over dense examples (f, label), and their number.

    Tasks send a sum for each dimension; no example leaves its executor.
    """
    rows = examples.select("f", slope(loss, F.col("label"), vectors.score(examples, model)).alias("g"))
    sums = [F.sum(F.col("g") * F.get("f", F.lit(k))).alias(f"w{k}") for k in range(len(model.w))]
    got = rows.agg(F.count("*").alias("n"), F.sum("g").alias("b"), *sums).first()
    n = got["n"]
    return np.array([(got[f"w{k}"] or 0.0) / max(1, n) for k in range(len(model.w))]), -(got["b"] or 0.0) / max(1, n), n


def bulk_train(examples: DataFrame, dim: int, loss: str = "hinge", eta0: float = 1.0, l2: float = 1e-3, rounds: int = 10, start: Model | None = None) -> Model:
    """``rounds`` steps down the mean loss over all examples, of size eta0 / (1 + round): a warm model for a view over any number of examples.

    Rows with a null vector or label are left out; without examples the model stays.
    """
    usable = examples.where("f is not null and label is not null").select("f", F.col("label").cast("int").alias("label"))
    model = start or Model.zero(dim)
    for k in range(rounds):
        by_w, by_b, n = gradient(usable, model, loss)
        if not n:
            break
        eta = eta0 / (1.0 + k)
        model = Model(model.w * (1.0 - eta * l2) - eta * by_w, model.b - eta * by_b, model.round + 1)
    return model
