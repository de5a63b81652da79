"""More than two classes by binary views: one against the rest, or a chain of decisions."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators.band import HolderPair, norm


def largest_class(examples: DataFrame, label: str = "label") -> object:
    """The most frequent label, ties by the smallest: the binary task of the dense experiment."""
    row = examples.where(F.col(label).isNotNull()).groupBy(label).count().orderBy(F.desc("count"), label).first()
    return None if row is None else row[label]


def train_ovr(batch: Sequence[tuple[object, object]], classes: Sequence[object], trainer: SgdTrainer, dim: int) -> list[Model]:
    """A model for each class, from (vector, label) in order."""
    models = [Model.zero(dim) for _ in classes]
    for f, label in batch:
        models = [trainer.step(m, f, 1 if label == c else -1) for m, c in zip(models, classes, strict=True)]
    return models


def scores(df: DataFrame, models: Sequence[Model]) -> Column:
    """The scores of all classes: written out while that is short, by a product of matrices over Arrow batches otherwise."""
    if vectors.is_sparse(df) or len(models) * len(models[0].w) > vectors.UNROLL:
        return vectors.arrow_scores(df, models)
    return F.array(*[vectors.score(df, m) for m in models])


def classify(df: DataFrame, models: Sequence[Model], classes: Sequence[object]) -> DataFrame:
    """(id, class) by the largest score, ties by the smaller class; one pass for all classes."""
    rows = df.select("id", scores(df, models).alias("scores"))
    best = F.array_position("scores", F.array_max("scores")).cast("int")
    return rows.select("id", F.element_at(F.array(*[F.lit(c) for c in classes]), best).alias("class"))


def classify_chain(df: DataFrame, models: Sequence[Model], classes: Sequence[object]) -> DataFrame:
    """(id, class): the first class whose binary view holds the row, else the last."""
    decision = None
    for model, c in zip(models[:-1], classes[:-1], strict=True):
        here = vectors.score(df, model) >= 0
        decision = F.when(here, F.lit(c)) if decision is None else decision.when(here, F.lit(c))
    return df.select("id", (decision.otherwise(F.lit(classes[-1])) if decision is not None else F.lit(classes[-1])).alias("class"))


def multiclass_certain(stored: Sequence[Model], current: Sequence[Model], classes: Sequence[object], largest: float, pair: HolderPair, eps: str = "scores", slack: float = 0.0) -> Column:
    """The class that no rival can reach, from stored scores alone; null where that is open.

    Ties go to the smaller class, so the test against smaller rivals is strict.
    ``slack`` is room for sums of doubles in another order.
    """
    shift = [c.b - s.b for s, c in zip(stored, current, strict=True)]
    reach = [largest * norm(c.w - s.w, pair.p) for s, c in zip(stored, current, strict=True)]
    out = None
    for a, c in enumerate(classes):
        low = F.get(eps, F.lit(a)) - F.lit(float(shift[a] + reach[a] + slack))
        sure = F.lit(True)
        for r in range(len(classes)):
            if r != a:
                high = F.get(eps, F.lit(r)) - F.lit(float(shift[r] - reach[r]))
                sure = sure & ((low > high) if r < a else (low >= high))
        out = F.when(sure, F.lit(c)) if out is None else out.when(sure, F.lit(c))
    return out


def confusion(view: DataFrame, truth: DataFrame, classes: Sequence[object]) -> DataFrame:
    """A row for each true class and a column for each predicted one."""
    return truth.select("id", F.col("label").alias("truth")).join(view, "id").groupBy("truth").pivot("class", list(classes)).agg(F.count(F.lit(1))).na.fill(0)
