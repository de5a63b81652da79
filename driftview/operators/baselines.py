"""What the incremental view is compared with: full relabels, full retraining, and batch solvers."""

from __future__ import annotations

import time
from collections.abc import Iterable

from pyspark import StorageLevel
from pyspark.ml.classification import LinearSVC, LogisticRegression
from pyspark.ml.functions import array_to_vector
from pyspark.ml.regression import LinearRegression
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.session import shared_path


class NaiveView:
    """Every update of an eager view scores all entities and writes all classes; every read of a lazy one scores what it reads.

    ``arch`` disk keeps parquet, memory keeps cached frames.
    """

    def __init__(self, entities: DataFrame, trainer: SgdTrainer, model: Model, policy: str = "eager", arch: str = "disk") -> None:
        self.spark, self.trainer, self.model, self.policy, self.arch = entities.sparkSession, trainer, model, policy, arch
        self.path, self.round = shared_path(self.spark, "naive"), 0
        rows = entities.select("id", "f")
        if arch == "memory":
            self.entities = rows.persist(StorageLevel.MEMORY_AND_DISK)
            self.entities.count()
        else:
            rows.write.parquet(f"{self.path}/entities")
            self.entities = self.spark.read.schema(rows.schema).parquet(f"{self.path}/entities")
        self.frame: DataFrame | None = None
        if policy == "eager":
            self._relabel()

    def _scored(self) -> DataFrame:
        return self.entities.select("id", vectors.sign_class(vectors.score(self.entities, self.model)).cast("int").alias("class"))

    def _relabel(self) -> None:
        if self.arch == "memory":
            old, self.frame = self.frame, self._scored().persist(StorageLevel.MEMORY_AND_DISK)
            self.frame.count()
            if old is not None:
                old.unpersist()
            return
        path = f"{self.path}/round={self.round}"
        self._scored().write.parquet(path)
        self.frame = self.spark.read.schema("id long, class int").parquet(path)

    def update(self, examples: Iterable[tuple[int, object, int]]) -> None:
        for _, f, y in examples:
            self.model = self.trainer.step(self.model, f, y)
        self.round += 1
        if self.policy == "eager":
            self._relabel()

    def view(self) -> DataFrame:
        return self.frame if self.policy == "eager" else self._scored()

    def all_members(self, cls: int = 1) -> DataFrame:
        return self.view().where(F.col("class") == cls).select("id")

    def count_members(self, cls: int = 1) -> int:
        return self.all_members(cls).count()

    def label_of_many(self, ids: DataFrame) -> DataFrame:
        if self.policy == "eager":
            return self.frame.join(ids, "id", "left_semi")
        rows = self.entities.join(ids, "id", "left_semi")
        return rows.select("id", vectors.sign_class(vectors.score(rows, self.model)).cast("int").alias("class"))

    def label_of(self, key: int) -> int | None:
        if self.policy == "eager":
            row = self.frame.where(F.col("id") == key).first()
            return None if row is None else row["class"]
        row = self.label_of_many(self.entities.where(F.col("id") == key).select("id")).first()
        return None if row is None else row["class"]

    def close(self) -> None:
        for frame in (self.frame, self.entities):
            if self.arch == "memory" and frame is not None:
                frame.unpersist()


class FullRetrain(NaiveView):
    """Each update trains on all examples from scratch, then relabels."""

    def __init__(self, entities: DataFrame, trainer: SgdTrainer, dim: int, examples: list[tuple[int, object, int]], arch: str = "disk") -> None:
        self.dim, self.examples = dim, list(examples)
        super().__init__(entities, trainer, self._train(trainer), "eager", arch)

    def _train(self, trainer: SgdTrainer) -> Model:
        return trainer.fit([(f, y) for _, f, y in self.examples], self.dim)

    def update(self, examples: Iterable[tuple[int, object, int]]) -> None:
        self.examples += list(examples)
        self.model = self._train(self.trainer)
        self.round += 1
        self._relabel()


def batch_solver(name: str, train: DataFrame, test: DataFrame) -> tuple[DataFrame, float]:
    """(id, class) of ``test`` by a batch solver trained on dense (f, label), and the seconds that training took."""
    solver = {"linear_svc": LinearSVC(maxIter=50, regParam=1e-3), "logistic": LogisticRegression(maxIter=50, regParam=1e-3), "linear": LinearRegression(maxIter=50, regParam=1e-3)}[name]
    target = F.col("label").cast("double") if name == "linear" else (F.col("label") > 0).cast("double")
    began = time.perf_counter()
    fitted = solver.fit(train.select(array_to_vector("f").alias("features"), target.alias("label")))
    took = time.perf_counter() - began
    model = Model(fitted.coefficients.toArray(), -float(fitted.intercept))
    return test.select("id", vectors.sign_class(vectors.score(test, model)).alias("class")), took
