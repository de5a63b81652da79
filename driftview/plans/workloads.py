"""The experiments' inputs on the given tables: entities, examples, trails of models."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import islice

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions.features import DenseArray, DenseColumns, FeatureFunction, TermFrequency
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators.view import ClassificationView, ExampleTable, Options, gather
from driftview.session import materialize
from driftview.sources.tables import keyed_lineitem, table

#: Of the examples, in order of id, so many train the warm model and so many come as updates: 4 to 1.
WARM, MEASURED = 160, 40


@dataclass
class Workload:
    """``source`` has (id, label) beside its own columns; ``entities`` is (id, f)."""

    name: str
    source: DataFrame
    feature: FeatureFunction
    trainer: SgdTrainer
    dim: int
    warm: int = WARM
    measured: int = MEASURED
    labelled: DataFrame | None = None

    @property
    def entities(self) -> DataFrame:
        return self.feature.transform(self.source, "id")

    def kept_entities(self) -> DataFrame:
        """The entities written out, for features that cost more than reading them."""
        return materialize(self.entities, "entities")

    def examples(self) -> DataFrame:
        """The first warm + measured labelled ids; a bounded number of rows."""
        rows = self.labelled if self.labelled is not None else self.source.select("id", "label")
        return rows.where("label is not null").orderBy("id").limit(self.warm + self.measured)

    def batch(self) -> list[tuple[int, object, int]]:
        """The examples with their vectors; only their own source rows are turned into vectors."""
        examples = self.examples()
        rows = self.source.drop("label").join(F.broadcast(examples.select("id")), "id", "left_semi")
        return gather(self.feature.transform(rows, "id"), examples)

    def learn_all(self, least: int, **options: object) -> ClassificationView:
        """A view by the whole table of examples, in a stream: the first ``warm`` make the model it starts with, the others come in rounds of a tenth, or of ``least``."""
        entities = self.kept_entities()
        table = ExampleTable.of(entities, self.labelled)
        stream = iter(table)
        model = self.trainer.run(Model.zero(self.dim), ((f, y) for _, f, y in islice(stream, self.warm)))
        view = ClassificationView(entities, self.trainer, self.dim, Options(**options), model)
        view.examples = [table]
        view.learn(stream, max(least, (len(table) - self.warm) // 10))
        return view

    def trail(self, batch: list | None = None) -> list[Model]:
        """The warm model, and the one after each measured example."""
        batch = self.batch() if batch is None else batch
        model = Model.zero(self.dim)
        for _, f, y in batch[: self.warm]:
            model = self.trainer.step(model, f, y)
        models = [model]
        for _, f, y in batch[self.warm :]:
            model = self.trainer.step(model, f, y)
            models.append(model)
        return models


#: Fixed values of the dense workload: columns, and what each is divided by.
LINEITEM = (("l_quantity", "l_extendedprice", "l_discount", "l_tax"), (50.0, 105000.0, 0.1, 0.08))
DENSE_TRAINER = SgdTrainer("hinge", 2.0, 0.01)


def planted_lineitem(spark: SparkSession, sf_dir: str, trainer: SgdTrainer = DENSE_TRAINER) -> Workload:
    """Dense rows of the largest table with a planted class."""
    source = keyed_lineitem(spark, sf_dir).withColumn("id", F.col("ent_id"))
    return Workload("planted_lineitem", source, DenseColumns(*LINEITEM), trainer, 4)


def embeddings_binary(spark: SparkSession, sf_dir: str) -> Workload:
    """Unit vectors whose labels carry no signal: the model never settles."""
    rows = table(spark, sf_dir, "embeddings")
    source = rows.withColumn("id", F.col("vec_id")).withColumn("label", F.when(F.col("label") < 5, 1).otherwise(-1))
    return Workload("embeddings_binary", source, DenseArray("embedding", 64), SgdTrainer("hinge", 0.1, 1e-3), 64)


def text_language(spark: SparkSession, sf_dir: str, first_tokens: int | None = None, norm: str | None = "l2", dim: int = 1 << 16, hash_: str = "xxhash64") -> Workload:
    """English or not, from the first words or all of a document."""
    rows = table(spark, sf_dir, "documents")
    source = rows.withColumn("id", F.col("doc_id")).withColumn("label", F.when(F.col("lang") == "en", 1).otherwise(-1))
    return Workload("text_language", source, TermFrequency("text", dim, norm, first_tokens, hash_), SgdTrainer("hinge", 1.0, 1e-4), dim)


def text_quality(spark: SparkSession, sf_dir: str, dim: int = 1 << 16, hash_: str = "xxhash64", label: str = "quality") -> Workload:
    """Documents with a table of examples of their own, all of which are learned from; of uneven classes the rare one weighs more."""
    rows = table(spark, sf_dir, "documents").withColumn("id", F.col("doc_id"))
    labelled = table(spark, sf_dir, "labels").where(F.col(label).isNotNull()).select(F.col("doc_id").alias("id"), F.when(F.col(label) == 1, 1).otherwise(-1).alias("label"))
    n = labelled.count()
    trainer = SgdTrainer("hinge", 0.3, 1e-4, class_weights=(3.0, 1.0) if label == "quality" else (1.0, 3.0))
    return Workload("text_quality", rows, TermFrequency("text", dim, "l2", None, hash_), trainer, dim, n * 4 // 5, n - n * 4 // 5, labelled)


#: Hashed dimensions that the queries share with their SQL, which has no sparse vectors.
IN_SQL = {"dim": 1024, "hash_": "md5"}


def models_frame(spark: SparkSession, models: list[Model]) -> DataFrame:
    """(round, w, b, prev_w, prev_b): a row for each model, beside the one before."""
    rows = [(k, m.w.tolist(), float(m.b), models[max(0, k - 1)].w.tolist(), float(models[max(0, k - 1)].b)) for k, m in enumerate(models)]
    return spark.createDataFrame(rows, "round int, w array<double>, b double, prev_w array<double>, prev_b double")


def random_ids(entities: DataFrame, n: int) -> DataFrame:
    """``n`` ids in an order that md5 fixes."""
    return entities.select("id").orderBy(F.md5(F.col("id").cast("string").cast("binary")), "id").limit(n)
