"""A maintained view with more than two classes: one linear model a class, the class of the largest score."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn import multiclass
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators.band import norm
from driftview.operators.policy import RentOrBuy, lazy_waste
from driftview.operators.store import ClusteredStore
from driftview.operators.view import MAX_BATCH, Options, Step, as_vector, computed_once
from driftview.session import shared_path


def lead_lost(stored: Sequence[Model], current: Sequence[Model], largest: float, p: float) -> np.ndarray:
    """For each class, the lead that a row of it can have lost to some rival since the models were stored.

    A score moves by dw.f - db, which lies within largest * |dw| of -db; the lead
    of class a over r shrinks by at most (R_a + db_a) + (R_r - db_r).
    """
    reach = np.array([largest * norm(c.w - s.w, p) for s, c in zip(stored, current, strict=True)])
    shift = np.array([c.b - s.b for s, c in zip(stored, current, strict=True)])
    rival = reach - shift
    return np.array([reach[a] + shift[a] + np.delete(rival, a).max() for a in range(len(reach))])


class MulticlassView:
    """(id, class) by the largest of several scores, ties by the smaller class, exact after each round.

    The base is clustered by the lead, the largest stored score less the second
    largest.  A row whose lead is larger than what its class can have lost since
    keeps its class, so a round scores only rows of small lead; the bound is the
    largest of all rounds since the models were stored.  Of the rows in the band,
    those whose stored scores settle the class for each rival by itself are not
    scored either.  What the bands cost is added up, and the data is clustered
    anew by the same rule as in a view of two classes.

    ``classes`` are in order, smaller first.  Rows that cannot be entities are
    set aside as in a view of two classes.  Arrivals, changes and removals of
    entities cluster anew.
    """

    def __init__(self, entities: DataFrame, trainer: SgdTrainer, dim: int, classes: Sequence[object], options: Options | None = None, models: Sequence[Model] | None = None, path: str | None = None, name: str = "view") -> None:
        self.spark, self.trainer, self.dim, self.name = entities.sparkSession, trainer, dim, name
        self.classes, self.options = list(classes), options or Options()
        if len(self.classes) < 2:
            raise ValueError("a view needs two classes at least")
        self.path = path or shared_path(self.spark, name)
        self.entities = self._usable(computed_once(entities, f"{self.path}/given"))
        self.models = list(models or [Model.zero(dim)] * len(self.classes))
        self.round = self.version = 0
        self.history: list[Step] = []
        self.rule = RentOrBuy(self.options.alpha)
        self.overlay: DataFrame | None = None
        self.store: ClusteredStore | None = None
        self._recluster()

    @classmethod
    def create(cls, entities: DataFrame, examples: DataFrame, trainer: SgdTrainer, dim: int, classes: Sequence[object], options: Options | None = None, **more: object) -> MulticlassView:
        """A view trained on the examples (id, label) there are, in order of id."""
        if entities.groupBy("id").count().where("count > 1").limit(1).count():
            raise ValueError("ids of entities are not unique")
        o = options or Options()
        batch = gather_labels(entities.where(vectors.usable(entities, dim, o.pair.q)), examples)
        return cls(entities, trainer, dim, classes, o, train(trainer, [Model.zero(dim)] * len(classes), batch, classes), **more)

    def _usable(self, rows: DataFrame) -> DataFrame:
        rows = rows.select("id", "f")
        return rows.where(vectors.usable(rows, self.dim, self.options.pair.q))

    # --- rounds

    def update(self, examples: Iterable[tuple[int, object, object]]) -> Step | None:
        """One round: train every class on a batch of (id, vector, label), then do what the policy asks for."""
        self.models = train(self.trainer, self.models, list(examples), self.classes)
        self.round += 1
        if self.options.policy == "eager" and self.rule.decide():
            return self._recluster()
        lost = lead_lost(self.stored, self.models, self.largest, self.options.pair.p)
        self.lost = np.maximum(self.lost, lost + self._slack())
        return self._incremental() if self.options.policy == "eager" else self._name()

    def add_examples(self, examples: DataFrame) -> Step | None:
        return self.update(gather_labels(self.entities, examples))

    def _slack(self) -> float:
        return 2e-9 * (1.0 + max(self.largest * norm(m.w, self.options.pair.p) + abs(m.b) for m in self.models))

    def _recluster(self) -> Step:
        o, old = self.options, self.store
        self.version += 1
        self.stored, self.stored_round = list(self.models), self.round
        scores = multiclass.scores(self.entities, self.stored)
        rows = self.entities.select("id", "f", scores.alias("scores"), vectors.vector_norm(self.entities, o.pair.q).alias("norm_q"))
        sorted_ = F.sort_array("scores", asc=False)
        leader = (F.array_position("scores", F.array_max("scores")) - 1).cast("int")
        rows = rows.select("id", "f", (sorted_[0] - sorted_[1]).alias("eps"), "norm_q", "scores", leader.alias("leader"))
        self.store = ClusteredStore.place(rows, f"{self.path}/v={self.version}/base", o.buckets, "clustered", o.arch == "memory", self.entities, "scores array<double>, leader int")
        if old is not None:
            old.evict()
        self.n, self.largest = self.store.n, self.store.largest
        self.lost = np.full(len(self.classes), -np.inf)
        self._overlay(None)
        self.rule.reclustered(self.n / o.sigma)
        step = Step(self.round, self.stored_round, 0.0, 0.0, 0, 0, self.n / o.sigma, 0.0, True)
        if self.round:
            self.history.append(step)
        self._name()
        return step

    def _overlay(self, rows: DataFrame | None) -> None:
        if self.overlay is not None and self.options.arch == "memory":
            self.overlay.unpersist()
        self.overlay = rows

    def _open(self) -> Column:
        """Whether a row's lead is within what its class can have lost."""
        return F.col("eps") <= F.element_at(F.lit([float(x) for x in self.lost]), F.col("leader") + 1)

    def band(self) -> DataFrame:
        """Rows of the base whose class their lead does not settle."""
        widest = float(self.lost.max())
        if widest < 0:
            return self.store.read().where(F.lit(False))
        return self.store.between(None, float(np.nextafter(widest, np.inf))).where(self._open())

    def _labelled(self, rows: DataFrame) -> DataFrame:
        """(id, class) of rows of the band, scored only where rivals are not ruled out one by one."""
        sure = multiclass.multiclass_certain(self.stored, self.models, self.classes, self.largest, self.options.pair, slack=self._slack())
        rows = rows.select("id", sure.alias("sure"), "f")
        certain, open_ = rows.where("sure is not null").select("id", F.col("sure").alias("class")), rows.where("sure is null")
        return certain.unionByName(multiclass.classify(open_, self.models, self.classes))

    def _incremental(self) -> Step:
        labelled = self._labelled(self.band())
        if self.options.arch == "memory":
            overlay = labelled.persist(StorageLevel.MEMORY_AND_DISK)
        else:
            target = f"{self.path}/v={self.version}/overlay/round={self.round}"
            labelled.write.parquet(target)
            overlay = self.spark.read.schema(labelled.schema).parquet(target)
        n = overlay.count()
        self._overlay(overlay)
        self.rule.charge(float(n))
        step = Step(self.round, self.stored_round, 0.0, float(self.lost.max()), n, 0, float(n), self.rule.waste, False)
        self.history.append(step)
        self._name()
        return step

    # --- entities

    def add_entities(self, rows: DataFrame) -> Step:
        """New entities, and changed ones, which replace those of the same id."""
        rows = self._usable(rows)
        return self._change(self.entities.join(rows.select("id"), "id", "left_anti").unionByName(rows))

    def delete_entities(self, ids: DataFrame) -> Step:
        return self._change(self.entities.join(ids.select("id"), "id", "left_anti"))

    def _change(self, entities: DataFrame) -> Step:
        path = f"{self.path}/v={self.version + 1}/entities"
        entities.write.parquet(path)
        self.entities = self.spark.read.schema(entities.schema).parquet(path)
        self.round += 1
        return self._recluster()

    # --- reads

    def view(self) -> DataFrame:
        """(id, class): leaders outside the band, and the band."""
        label = F.element_at(F.array(*[F.lit(c) for c in self.classes]), F.col("leader") + 1).alias("class")
        if self.lost.max() < 0:
            return self.store.read().select("id", label)
        sure = self.store.read().where(~self._open()).select("id", label)
        return sure.unionByName(self.overlay if self.overlay is not None else self._labelled(self.band()))

    def all_members(self, cls: object) -> DataFrame:
        return self.view().where(F.col("class") == F.lit(cls)).select("id")

    def count_members(self, cls: object) -> int:
        """Size of a class; a lazy view charges what the read wasted on rows of the band that are not in it."""
        lazy = self.options.policy == "lazy"
        if lazy and self.rule.decide():
            self._recluster()
        n = self.all_members(cls).count()
        if lazy and self.lost.max() >= 0:
            sure = self.store.read().where(~self._open() & (F.col("leader") == self.classes.index(cls))).count()
            read = sure + self.band().count()
            self.rule.charge(lazy_waste(read, n, float(read)))
            self.history.append(Step(self.round, self.stored_round, 0.0, float(self.lost.max()), read, n, float(read), self.rule.waste, False))
        return n

    def label_of_many(self, ids: DataFrame) -> DataFrame:
        return self.view().join(ids.select("id"), "id", "left_semi")

    def exact(self) -> DataFrame:
        """A full relabel under the current models."""
        return multiclass.classify(self.entities, self.models, self.classes)

    def _name(self) -> None:
        self.view().createOrReplaceTempView(self.name)


def train(trainer: SgdTrainer, models: Sequence[Model], batch: Sequence[tuple[int, object, object]], classes: Sequence[object]) -> list[Model]:
    """Every class's model after a batch, its own examples against all others."""
    return [trainer.run(m, [(f, 1 if label == c else -1) for _, f, label in batch]) for m, c in zip(models, classes, strict=True)]


def gather_labels(entities: DataFrame, examples: DataFrame) -> list[tuple[int, object, object]]:
    """Vectors and labels of a batch of examples (id, label), in order of id."""
    n = examples.count()
    if n > MAX_BATCH:
        raise ValueError(f"{n} examples in one batch; train in batches of {MAX_BATCH} at most")
    rows = entities.join(F.broadcast(examples.select("id", "label").where("label is not null")), "id").select("id", "f", "label").orderBy("id")
    return [(r["id"], as_vector(r["f"]), r["label"]) for r in rows.toLocalIterator()]
