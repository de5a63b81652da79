"""Whole runs over a trail of models as DataFrame programs: no loop over rows, few jobs.

Bounds depend on models alone, so they are known before any entity is read.
One scan then counts the bands of all rounds at once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn.model import Model
from driftview.operators.band import HolderPair, in_band, water_marks
from driftview.operators.policy import lazy_waste
from driftview.plans.workloads import models_frame
from driftview.shipping import ship


def _dot(w: Column, f: Column, dim: int) -> Column:
    total = F.lit(0.0)
    for k in range(dim):
        total = total + F.get(w, F.lit(k)) * F.get(f, F.lit(k))
    return total


def round_classes(entities: DataFrame, models: list[Model]) -> DataFrame:
    """(round, n_positive, n_flipped) of every round by scoring every entity under every model: a partial sum for each round and task."""
    spark = entities.sparkSession
    crossed = entities.crossJoin(F.broadcast(models_frame(spark, models)))  # a row for each model, whatever the data
    dim = len(models[0].w)
    now = vectors.sign_class(_dot(F.col("w"), F.col("f"), dim) - F.col("b"))
    before = vectors.sign_class(_dot(F.col("prev_w"), F.col("f"), dim) - F.col("prev_b"))
    return crossed.select("round", now.alias("now"), (now != before).cast("long").alias("flipped")).groupBy("round").agg(F.sum((F.col("now") == 1).cast("long")).alias("n_positive"), F.sum("flipped").alias("n_flipped"))


@dataclass
class RoundBand:
    round: int
    low: float
    high: float
    low_water: float
    high_water: float
    n_band: int
    n_above: int


def band_counts(entities: DataFrame, models: list[Model], stored: int, largest: float, pair: HolderPair, kind: str = "cumulative") -> list[RoundBand]:
    """Rows in the band, and from the low water up, of every round since ``stored``: one scan."""
    marks = water_marks(models, stored, largest, pair.p, kind)
    eps = entities.select(vectors.score(entities, models[stored]).alias("eps"))
    sums = []
    for j, _, _, lw, hw in marks:
        sums += [F.sum(in_band(F.col("eps"), lw, hw).cast("long")).alias(f"band{j}"), F.sum((F.col("eps") >= F.lit(float(lw))).cast("long")).alias(f"above{j}")]
    row = eps.agg(*sums).first()
    return [RoundBand(j, low, high, lw, hw, row[f"band{j}"] or 0, row[f"above{j}"] or 0) for j, low, high, lw, hw in marks]


def replay_rounds(entities: DataFrame, models: list[Model], decide: Callable[[int, float, float], bool], largest: float, n: int, sigma: float = 0.25, pair: HolderPair | None = None, kind: str = "cumulative", lazy: dict[int, int] | None = None) -> list[tuple]:
    """(round, stored, lw, hw, n_band, cost, waste, reclustered) in the rows clock.

    ``decide`` gets the round, the waste and a recluster's cost, n / sigma.  The
    data is scanned once for each clustering, not for each round.  With ``lazy``,
    the sizes of the positive class by round, a round is a read of that class.
    """
    pair = pair or HolderPair()
    cost_all = n / sigma
    out, stored, waste = [], 0, 0.0
    bands = {b.round: b for b in band_counts(entities, models, 0, largest, pair, kind)}
    for i in range(1, len(models)):
        if decide(i, waste, cost_all):
            stored, waste = i, 0.0
            bands = {b.round: b for b in band_counts(entities, models, i, largest, pair, kind)}
            out.append((i, stored, 0.0, 0.0, 0, cost_all, waste, True))
            continue
        b = bands[i]
        cost = float(b.n_band) if lazy is None else lazy_waste(b.n_above, lazy[i], float(b.n_above))
        waste += cost
        out.append((i, stored, b.low_water, b.high_water, b.n_band, cost, waste, False))
    return out


LEDGER = "round int, s int, lw double, hw double, n_band long, cost double, waste double, reclustered boolean"


def ledger_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, LEDGER)


def cost_family(entities: DataFrame, models: list[Model], largest: float, pair: HolderPair | None = None) -> DataFrame:
    """(s, i, n_band) for all s <= i: the rows in the band of round i if the data was clustered at s.

    Cumulative bands of one s are nested, so a margin lies in those from some
    round on.  Tasks find those rounds by binary search, and send a count for
    each pair of rounds.
    """
    pair = pair or HolderPair()
    ship(entities.sparkSession)
    spark, n = entities.sparkSession, len(models)
    marks = [water_marks(models, s, largest, pair.p) for s in range(n)]
    lows, highs = ([np.array([m[k] for m in rows]) for rows in marks] for k in (3, 4))
    weights, biases = np.array([m.w for m in models]), np.array([m.b for m in models])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((n, n + 1), np.int64)
        for batch in batches:
            f = batch.column("f").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            for s in range(n):
                eps = np.zeros(len(f))
                for k in range(f.shape[1]):
                    eps += weights[s, k] * f[:, k]
                eps -= biases[s]
                # marks move outwards: the first round whose low mark is reached, and whose high mark is above
                first = np.maximum(np.searchsorted(-lows[s], -eps, "left"), np.searchsorted(highs[s], eps, "right"))
                sums[s] += np.bincount(s + first, minlength=n + 1)[: n + 1]
        at, to = np.nonzero(sums)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(to, pa.int32()), pa.array(sums[at, to])], ["s", "i", "n"])

    first = entities.select("f").mapInArrow(count, "s int, i int, n long").groupBy("s", "i").agg(F.sum("n").alias("n"))
    grid = spark.range(n).select(F.col("id").cast("int").alias("s")).select("s", F.explode(F.sequence("s", F.lit(n - 1))).alias("i"))
    met = grid.join(first.withColumnRenamed("i", "k").withColumnRenamed("s", "t"), (F.col("s") == F.col("t")) & (F.col("k") <= F.col("i")), "left")
    return met.groupBy("s", "i").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n_band"))


def costs_of(family: DataFrame, n_models: int) -> list[list[float]]:
    """The family as a table on the driver: a number for each pair of rounds."""
    out = [[0.0] * n_models for _ in range(n_models)]
    for r in family.collect():
        out[r["s"]][r["i"]] = float(r["n_band"])
    return out
