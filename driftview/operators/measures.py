"""Accuracy, band, read and memory measures, and timings."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.operators.store import full_bytes, hybrid_bytes


def quality(view: DataFrame, truth: DataFrame) -> DataFrame:
    """(n, tp, fp, fn, tn, accuracy, precision, recall, f1) of a view against (id, label)."""
    rows = view.join(truth.select("id", "label"), "id")
    count = lambda y, c: F.sum(((F.col("label") == y) & (F.col("class") == c)).cast("long"))
    sums = rows.agg(F.count("*").alias("n"), count(1, 1).alias("tp"), count(-1, 1).alias("fp"), count(1, -1).alias("fn"), count(-1, -1).alias("tn"))
    ratio = lambda a, b: F.when(b > 0, F.round(a / b, 6)).otherwise(F.lit(0.0))
    tp, fp, fn, tn = (F.col(c) for c in ("tp", "fp", "fn", "tn"))
    return sums.select("n", "tp", "fp", "fn", "tn", ratio(tp + tn, F.col("n")).alias("accuracy"), ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fn).alias("recall"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"))


def diff_with_exact(view: DataFrame, exact: DataFrame) -> DataFrame:
    """Rows that one has and the other has not; empty for a view that is right."""
    return view.exceptAll(exact).unionByName(exact.exceptAll(view))


def dataset_stats(entities: DataFrame, name: str) -> DataFrame:
    """(dataset, n_entities, n_features, mean_nonzero) of (id, f)."""
    if vectors.is_sparse(entities):
        rows = entities.select(F.size("f.val").alias("nz"), F.array_max("f.idx").alias("top"))
    else:
        rows = entities.select(F.size(F.filter("f", lambda x: x != 0)).alias("nz"), (F.size("f") - 1).alias("top"))
    return rows.agg(F.lit(name).alias("dataset"), F.count("*").alias("n_entities"), (F.max("top") + 1).cast("long").alias("n_features"), F.round(F.avg("nz"), 6).alias("mean_nonzero"))


def band_stats(history: DataFrame, n: int) -> DataFrame:
    """Mean and deviation of the band over incremental rounds, its share of the entities, and flips for each round."""
    rows = history.where("not reclustered")
    return rows.agg(F.round(F.avg("n_band"), 6).alias("mean_band"), F.round(F.stddev_pop("n_band"), 6).alias("sd_band"), F.round(F.avg("n_band") / F.lit(n), 6).alias("share"), F.round(F.avg("n_flipped"), 6).alias("mean_flips"))


def source_stats(labels: DataFrame) -> DataFrame:
    """(source, n, share) of a batch of single reads."""
    total = F.sum("n").over(Window.partitionBy())  # a row for each source
    return labels.groupBy("source").agg(F.count("*").alias("n")).select("source", "n", F.round(F.col("n") / total, 6).alias("share"))


def memory_stats(n: int, buffered: int, key: int, feature: int) -> dict[str, float]:
    total, whole = hybrid_bytes(n, buffered, key, feature), full_bytes(n, key, feature)
    return {"margin_map": (key + 8) * n, "hybrid": total, "whole": whole, "ratio": whole / max(1, (key + 8) * n)}


def rel_std(values: Sequence[float]) -> float:
    mean = sum(values) / len(values)
    return math.sqrt(sum((v - mean) ** 2 for v in values) / len(values)) / mean if mean else 0.0


def speedups(rates: dict[str, float], base: str) -> dict[str, float]:
    return {k: v / rates[base] for k, v in rates.items()}
