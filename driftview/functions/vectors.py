"""Vectors as columns: ARRAY<DOUBLE>, or STRUCT<idx: ARRAY<INT>, val: ARRAY<DOUBLE>>."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf
from pyspark.sql.types import ArrayType, StructType

from driftview.learn.model import Model

#: Up to this many dimensions a dot product is written out term by term and stays in generated code.
UNROLL = 128


def is_sparse(df: DataFrame, column: str = "f") -> bool:
    kind = df.schema[column].dataType
    if isinstance(kind, StructType):
        return True
    if isinstance(kind, ArrayType):
        return False
    raise TypeError(f"{column} is {kind.simpleString()}, not a vector")


def dense_score(f: Column, model: Model) -> Column:
    """w.f - b over a dense column."""
    if len(model.w) > UNROLL:
        return _arrow_dense(model)(f)
    total = F.lit(0.0)
    for k, weight in enumerate(model.w.tolist()):
        total = total + F.lit(weight) * F.get(f, F.lit(k))
    return total - F.lit(float(model.b))


def _arrow_dense(model: Model):  # noqa: ANN202
    w, b = model.w, float(model.b)

    @arrow_udf("double")
    def score(f: pa.Array) -> pa.Array:
        flat = f.flatten().to_numpy(zero_copy_only=False)
        return pa.array(flat.reshape(-1, len(w)) @ w - b if len(w) and len(flat) else np.full(len(f), -b))

    return score


def _arrow_sparse(model: Model):  # noqa: ANN202
    w, b = model.w, float(model.b)

    @arrow_udf("double")
    def score(idx: pa.Array, val: pa.Array) -> pa.Array:
        sizes = np.asarray(idx.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
        terms = w[idx.flatten().to_numpy(zero_copy_only=False)] * val.flatten().to_numpy(zero_copy_only=False)
        sums = np.bincount(np.repeat(np.arange(len(sizes)), sizes), terms, len(sizes)) if len(terms) else np.zeros(len(sizes))
        return pa.array(sums - b)

    return score


def arrow_scores(df: DataFrame, models: Sequence[Model], column: str = "f") -> Column:
    """Margins under several models, as an array, in one pass."""
    w, b = np.stack([m.w for m in models]), np.array([float(m.b) for m in models])

    def listed(z: np.ndarray) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.arange(0, z.size + 1, len(b)), pa.int32()), pa.array(z.reshape(-1)))

    @arrow_udf("array<double>")
    def dense(f: pa.Array) -> pa.Array:
        flat = f.flatten().to_numpy(zero_copy_only=False).reshape(len(f), -1)
        return listed(flat @ w.T - b if flat.size else np.tile(-b, (len(f), 1)))

    @arrow_udf("array<double>")
    def sparse(idx: pa.Array, val: pa.Array) -> pa.Array:
        sizes = np.asarray(idx.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
        at, x, who = idx.flatten().to_numpy(zero_copy_only=False), val.flatten().to_numpy(zero_copy_only=False), np.repeat(np.arange(len(sizes)), sizes)
        return listed(np.stack([np.bincount(who, row[at] * x, len(sizes)) for row in w], axis=1) - b)

    f = F.col(column)
    return sparse(f["idx"], f["val"]) if is_sparse(df, column) else dense(f)


def score(df: DataFrame, model: Model, column: str = "f") -> Column:
    """The margin of each row; rows outside a filter beneath never reach it."""
    f = F.col(column)
    return _arrow_sparse(model)(f["idx"], f["val"]) if is_sparse(df, column) else dense_score(f, model)


def sign_class(eps: Column) -> Column:
    """1 where the margin is not negative, else -1."""
    return F.when(eps >= 0, 1).otherwise(-1)


def norm(values: Column, q: float) -> Column:
    """The q-norm of an array of doubles; 0 for an empty one."""
    if math.isinf(q):
        return F.coalesce(F.array_max(F.transform(values, F.abs)), F.lit(0.0))
    start = F.lit(0.0)
    if q == 1:
        return F.aggregate(values, start, lambda a, x: a + F.abs(x))
    if q == 2:
        return F.sqrt(F.aggregate(values, start, lambda a, x: a + x * x))
    return F.pow(F.aggregate(values, start, lambda a, x: a + F.pow(F.abs(x), q)), 1.0 / q)


def vector_norm(df: DataFrame, q: float, column: str = "f") -> Column:
    return norm(F.col(column)["val"] if is_sparse(df, column) else F.col(column), q)


def normalized(values: Column, q: float) -> Column:
    """The array over its q-norm; a zero vector stays."""
    # the size is bound to a name first: written inside the lambda it would be computed for each element
    bound = F.array(F.struct(values.alias("v"), norm(values, q).alias("size")))
    return F.get(F.transform(bound, lambda b: F.transform(b["v"], lambda x: F.when(b["size"] > 0, x / b["size"]).otherwise(x))), F.lit(0))


def max_norm(df: DataFrame, q: float, column: str = "f") -> float:
    """The largest q-norm of all rows, 0 without rows: one scan."""
    return df.agg(F.max(vector_norm(df, q, column))).first()[0] or 0.0


def usable(df: DataFrame, dim: int, q: float, key: str = "id", column: str = "f") -> Column:
    """Whether a row can be an entity: its key is not null, its vector is of ``dim`` dimensions, and its q-norm is a finite number.

    A vector that is null, or holds a null, a NaN or an infinite value, is not
    usable.  NaN is larger than any number here, so one comparison tells.
    """
    f = F.col(column)
    if is_sparse(df, column):
        idx = f["idx"]
        shape = (F.size(idx) == F.size(f["val"])) & (F.coalesce(F.array_min(idx), F.lit(0)) >= 0) & (F.coalesce(F.array_max(idx), F.lit(0)) < dim)
    else:
        shape = F.size(f) == dim
    # a null among the values makes a sum null, but the largest of absolute values passes over it
    holds_null = F.exists(f["val"] if is_sparse(df, column) else f, F.isnull) if math.isinf(q) else F.lit(False)
    return F.coalesce(F.col(key).isNotNull() & shape & (vector_norm(df, q, column) < F.lit(math.inf)) & ~holds_null, F.lit(False))


def score_sql(model: Model, column: str = "f") -> str:
    """``dense_score`` as SQL text, which takes one call to build."""
    terms = "".join(f" + {weight!r}D * get({column}, {k})" for k, weight in enumerate(model.w.tolist()))
    return f"0D{terms} - {float(model.b)!r}D"


def register_sql(spark: SparkSession) -> None:
    """SQL functions for users: mv_score, mv_class, mv_certain and mv_norm (1 and 2; 0 stands for the largest)."""
    array = "ARRAY<DOUBLE>"
    for text in (
        f"mv_score(f {array}, w {array}, b DOUBLE) RETURNS DOUBLE RETURN aggregate(zip_with(f, w, (x, y) -> x * y), 0D, (a, x) -> a + x) - b",
        "mv_class(eps DOUBLE) RETURNS INT RETURN IF(eps >= 0, 1, -1)",
        "mv_certain(eps DOUBLE, lw DOUBLE, hw DOUBLE) RETURNS INT RETURN CASE WHEN eps >= hw THEN 1 WHEN eps < lw THEN -1 END",
        f"mv_norm(f {array}, q INT) RETURNS DOUBLE RETURN CASE WHEN q = 1 THEN aggregate(f, 0D, (a, x) -> a + abs(x)) WHEN q = 2 THEN sqrt(aggregate(f, 0D, (a, x) -> a + x * x)) ELSE array_max(transform(f, x -> abs(x))) END",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
