"""Feature functions: from rows to vectors in a column ``f``.

Each has ``fit(df)``, which returns itself with what it learned from the corpus,
and ``transform(df, key)``, which returns (id, f).  Null texts give zero vectors.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf

from driftview.functions import vectors

SPLIT = r"[^\p{L}\p{N}]+"


def terms(text: Column, first: int | None = None) -> Column:
    """Words in order, in lower case; the first so many if asked for."""
    found = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SPLIT), lambda t: t != "")
    return F.slice(found, 1, first) if first else found


def slot(term: Column, dim: int, hash_: str = "xxhash64") -> Column:
    """A term's slot; ``md5`` is slower, but other engines have it too."""
    if hash_ == "md5":
        return (F.conv(F.substring(F.md5(term.cast("binary")), 1, 8), 16, 10).cast("long") % dim).cast("int")
    return F.pmod(F.xxhash64(term), F.lit(dim)).cast("int")


def sparse(pairs: Column) -> Column:
    """A sparse vector from an array of (idx, val) of distinct indexes."""
    ordered = F.array_sort(pairs)
    return F.struct(F.transform(ordered, lambda p: p["idx"]).alias("idx"), F.transform(ordered, lambda p: p["val"]).alias("val"))


class FeatureFunction:
    dim: int

    def fit(self, df: DataFrame) -> FeatureFunction:
        return self

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        raise NotImplementedError


@dataclass(frozen=True)
class TermFrequency(FeatureFunction):
    """Word counts in ``dim`` hashed slots, over their sum (``l1``), length (``l2``) or as they are."""

    column: str
    dim: int = 1 << 18
    norm: str | None = "l1"
    first_tokens: int | None = None
    hash_: str = "xxhash64"

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        slots = F.transform(terms(F.col(self.column), self.first_tokens), lambda t: slot(t, self.dim, self.hash_))
        counted = df.select(F.col(key).alias("id"), _counts(slots).alias("f"))
        return counted.select("id", _normed(self.norm).alias("f"))

    def long_form(self, df: DataFrame, key: str) -> DataFrame:
        """(id, term, val) with the words themselves: one row for each word of a text."""
        rows = df.select(F.col(key).alias("id"), F.explode(terms(F.col(self.column), self.first_tokens)).alias("term"))
        counts = rows.groupBy("id", "term").agg(F.count("*").cast("double").alias("val"))
        if not self.norm:
            return counts
        size = counts.groupBy("id").agg((F.sum("val") if self.norm == "l1" else F.sqrt(F.sum(F.col("val") * F.col("val")))).alias("size"))
        return counts.join(size, "id").select("id", "term", (F.col("val") / F.col("size")).alias("val"))


def _counts(slots: Column) -> Column:
    """Counts of equal values of a sorted array, within the row."""
    ordered = F.array_sort(slots)
    empty = F.struct(F.array().cast("array<int>").alias("idx"), F.array().cast("array<double>").alias("val"))

    @arrow_udf("struct<idx: array<int>, val: array<double>>")
    def count(lists: pa.Array) -> pa.Array:
        flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
        sizes = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
        who = np.repeat(np.arange(len(sizes)), sizes)
        new = np.ones(len(flat), bool)
        new[1:] = (flat[1:] != flat[:-1]) | (who[1:] != who[:-1])
        at = np.flatnonzero(new)
        val = np.diff(np.append(at, len(flat))).astype(float)
        ends = pa.array(np.append(0, np.cumsum(np.bincount(who[at], minlength=len(sizes)))), pa.int32())
        return pa.StructArray.from_arrays([pa.ListArray.from_arrays(ends, pa.array(flat[at], pa.int32())), pa.ListArray.from_arrays(ends, pa.array(val))], ["idx", "val"])

    return F.coalesce(count(ordered), empty)


def _normed(kind: str | None) -> Column:
    f = F.col("f")
    if not kind:
        return f
    return F.struct(f["idx"].alias("idx"), vectors.normalized(f["val"], 1 if kind == "l1" else 2).alias("val"))


@dataclass(frozen=True)
class TfIdf(FeatureFunction):
    """Word counts times log((n + 1) / (df + 1)) + 1; document frequencies by slot come from a pass over the corpus and can be added to."""

    column: str
    dim: int = 1 << 16
    n_docs: int = 0
    frequencies: np.ndarray = field(default=None, repr=False)

    def _frequencies(self, df: DataFrame) -> np.ndarray:
        slots = df.select(F.explode(F.array_distinct(F.transform(terms(F.col(self.column)), lambda t: slot(t, self.dim)))).alias("slot"))
        rows = slots.groupBy("slot").count().toArrow()  # dim rows at most
        out = np.zeros(self.dim, np.int64)
        out[rows["slot"].to_numpy()] = rows["count"].to_numpy()
        return out

    def fit(self, df: DataFrame) -> TfIdf:
        return replace(self, n_docs=df.count(), frequencies=self._frequencies(df))

    def update(self, df: DataFrame) -> TfIdf:
        """With the frequencies of more documents added."""
        base = np.zeros(self.dim, np.int64) if self.frequencies is None else self.frequencies
        return replace(self, n_docs=self.n_docs + df.count(), frequencies=base + self._frequencies(df))

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        idf = np.log((self.n_docs + 1.0) / (self.frequencies + 1.0)) + 1.0

        @arrow_udf("array<double>")
        def weigh(idx: pa.Array, val: pa.Array) -> pa.Array:
            weighted = idf[idx.flatten().to_numpy(zero_copy_only=False)] * val.flatten().to_numpy(zero_copy_only=False)
            sizes = idx.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
            return pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(sizes)), pa.int32()), pa.array(weighted))

        counts = TermFrequency(self.column, self.dim, None).transform(df, key)
        f = F.col("f")
        weighted = counts.select("id", F.struct(f["idx"].alias("idx"), weigh(f["idx"], f["val"]).alias("val")).alias("f"))
        return weighted.select("id", _normed("l2").alias("f"))

    @staticmethod
    def long_form(df: DataFrame, key: str, column: str) -> DataFrame:
        """(id, term, val) over the words themselves; frequencies meet counts in a join."""
        counts = TermFrequency(column, norm=None).long_form(df, key)
        n = df.agg(F.count("*").alias("n"))
        idf = counts.groupBy("term").agg(F.count("*").alias("df")).crossJoin(F.broadcast(n)).select("term", (F.log((F.col("n") + 1) / (F.col("df") + 1)) + 1).alias("idf"))
        return counts.join(idf, "term").select("id", "term", (F.col("val") * F.col("idf")).alias("val"))


@dataclass(frozen=True)
class DenseColumns(FeatureFunction):
    """Numeric columns, each divided by its scale."""

    columns: tuple[str, ...]
    scale: tuple[float, ...] | None = None
    norm: str | None = None

    @property
    def dim(self) -> int:
        return len(self.columns)

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        scale = self.scale or (1.0,) * len(self.columns)
        f = F.array(*[F.coalesce(F.col(c).cast("double"), F.lit(0.0)) / F.lit(float(s)) for c, s in zip(self.columns, scale, strict=True)])
        f = vectors.normalized(f, 1 if self.norm == "l1" else 2) if self.norm else f
        return df.select(F.col(key).alias("id"), f.alias("f"))


@dataclass(frozen=True)
class DenseArray(FeatureFunction):
    column: str
    dim: int

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        return df.select(F.col(key).alias("id"), F.transform(F.col(self.column), lambda x: x.cast("double")).alias("f"))


@dataclass(frozen=True)
class OneHot(FeatureFunction):
    """A slot for each value of each column, by hash of name and value."""

    columns: tuple[str, ...]
    dim: int = 1 << 16

    def pairs(self) -> Column:
        """name=value of each column that is not null."""
        return F.array_compact(F.array(*[F.when(F.col(c).isNotNull(), F.concat_ws("=", F.lit(c), F.col(c).cast("string"))) for c in self.columns]))

    def long_form(self, df: DataFrame, key: str) -> DataFrame:
        """(id, term, val) with the pairs themselves."""
        return df.select(F.col(key).alias("id"), F.explode(F.array_distinct(self.pairs())).alias("term"), F.lit(1.0).alias("val"))

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        slots = F.transform(self.pairs(), lambda t: slot(t, self.dim))
        return df.select(F.col(key).alias("id"), F.array_distinct(slots).alias("s")).select("id", sparse(F.transform("s", lambda s: F.struct(s.alias("idx"), F.lit(1.0).alias("val")))).alias("f"))


def _plus(n: int) -> Callable[[Column], Column]:
    return lambda i: i + n


@dataclass(frozen=True)
class Concat(FeatureFunction):
    """Several feature functions side by side; dense parts become sparse ones."""

    parts: tuple[FeatureFunction, ...]

    @property
    def dim(self) -> int:
        return sum(p.dim for p in self.parts)

    def fit(self, df: DataFrame) -> Concat:
        return Concat(tuple(p.fit(df) for p in self.parts))

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        joined, offset, names = None, 0, []
        for k, part in enumerate(self.parts):
            rows = part.transform(df, key)
            f = F.col("f") if vectors.is_sparse(rows) else F.struct(F.sequence(F.lit(0), F.size("f") - 1).alias("idx"), F.col("f").alias("val"))
            moved = F.transform(f["idx"], _plus(offset))
            rows = rows.select("id", F.struct(moved.alias("idx"), f["val"].alias("val")).alias(f"f{k}"))
            joined = rows if joined is None else joined.join(rows, "id")
            names.append(f"f{k}")
            offset += part.dim
        idx, val = (F.concat(*[F.col(n)[x] for n in names]) for x in ("idx", "val"))
        return joined.select("id", F.struct(idx.alias("idx"), val.alias("val")).alias("f"))


@dataclass(frozen=True)
class Polynomial2(FeatureFunction):
    """All products of two values of a dense vector, and the values: the feature map of a polynomial kernel of degree 2."""

    base: FeatureFunction

    @property
    def dim(self) -> int:
        return self.base.dim + self.base.dim * (self.base.dim + 1) // 2

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        d = self.base.dim
        f = F.col("f")
        products = [f[i] * f[j] for i in range(d) for j in range(i, d)]
        return self.base.transform(df, key).select("id", F.concat(f, F.array(*products)).alias("f"))


@dataclass(frozen=True)
class RandomFourier(FeatureFunction):
    """Random cosines whose products approximate the kernel exp(-gamma |x - y|^2); the seed fixes them."""

    base: FeatureFunction
    dim: int = 64
    gamma: float = 1.0
    seed: int = 5

    def draws(self) -> tuple[np.ndarray, np.ndarray]:
        rng = np.random.default_rng(self.seed)
        return rng.normal(0.0, np.sqrt(2.0 * self.gamma), (self.base.dim, self.dim)), rng.uniform(0.0, 2.0 * np.pi, self.dim)

    def transform(self, df: DataFrame, key: str) -> DataFrame:
        omega, phase = self.draws()
        d, n = omega.shape

        @arrow_udf("array<double>")
        def cosines(f: pa.Array) -> pa.Array:
            x = f.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            y = np.sqrt(2.0 / n) * np.cos(x @ omega + phase)
            return pa.ListArray.from_arrays(pa.array(np.arange(0, len(f) * n + 1, n), pa.int32()), pa.array(y.reshape(-1)))

        return self.base.transform(df, key).select("id", cosines("f").alias("f"))


def kernel_error(base: FeatureFunction, fourier: RandomFourier, df: DataFrame, key: str, anchors: int) -> DataFrame:
    """(n, mean_error, max_error) of the map's products against the kernel, of all rows with the first ``anchors`` by key."""
    rows = fourier.transform(df, key).withColumnRenamed("f", "phi").join(base.transform(df, key).withColumnRenamed("f", "x"), "id")
    few = rows.orderBy("id").limit(anchors).select(F.col("phi").alias("phi_a"), F.col("x").alias("x_a"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, v: s + v)
    product = total(F.zip_with("phi", "phi_a", lambda a, b: a * b))
    distance = total(F.zip_with("x", "x_a", lambda a, b: (a - b) * (a - b)))
    error = F.abs(product - F.exp(F.lit(-fourier.gamma) * distance))
    return rows.crossJoin(F.broadcast(few)).select(error.alias("e")).agg(F.count("*").alias("n"), F.round(F.avg("e"), 6).alias("mean_error"), F.round(F.max("e"), 6).alias("max_error"))


_REGISTRY: dict[str, Callable[..., FeatureFunction]] = {
    "tf_bag_of_terms": TermFrequency,
    "tf_idf": TfIdf,
    "dense_columns": lambda *columns, **kw: DenseColumns(tuple(columns), **kw),
    "dense_array": DenseArray,
    "one_hot": lambda *columns, **kw: OneHot(tuple(columns), **kw),
    "polynomial_kernel": lambda *columns, **kw: Polynomial2(DenseColumns(tuple(columns), **kw)),
    "gaussian_kernel": lambda *columns, dim=64, gamma=1.0, seed=5, **kw: RandomFourier(DenseColumns(tuple(columns), **kw), dim, gamma, seed),
}


def register_feature(name: str, make: Callable[..., FeatureFunction]) -> None:
    """Make a feature function known to declarations by name."""
    _REGISTRY[name] = make


def get_feature(name: str, *args: object, **kw: object) -> FeatureFunction:
    if name not in _REGISTRY:
        raise ValueError(f"unknown feature function {name!r}; known: {', '.join(sorted(_REGISTRY))}")
    return _REGISTRY[name](*args, **kw)
