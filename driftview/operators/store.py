"""Entities clustered by their margin under the stored model, as parquet directories by margin range.

A range read on the margin opens only the directories that the range meets, and
within them only the row groups; the wide vector is read only where a plan
names it.
"""

from __future__ import annotations

import json
from bisect import bisect_right
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.functions import vectors
from driftview.learn.model import Model


#: Rows that a task places at most, but for ranges that are uneven.
ROWS_PER_TASK = 1_000_000
#: Error of the quantile that cuts the buffer: 1 over this.
QUANTILE_STEPS = 20_000
#: Entities of a buffer whose keys one task may merge, 16 bytes each.
SORTED_BUFFER = 100_000


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """Write a small file in whatever store the path names, under another name first."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target, draft = jvm.org.apache.hadoop.fs.Path(path), jvm.org.apache.hadoop.fs.Path(f"{path}.draft")
    files = target.getFileSystem(conf)
    out = files.create(draft, True)
    out.write(bytearray(text, "utf-8"))
    out.close()
    files.delete(target, False)
    files.rename(draft, target)


def read_text(spark: SparkSession, path: str) -> str | None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    files = target.getFileSystem(conf)
    if not files.exists(target):
        return None
    source = files.open(target)
    try:
        return jvm.org.apache.commons.io.IOUtils.toString(source, "UTF-8")
    finally:
        source.close()


def bucket_of(eps: Column, splits: Sequence[float]) -> Column:
    """Number of the margin range, from 0: how many splits the margin reaches."""
    if not splits:
        return F.lit(0)
    return F.size(F.filter(F.lit(list(map(float, splits))), lambda s: s <= eps))


@dataclass
class ClusteredStore:
    """``layout`` clustered keeps the vectors by margin; slim keeps (id, eps, norm) by margin, and the vectors where they are."""

    spark: SparkSession
    path: str
    splits: list[float]
    layout: str = "clustered"
    entities: DataFrame | None = field(default=None, repr=False)
    counts: list[int] = field(default_factory=list)
    frame: DataFrame | None = field(default=None, repr=False)
    sparse: bool = False
    listed: DataFrame | None = field(default=None, repr=False)
    n: int = 0
    largest: float = 0.0
    extra: str = ""

    @classmethod
    def build(cls, entities: DataFrame, model: Model, path: str, q: float = 2.0, buckets: int = 16, layout: str = "clustered", memory: bool = False) -> ClusteredStore:
        """Score, place by margin, sort within and write; with ``memory``, keep the same in memory, where it can be dropped and made again.

        One pass counts the rows and finds the quantiles, a second places them.
        Ranges of margins are dealt to tasks in order; a range of many rows, such
        as that of a model which knows nothing yet, to several.  Files carry a
        filter on the id, so that a look-up opens few of them.
        """
        scored = entities.select("id", "f", vectors.score(entities, model).alias("eps"), vectors.vector_norm(entities, q).alias("norm_q"))
        return cls.place(scored, path, buckets, layout, memory, entities)

    @classmethod
    def place(cls, scored: DataFrame, path: str, buckets: int, layout: str, memory: bool, entities: DataFrame, extra: str = "") -> ClusteredStore:
        """Rows (id, f, eps, norm_q) and columns named in ``extra``, clustered by eps."""
        spark = entities.sparkSession
        cuts = [k / buckets for k in range(1, buckets)]
        quantiles = F.percentile_approx("eps", F.array(*map(F.lit, cuts)), 1000) if cuts else F.lit(None)
        n, largest, found = scored.agg(F.count("*"), F.max("norm_q"), quantiles).first()
        store = cls(spark, path, sorted(set(found or [])), layout, entities, sparse=vectors.is_sparse(entities), n=n, largest=float(largest or 0.0), extra=extra)
        rows = scored if layout == "clustered" else scored.drop("f")
        placed = rows.withColumn("eps_bucket", bucket_of(F.col("eps"), store.splits))
        ranges, threads = len(store.splits) + 1, spark.sparkContext.defaultParallelism
        tasks = min(ranges, threads)
        each = max(50_000, min(ROWS_PER_TASK, n // threads))
        salts = max(1, -(-n // (each * (tasks if ranges == buckets else 1))))
        task = F.floor(F.col("eps_bucket") * tasks / ranges) * salts + F.pmod(F.xxhash64("id"), F.lit(salts))
        placed = placed.repartitionById(tasks * salts, task.cast("int")).sortWithinPartitions("eps_bucket", "eps")
        if memory:
            store.frame = placed.persist(StorageLevel.MEMORY_AND_DISK)
        else:
            store.write(placed, n // (tasks * salts))
        store.recount()
        return store

    def write(self, placed: DataFrame, rows_per_file: int) -> None:
        out = placed.write.mode("append").partitionBy("eps_bucket").option("parquet.bloom.filter.enabled#id", "true")
        out.option("parquet.bloom.filter.expected.ndv#id", str(max(1000, rows_per_file))).parquet(self.path)

    def recount(self) -> None:
        """Rows of each range, which the planner needs."""
        rows = {r[0]: r[1] for r in self.read().groupBy("eps_bucket").count().collect()}  # a row for each directory
        self.counts = [rows.get(k, 0) for k in range(len(self.splits) + 1)]

    def read(self) -> DataFrame:
        if self.frame is not None:
            return self.frame
        if self.listed is None:  # files are listed once for each version, not for each read
            self.listed = self.spark.read.schema(self.schema()).parquet(self.path)
        return self.listed

    def schema(self) -> str:
        f = "f struct<idx: array<int>, val: array<double>>, " if self.sparse else "f array<double>, "
        return f"id long, {f if self.layout == 'clustered' else ''}eps double, norm_q double, {self.extra + ', ' if self.extra else ''}eps_bucket int"

    def between(self, low: float | None, high: float | None) -> DataFrame:
        """Rows with low <= eps < high; None leaves an end open.  Directories are named in the filter, as Spark does not infer them."""
        rows = self.read()
        if low is not None:
            rows = rows.where((F.col("eps_bucket") >= bisect_right(self.splits, low)) & (F.col("eps") >= F.lit(float(low))))
        if high is not None:
            rows = rows.where((F.col("eps_bucket") <= bisect_right(self.splits, high)) & (F.col("eps") < F.lit(float(high))))
        return rows

    def with_vectors(self, rows: DataFrame) -> DataFrame:
        """Rows with their vectors; in the slim layout these come by a join on the id."""
        if self.layout == "clustered":
            return rows
        return rows.join(self.entities.select("id", "f"), "id")

    def append(self, entities: DataFrame, model: Model, q: float) -> None:
        """New entities, placed by their margin under the stored model."""
        scored = entities.select("id", "f", vectors.score(entities, model).alias("eps"), vectors.vector_norm(entities, q).alias("norm_q"))
        columns = ["id", "f", "eps", "norm_q"] if self.layout == "clustered" else ["id", "eps", "norm_q"]
        placed = scored.select(*columns, bucket_of(F.col("eps"), self.splits).alias("eps_bucket"))
        if self.frame is not None:
            self.frame = self.frame.unionByName(placed).persist(StorageLevel.MEMORY_AND_DISK)
        else:
            self.write(placed, 1000)
            self.listed = None
        if self.entities is not None:
            self.entities = self.entities.unionByName(entities.select("id", "f"))
        self.recount()

    def evict(self) -> None:
        """Drop what is in memory; the plan can make it again."""
        if self.frame is not None:
            self.frame.unpersist()


def hybrid_bytes(n: int, buffered: int, key: int, feature: int) -> int:
    """Memory of a margin map of ``n`` keys and a buffer of entities."""
    return buffered * (feature + key) + (key + 8) * n


def full_bytes(n: int, key: int, feature: int) -> int:
    return n * (key + feature)


@dataclass
class MarginMap:
    """Keys with their stored margins, and the entities likeliest to change beside them."""

    margins: DataFrame
    buffer: DataFrame
    ids: DataFrame
    buffered: int

    @classmethod
    def build(cls, store: ClusteredStore, low: float, high: float, buffered: int) -> MarginMap:
        margins = store.read().select("id", "eps", "eps_bucket").persist(StorageLevel.MEMORY_AND_DISK)
        buffer = choose_buffer(store, low, high, buffered).persist(StorageLevel.MEMORY_AND_DISK)
        return cls(margins, buffer, buffer.select("id"), buffered)

    def drop(self) -> None:
        self.margins.unpersist()
        self.buffer.unpersist()


def band_distance(eps: Column, low: float, high: float) -> Column:
    """0 inside the band, else how far the margin is from it."""
    return F.when(eps >= F.lit(float(high)), eps - F.lit(float(high))).when(eps < F.lit(float(low)), F.lit(float(low)) - eps).otherwise(F.lit(0.0))


def choose_buffer(store: ClusteredStore, low: float, high: float, buffered: int) -> DataFrame:
    """The ``buffered`` entities nearest to the band, ties by id: (id, f).

    Up to SORTED_BUFFER are found by sorting keys.  Beyond, a quantile of the
    distance settles all but those about the cut; only these
    are sorted.  Where more rows tie, inside the band, than the buffer holds, the
    quantile is of their ids.  Vectors are fetched for the chosen ids alone.
    """
    rows = store.read().select("id", band_distance(F.col("eps"), low, high).alias("distance"))

    def nearest(rows: DataFrame, by: str, k: int) -> tuple[DataFrame, DataFrame, int]:
        """Rows surely among the ``k`` of smallest ``by``, rows that may be, and how many of these."""
        n = rows.count()
        shares = [max(0.0, k / max(1, n) - 2.0 / QUANTILE_STEPS), min(1.0, k / max(1, n) + 2.0 / QUANTILE_STEPS)]
        a, b = rows.agg(F.percentile_approx(by, F.array(*map(F.lit, shares)), QUANTILE_STEPS)).first()[0] or (0, 0)
        sure = rows.where(F.col(by) < F.lit(a))
        return sure, rows.where((F.col(by) >= F.lit(a)) & (F.col(by) <= F.lit(b))), k - sure.count()

    if buffered <= SORTED_BUFFER:
        sure, open_, left = rows.where(F.lit(False)), rows, buffered
    else:
        sure, open_, left = nearest(rows, "distance", buffered)
    within = open_.where("distance = 0")
    if buffered > SORTED_BUFFER and within.limit(left + 1).count() > left:
        more, open_, left = nearest(within, "id", left)
        sure = sure.unionByName(more)
    chosen = sure.unionByName(open_.orderBy("distance", "id").limit(max(0, left))).select("id")
    return store.with_vectors(store.read().join(chosen, "id", "left_semi")).select("id", "f")


def dump(state: dict) -> str:
    return json.dumps(state, sort_keys=True)
