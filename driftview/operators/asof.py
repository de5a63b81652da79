"""As-of join: beside each row, the last row of another table at or before its time."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, values: Sequence[str], suffix: str = "_asof", bucket_seconds: int = 86_400) -> DataFrame:
    """``left`` with ``values`` of the last row of ``right`` of the same key ``by`` at or before its time ``on``.

    Both tables are put in one, dealt by key and stretch of time, and filled
    forward by a window, so a hot key is no single task's.  What a stretch begins
    with comes from the stretches before it, of which there is a row each.

    Of right rows with one key and time, the largest by ``values`` counts.  Rows
    of the left with a null key or time find nothing, and stay; null values of
    the right count as values.  Repeated left rows stay; an empty right gives nulls.
    """
    names = [f"{v}{suffix}" for v in values]
    payload = F.struct(*[F.col(v).alias(n) for v, n in zip(values, names, strict=True)])
    kind = right.select(payload.alias("p")).schema["p"].dataType
    mine = left.select(F.col(by).alias("k"), F.col(on).alias("t"), F.lit(1).alias("side"), F.struct(*[F.col(c) for c in left.columns]).alias("row"), F.lit(None).cast(kind).alias("p"))
    other = right.where(F.col(by).isNotNull() & F.col(on).isNotNull()).select(F.col(by).alias("k"), F.col(on).alias("t"), F.lit(0).alias("side"), F.lit(None).cast(mine.schema["row"].dataType).alias("row"), payload.alias("p"))
    both = other.unionByName(mine).withColumn("stretch", F.floor(F.col("t").cast("timestamp").cast("double") / bucket_seconds))
    ends = both.where("side = 0").groupBy("k", "stretch").agg(F.max(F.struct("t", "p")).alias("last")).select("k", "stretch", F.col("last.p").alias("last"))
    stretches = both.groupBy("k", "stretch").agg(F.lit(1).alias("one")).drop("one").join(ends, ["k", "stretch"], "left")
    earlier = Window.partitionBy("k").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)  # a row for each stretch
    carried = stretches.select(F.col("k").alias("key"), F.col("stretch").alias("at"), F.last("last", ignorenulls=True).over(earlier).alias("carried"))
    upto = Window.partitionBy("k", "stretch").orderBy("t", "side", "p").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumn("found", F.last("p", ignorenulls=True).over(upto)).where("side = 1")
    found = filled.join(carried, (F.col("k") == F.col("key")) & (F.col("stretch") == F.col("at")), "left").withColumn("found", F.coalesce("found", "carried"))
    return found.select("row.*", *[F.when(F.col("k").isNotNull() & F.col("t").isNotNull(), F.col(f"found.{n}")).alias(n) for n in names])
