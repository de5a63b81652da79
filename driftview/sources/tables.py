"""The given tables, and entities with a key of one column."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def short_hash(*columns: str) -> Column:
    """60 bits of md5 over the columns, as a long that any SQL engine can reproduce without a sort."""
    return F.conv(F.substring(F.md5(F.concat_ws("-", *[F.col(c).cast("string") for c in columns]).cast("binary")), 1, 15), 16, 10).cast("long")


def keyed_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with ``ent_id``, a hash of the columns that together are unique, and a planted label."""
    rows = table(spark, sf_dir, "lineitem")
    label = F.when(F.col("l_extendedprice") >= 1500 * F.col("l_quantity"), 1).otherwise(-1)
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    return rows.withColumn("cents", cents).withColumn("ent_id", short_hash("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "cents")).drop("cents").withColumn("label", label)


def strip_tags(html: Column) -> Column:
    """Text of a page: tags become blanks."""
    return F.regexp_replace(html, r"<[^>]*>", " ")
