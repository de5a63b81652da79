"""Intermediate tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

CHECKPOINT_DIR = "spark.checkpoint.dir"
PARALLELISM_FIRST = "spark.sql.adaptive.coalescePartitions.parallelismFirst"


def shared_dir(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``; where none is set, a new local one in a local session, as in tests, and an error on a cluster."""
    path = spark.conf.get(CHECKPOINT_DIR, None) or spark.sparkContext.getConf().get(CHECKPOINT_DIR)
    if not path:
        current = spark.sparkContext.getCheckpointDir()
        if current:
            return current.rstrip("/")
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError(f"{CHECKPOINT_DIR} must name a folder that the driver and all executors share")
        path = tempfile.mkdtemp(prefix="driftview-")
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str, by_size: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back, so that its lineage ends there.

    ``by_size`` asks for tasks, and so files, by the bytes there are to write
    rather than by the cores that are free: tables that are mostly small, such as
    those of a loop, then cost a task each.
    """
    spark = df.sparkSession
    path = new_path(spark, label)
    before = spark.conf.get(PARALLELISM_FIRST)
    spark.conf.set(PARALLELISM_FIRST, "false" if by_size else before)
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(PARALLELISM_FIRST, before)
    return spark.read.schema(df.schema).parquet(path)


def columns(df: DataFrame) -> list[Column]:
    """All columns of a frame, whatever characters their names hold."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or one like it that the frame does not have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def discard(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete the files of materialized tables that no later plan reads."""
    root = shared_dir(spark).removeprefix("file://")
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    parents = {f.rsplit("/", 1)[0] for t in tables for f in t.inputFiles()}
    for parent in parents:
        if root in parent:
            path = jvm.org.apache.hadoop.fs.Path(parent)
            path.getFileSystem(conf).delete(path, True)
