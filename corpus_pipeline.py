"""The corpus pipeline: five stages, each over all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftview.llm import decontaminate, lines, mixing, near_dup, toxicity
from driftview.llm.scratch import columns, fresh, materialize, new_path


REJECTED = "__rejected"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject; rows with a null id stay."""
    scored = toxicity.toxicity(docs, _table(spark, sf_dir, "labels"))
    rejected = materialize(scored.where("predicted = 1 and doc_id is not null").select(F.col("doc_id").alias(REJECTED)).distinct(), "rejected", by_size=True)
    return docs.join(rejected, docs["doc_id"] == F.col(REJECTED), "left_anti")


def without_shared_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, less the lines that many share; ``n_chars`` follows the text, and stays null where it was."""
    kept = lines.drop_shared_lines(docs)
    length = F.when(F.col("n_chars").isNotNull(), F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return kept.withColumn("n_chars", length).select(*columns(docs))


def without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class, that of smallest id."""
    return near_dup.keep_one(docs, near_dup.near_duplicates(docs)).select(*columns(docs))


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark passage is found."""
    return decontaminate.clean_of(docs, decontaminate.contamination(docs, _table(spark, sf_dir, "benchmark"))).select(*columns(docs))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix takes words of, with their size, their source's target, and the words taken.

    Rows are told apart by id, source and size, nulls among them; those that
    share all three get the most words that the mix takes of any of them.  Where
    the documents have columns of the added names, the added ones get an
    underscore more.
    """
    keys = ("doc_id", "source", "size")
    mix = mixing.fair_mix(docs).where("taken > 0").groupBy(*keys).agg(F.max("target").alias("target"), F.max("taken").alias("taken"))
    named = {c: fresh(docs, c) for c in ("size", "target", "taken")}
    mix = materialize(mix.select(F.col("doc_id").alias("__id"), F.col("source").alias("__source"), *[F.col(c).alias(n) for c, n in named.items()]), "mix")
    met = docs["doc_id"].eqNullSafe(F.col("__id")) & docs["source"].eqNullSafe(F.col("__source")) & (mixing.word_count(docs["text"]) == F.col(named["size"]))
    return docs.join(mix, met).select(*columns(docs), *named.values())


STAGES = [
    ("toxicity", without_toxic),
    ("line_dedup", without_shared_lines),
    ("near_dup", without_near_duplicates),
    ("decontamination", without_benchmark),
    ("mixing", mixed),
]

#: The classifier and the sampled sketches cannot be stated in SQL.  Tests hold each stage against its operator, and the operators against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
