"""What users do around a view in SQL and in streams: joins, subqueries, groupings, dates, JSON, own functions, late rows and state."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from driftview.functions import vectors
from driftview.learn.bulk import bulk_train
from driftview.learn.model import Model
from driftview.operators.asof import asof_join
from driftview.operators.band import water_marks
from driftview.operators.store import ClusteredStore
from driftview.plans import workloads
from driftview.queries import _exact_view, _run, _trail_frame, _trailed
from driftview.registry import query
from driftview.session import shared_path
from driftview.sources import view_source
from driftview.sources.tables import table
from driftview.streaming.attach import running_waste, user_windows


def _margins(spark: SparkSession, sf_dir: str) -> tuple[str, DataFrame]:
    """A temporary view (id, eps, l_returnflag, l_linestatus, l_orderkey, l_shipdate) of margins under the last model."""
    w = workloads.planted_lineitem(spark, sf_dir)
    rows = w.feature.transform(w.source, "id")
    eps = rows.select("id", vectors.score(rows, w.trail()[-1]).alias("eps"))
    out = eps.join(w.source.select("id", "l_returnflag", "l_linestatus", "l_orderkey", "l_shipdate"), "id")
    name = f"margins_{uuid.uuid4().hex[:8]}"
    out.createOrReplaceTempView(name)
    return name, out


@query
def event_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beside each click, the user's last purchase at or before it."""
    events = table(spark, sf_dir, "events")
    clicks = events.where("event_type = 'click'").select("event_id", "user_id", "ts")
    bought = events.where("event_type = 'purchase'").select("user_id", "ts", "event_id", "value")
    return asof_join(clicks, bought, "user_id", "ts", ["event_id", "value"]).select("event_id", "user_id", F.coalesce("event_id_asof", F.lit(-1)).alias("event_id_asof"), F.coalesce("value_asof", F.lit(-1.0)).alias("value_asof"))


@query
def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A number out of a JSON column, by user."""
    events = table(spark, sf_dir, "events").select("user_id", F.from_json("props", "k long").alias("p"))
    return events.groupBy("user_id").agg(F.sum("p.k").alias("total"), F.max("p.k").alias("largest"))


@query
def view_by_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positive and negative items by the month of shipping, of a stretch of dates."""
    w, view = _exact_view(spark, sf_dir)
    rows = w.source.where("l_shipdate >= TIMESTAMP'1996-01-01 00:00:00' AND l_shipdate < TIMESTAMP'1998-01-01 00:00:00'").select("id", F.date_format(F.date_trunc("month", "l_shipdate"), "yyyy-MM").alias("month"))
    return view.join(rows, "id").groupBy("month", "class").agg(F.count("*").alias("n"))


@query
def view_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, view = _exact_view(spark, sf_dir)
    name = f"grouped_{uuid.uuid4().hex[:8]}"
    view.join(w.source.select("id", "l_returnflag", "l_linestatus"), "id").withColumn("class", F.col("class").cast("string")).createOrReplaceTempView(name)
    return spark.sql(f"SELECT l_returnflag, l_linestatus, class, grouping_id(l_returnflag, class, l_linestatus) AS level, count(*) AS n FROM {name} GROUP BY GROUPING SETS ((l_returnflag, class), (l_linestatus), ())")


@query
def margins_lateral(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each flag, the three entities nearest to the hyperplane, by a lateral subquery."""
    name, _ = _margins(spark, sf_dir)
    return spark.sql(f"SELECT f.l_returnflag, near.id, round(near.eps, 6) AS eps FROM (SELECT DISTINCT l_returnflag FROM {name}) f, LATERAL (SELECT id, eps FROM {name} m WHERE m.l_returnflag = f.l_returnflag ORDER BY abs(eps), id LIMIT 3) near")


@query
def margins_scalar_subquery(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flags with the share of entities above the mean margin of all."""
    name, _ = _margins(spark, sf_dir)
    return spark.sql(f"SELECT l_returnflag, count(*) AS n, count_if(eps > (SELECT avg(eps) FROM {name})) AS n_above FROM {name} GROUP BY l_returnflag")


@query
def margins_by_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities in each of overlapping intervals of margins, by a join on a range; the intervals are a table of fixed size."""
    _, rows = _margins(spark, sf_dir)
    intervals = spark.range(20).select(F.col("id").alias("k"), (F.col("id") / 10 - 1.0).alias("lo"), (F.col("id") / 10 - 0.75).alias("hi"))
    return rows.join(F.broadcast(intervals), (F.col("eps") >= F.col("lo")) & (F.col("eps") < F.col("hi"))).groupBy("k").agg(F.count("*").alias("n"))


@query
def view_aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By flag: distinct orders, the entity of largest margin, and the exact median."""
    _, rows = _margins(spark, sf_dir)
    return rows.groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("orders"), F.max_by("id", F.struct("eps", "id")).alias("furthest"), F.round(F.median("eps"), 6).alias("median"))


@udtf(returnType="term: string, n: long")
class TermCounts:
    """Words of a text with their counts, in order of the words: a table function for users."""

    def eval(self, text: str):  # noqa: ANN201
        import re

        counts: dict[str, int] = {}
        for t in filter(None, re.split(r"[\W_]+", (text or "").lower())):
            counts[t] = counts.get(t, 0) + 1
        yield from sorted(counts.items())


@query
def part_terms_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of part names by a table function of the user's."""
    spark.udtf.register("term_counts", TermCounts)
    table(spark, sf_dir, "part").createOrReplaceTempView("udtf_parts")
    return spark.sql("SELECT p_partkey AS id, t.term, t.n FROM udtf_parts, LATERAL term_counts(p_name) t")


@query
def bulk_gradient_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A warm model from all labelled rows, by five whole-batch steps."""
    w = workloads.planted_lineitem(spark, sf_dir)
    examples = w.feature.transform(w.source, "id").join(w.source.select("id", "label"), "id")
    return _trail_frame(spark, [bulk_train(examples, 4, rounds=5)])


@query
def clustered_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of a clustered store with margins in a narrow range, by directory and filter."""
    w = workloads.planted_lineitem(spark, sf_dir)
    model: Model = w.trail()[-1]
    store = ClusteredStore.build(w.entities, model, shared_path(spark, "ranges"))
    return store.between(-0.1, 0.1).select("id", F.round("eps", 6).alias("eps"))


@query
def certain_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities whose stored margin settles their class at the last round, by the SQL function."""
    _, entities, models, largest, _ = _trailed(spark, sf_dir)
    *_, lw, hw = water_marks(models, 0, largest, 2.0)[-1]
    vectors.register_sql(spark)
    name = f"stored_{uuid.uuid4().hex[:8]}"
    entities.select(vectors.score(entities, models[0]).alias("eps")).createOrReplaceTempView(name)
    return spark.sql(f"SELECT coalesce(mv_certain(eps, {lw!r}D, {hw!r}D), 0) AS certain, count(*) AS n FROM {name} GROUP BY 1")


@query
def data_source_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positive entities of a view that is known by its path alone."""
    view = _run(spark, sf_dir, each=20)
    view_source.register(spark)
    return spark.read.format("modelview").load(view.path).where("class = 1").select("id", "class")


@query
def partition_overwrite(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A copy of the view by class, of which one partition is written anew."""
    _, view = _exact_view(spark, sf_dir)
    path = shared_path(spark, "by_class")
    view.write.partitionBy("class").parquet(path)
    even = view.where("class = 1 AND id % 2 = 0")
    even.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("class").parquet(path)
    return spark.read.schema("id long, class int").parquet(path)


# --- streams


@query
def stream_late_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of a stream in which some rows come a second time, too late: they are dropped, and closed windows stand."""
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "value")
    n = events.count()
    path = shared_path(spark, "late")
    for part in (events.where(F.col("event_id") < n // 2), events.where(F.col("event_id") >= n // 2), events.where(F.col("event_id") < n // 10)):
        part.coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.05)  # files are taken in order of time
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    out = shared_path(spark, "windows")
    writer = user_windows(stream, "6 hours", late="1 hour").writeStream.option("checkpointLocation", shared_path(spark, "progress"))
    writer.trigger(availableNow=True).format("parquet").outputMode("append").start(out).awaitTermination()
    return spark.read.schema("user_id long, start timestamp, n long, total double").parquet(out).select("user_id", F.unix_timestamp("start").alias("start"), "n", F.round("total", 4).alias("total"))


@query
def stream_running_waste(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rent-or-buy rule as state of a stream: a user's events are costs, and 200 buys a reclustering."""
    events = table(spark, sf_dir, "events").select(F.col("user_id").alias("key"), F.col("event_id").alias("seq"), F.col("value").alias("cost"))
    n = events.count()
    path = shared_path(spark, "costs")
    for part in (events.where(F.col("seq") < n // 2), events.where(F.col("seq") >= n // 2)):
        part.coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.05)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    out = shared_path(spark, "waste")
    writer = running_waste(stream, 200.0).writeStream.option("checkpointLocation", shared_path(spark, "progress"))
    writer.trigger(availableNow=True).format("parquet").outputMode("append").start(out).awaitTermination()
    return spark.read.schema("key long, seq long, waste double, reclusters long").parquet(out).select("key", "seq", F.round("waste", 4).alias("waste"), "reclusters")
