"""Streams of examples and of entities that keep a view up to date, and features of event streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from driftview.operators.view import ClassificationView


def attach_stream(view: ClassificationView, stream: DataFrame, kind: str, checkpoint: str, available_now: bool = True) -> StreamingQuery:
    """Apply each micro-batch as one round.

    ``kind`` examples takes (id, label), entities takes (id, f).  A batch's
    number is kept in the view's manifest, so one that is sent again after a
    failure is left out.
    """
    if kind not in ("examples", "entities"):
        raise ValueError(kind)

    def apply(batch: DataFrame, number: int) -> None:
        if number <= view.last_batch or batch.isEmpty():
            return
        view.last_batch = number
        if kind == "examples":
            view.add_examples(batch)
        else:
            view.add_entities(batch)
        view.publish()

    writer = stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def user_windows(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str | None = None) -> DataFrame:
    """(user_id, start, n, total) of tumbling or sliding windows; ``late`` sets a watermark on a stream."""
    rows = events.withWatermark("ts", late) if late else events
    grouped = rows.groupBy("user_id", F.window("ts", size, slide) if slide else F.window("ts", size))
    return grouped.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("window.start").alias("start"), "n", "total")


def user_sessions(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    """(user_id, start, n, total) of sessions that end after ``gap`` without an event."""
    rows = events.withWatermark("ts", late) if late else events
    grouped = rows.groupBy("user_id", F.session_window("ts", gap))
    return grouped.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("session_window.start").alias("start"), "n", "total")


def window_vector(n: Column, total: Column) -> Column:
    """A dense vector of a window: its events and its mean value, scaled."""
    return F.array(n.cast("double") / 10.0, total / n / 100.0)


def running_waste(costs: DataFrame, recluster_cost: float) -> DataFrame:
    """The rent-or-buy rule over a stream of costs (key, seq, cost): (key, seq, waste, reclusters) after each, kept as state by key.

    A round whose waste so far reaches ``recluster_cost`` buys: its own cost is
    not paid, and the waste starts from 0.  Rows of a micro-batch are taken in
    order of ``seq``; null costs are 0.  State is two numbers a key.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        waste, bought = state.get if state.exists else (0.0, 0)
        rows = pd.concat(list(batches)).sort_values("seq")
        out = []
        for seq, cost in zip(rows["seq"], rows["cost"].fillna(0.0), strict=True):
            if waste >= recluster_cost:
                waste, bought = 0.0, bought + 1
            else:
                waste += cost
            out.append((key[0], seq, waste, bought))
        state.update((waste, bought))
        yield pd.DataFrame(out, columns=["key", "seq", "waste", "reclusters"])

    return costs.groupBy("key").applyInPandasWithState(step, "key long, seq long, waste double, reclusters long", "waste double, reclusters long", "append", GroupStateTimeout.NoTimeout)
