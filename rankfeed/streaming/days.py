"""Gradients of a stream of events: one matrix for each day, as the daily source makes them from a table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import gradients as G


def daily_gradients(events: DataFrame, workers: int = 4, late: str = "2 hours") -> DataFrame:
    """``step, worker, i, j, v`` of windows of a day; events later than ``late`` behind the newest one are dropped by the watermark.

    In append mode a day comes out once, when the watermark has passed its end. Days are those of the session's time zone.
    """
    timed = events.where(F.col("event_type").isin(G.EVENTS)).withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    cents = F.round(F.col("value") * 100).cast("bigint")
    keys = [F.window("at", "1 day").alias("day"), G.worker_of("event_id", workers).alias("worker"), F.hour("at").alias("i"), G.index_in(G.EVENTS, "event_type").alias("j")]
    sums = timed.groupBy(*keys).agg(F.sum(cents).cast("double").alias("v"))
    return sums.select(F.datediff(F.to_date("day.start"), F.lit("2024-01-01").cast("date")).alias("step"), "worker", "i", "j", "v")
