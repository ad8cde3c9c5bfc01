"""Queries that arrive as a stream, against a training set that stays.

The training side (counts, blocks) is made once. Each micro-batch is an ordinary search, so
streaming and batch answers are the same; the search joins more than once, hence foreachBatch.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.grid import GridSpec
from ..plans.pipeline import classify, prepare


def classify_stream(stream: DataFrame, train: DataFrame, k: int, grid: GridSpec, sink: Callable[[DataFrame, int], None], checkpoint: str, available_now: bool = True, **options) -> StreamingQuery:
    """Starts the stream (pid, q0.., other columns); sink gets each batch's rows with cls_pred, votes and best_rank."""
    axes = [f"q{i}" for i in range(grid.d)]
    ready = prepare(train, grid)

    def each(batch: DataFrame, number: int) -> None:
        pred = classify(batch.select("pid", *axes), ready, k, **options)
        sink(batch.join(pred, "pid", "left"), number)

    writer = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def once_each(stream: DataFrame, key: str, ts: str, delay: str = "1 hour") -> DataFrame:
    """The stream without repetitions of a key that come within the delay."""
    return stream.withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def class_counts(stream: DataFrame, ts: str, cls: str, window: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Rows by class in tumbling or sliding windows; rows later than the watermark are dropped."""
    return stream.withWatermark(ts, delay).groupBy(F.window(ts, window, slide or window), cls).agg(F.count("*").alias("n"))


def session_counts(stream: DataFrame, ts: str, key: str, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Rows by key in sessions that end after a gap."""
    return stream.withWatermark(ts, delay).groupBy(F.session_window(ts, gap), key).agg(F.count("*").alias("n"))


def running_density(stream: DataFrame, grid: GridSpec, prefix: str = "t") -> DataFrame:
    """cell, n: how many training points of the stream fell into each cell so far (complete output)."""
    return grid.assign(stream, prefix).groupBy("cell").agg(F.count("*").alias("n"))
