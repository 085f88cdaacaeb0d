"""Streaming surface: joins of a stream with a static side, and hot keys of a stream."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from equiscale.operators.adaptive import adaptive_join
from equiscale.operators.small_large import index_broadcast_join, small
from equiscale.plans.config import JoinConfig


def enrich(stream: DataFrame, static: DataFrame, on, how: str = "inner") -> DataFrame:
    """The stream is the large side.  A static row is never finally unmatched, so right and full forms exist per micro-batch only."""
    if how not in ("inner", "left", "left_semi"):
        raise ValueError("an unbounded stream allows inner, left and left_semi; use per_batch for others")
    return stream.join(small(static), on, how)


def hot_keys(stream: DataFrame, on: str, window: str = "10 minutes", watermark: str = "30 minutes", ts: str = "ts", slide: str | None = None) -> DataFrame:
    """Counts of each key in tumbling or sliding windows of event time."""
    timed = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark)
    return timed.groupBy(F.window(ts, window, slide), F.col(on)).agg(F.count("*").alias("f"))


def session_hot_keys(stream: DataFrame, on: str, gap: str = "10 minutes", watermark: str = "30 minutes", ts: str = "ts") -> DataFrame:
    timed = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark)
    return timed.groupBy(F.session_window(ts, gap), F.col(on)).agg(F.count("*").alias("f"))


def per_batch(static: DataFrame, on, sink: Callable[[DataFrame, int], None], how: str = "inner", cfg: JoinConfig = JoinConfig(), *, right_on=None, large: bool = True):
    """A foreachBatch function that joins each micro-batch with ``static``, adaptively or by broadcast of ``static``."""

    def run(batch: DataFrame, batch_id: int) -> None:
        if large:
            sink(index_broadcast_join(batch, static, on, how, right_on=right_on), batch_id)
        else:
            sink(adaptive_join(batch, static, on, how, cfg, right_on=right_on), batch_id)

    return run
