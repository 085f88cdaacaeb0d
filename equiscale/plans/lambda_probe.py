"""Measures lambda: the time to shuffle rows against the time to write them locally."""

from __future__ import annotations

import statistics
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from equiscale.sources.io import shared_dir


def padded(spark: SparkSession, records: int, row_bytes: int) -> DataFrame:
    return widened(spark.range(records), row_bytes)


def widened(rows: DataFrame, row_bytes: int) -> DataFrame:
    return rows.select(F.col("id"), F.rpad(F.col("id").cast("string"), row_bytes - 8, "x").alias("pay"))


def estimate(spark: SparkSession, records: int = 1_000_000, row_bytes: int = 100, repeats: int = 5, rows: DataFrame | None = None) -> dict[str, float]:
    """Medians of both times and their ratio.  On one machine both are memory and disk, so the ratio is only a check of the probe.  ``rows`` has an ``id`` and takes the place of the made records."""
    df = padded(spark, records, row_bytes) if rows is None else widened(rows, row_bytes)
    n = spark.sparkContext.defaultParallelism
    shuffle, write = [], []
    for k in range(repeats):
        start = time.perf_counter()
        df.repartition(n, "id").write.format("noop").mode("overwrite").save()
        shuffle.append(time.perf_counter() - start)
        start = time.perf_counter()
        df.write.mode("overwrite").parquet(f"{shared_dir(spark)}/probe-{k}")
        write.append(time.perf_counter() - start)
    s, w = statistics.median(shuffle), statistics.median(write)
    return {"shuffle_s": s, "write_s": w, "lambda": s / w}


def grid(spark: SparkSession, records: int = 100_000, sizes: tuple[int, ...] = (100, 1000), repeats: int = 3, rows: DataFrame | None = None) -> list[dict[str, float]]:
    return [{"row_bytes": b, **estimate(spark, records, b, repeats, rows)} for b in sizes]
