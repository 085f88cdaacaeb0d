"""Measures of joins and of hot-key summaries."""

from __future__ import annotations

import statistics
import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from equiscale.operators.keys import TooLargeToBroadcast, field


def time_join(make: Callable[[], DataFrame], repeat: int = 3, timeout_s: float | None = None) -> dict:
    """Median seconds of whole runs to a sink that drops its rows; ``dnf`` after the time limit."""
    times = []
    for _ in range(repeat):
        df_holder: list = []
        start = time.perf_counter()
        spark_group = f"timed-{id(df_holder)}"
        from pyspark.sql import SparkSession

        sc = SparkSession.getActiveSession().sparkContext
        timer = threading.Timer(timeout_s, lambda: sc.cancelJobGroup(spark_group)) if timeout_s else None
        sc.setJobGroup(spark_group, "timed join", True)
        if timer:
            timer.start()
        try:
            make().write.format("noop").mode("overwrite").save()
        except TooLargeToBroadcast:
            return {"seconds": None, "dnf": True}
        except Exception:
            if timer and time.perf_counter() - start >= timeout_s:
                return {"seconds": None, "dnf": True}
            raise
        finally:
            if timer:
                timer.cancel()
            sc.setLocalProperty("spark.jobGroup.id", None)
        times.append(time.perf_counter() - start)
    return {"seconds": statistics.median(times), "dnf": False}


def speedup(slow: float, fast: float) -> float:
    return slow / fast


def pairs_per_partition(df: DataFrame) -> DataFrame:
    """One row: most, fewest and coefficient of variation of rows over partitions."""
    n = max(1, df.rdd.getNumPartitions())
    per = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("c"))
    mean = F.sum("c") / n
    return per.agg(F.max("c").alias("most"), F.when(F.count("*") < n, 0).otherwise(F.min("c")).alias("least"), (F.sqrt(F.sum(F.col("c") * F.col("c")) / n - mean * mean) / mean).alias("cv"))


def key_counts(df: DataFrame, on: str) -> DataFrame:
    return df.filter(F.col(on).isNotNull()).groupBy(F.col(on).alias("k")).agg(F.count("*").alias("f"))


def result_size(left: DataFrame, right: DataFrame, on: str, right_on: str | None = None) -> DataFrame:
    """Rows of the join from counts alone; no pair is made."""
    a, b = key_counts(left, on), key_counts(right, right_on or on).withColumnRenamed("f", "g")
    return a.join(b, "k").agg(F.coalesce(F.sum(F.col("f") * F.col("g")), F.lit(0)).cast("long").alias("pairs"))


def selectivity(left: DataFrame, right: DataFrame, on: str, right_on: str | None = None) -> DataFrame:
    """Share of left rows that find a match."""
    keys = right.select(F.col(right_on or on).alias("k")).distinct()
    return left.select(F.col(on).alias("k")).join(keys.withColumn("hit", F.lit(1)), "k", "left").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("selectivity"))


def hot_recall(found: DataFrame, exact: DataFrame, on: list[str]) -> DataFrame:
    """One row: exact hot keys, how many were found, and the largest error of their frequency."""
    both = exact.join(found.withColumnRenamed("f", "g"), on, "left")
    return both.agg(F.count("*").alias("hot"), F.count("g").alias("found"), F.coalesce(F.max(F.abs(F.col("g") - F.col("f"))), F.lit(0)).cast("long").alias("worst_error"))


def row_width(df: DataFrame):
    """Bytes of a row as a column: its strings and bytes as they are long, other plain columns 8, nested ones as JSON."""
    out = F.lit(8 * len(df.columns)).cast("long")
    for f in df.schema.fields:
        c = field(df, f.name)
        if isinstance(f.dataType, (T.StringType, T.BinaryType)):
            out = out + F.coalesce(F.octet_length(c), F.lit(0))
        elif isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType)):
            out = out + F.coalesce(F.octet_length(F.to_json(F.struct(c))), F.lit(0))
    return out


def avg_row_bytes(df: DataFrame, rows: int = 1000) -> float:
    """Mean width of a few rows, for planning."""
    few = df.limit(rows)
    return float(few.agg(F.avg(row_width(few))).first()[0] or 8 * len(df.columns) or 8)


def measured(df: DataFrame) -> tuple[int, int]:
    """(rows, bytes) of a relation that is written or cheap to scan."""
    n, size = df.agg(F.count("*"), F.coalesce(F.sum(row_width(df)), F.lit(0))).first()
    return n, size


def stage_metrics(spark, before: set[int] | None = None) -> dict[str, int]:
    """Shuffle, spill, peak execution memory and task figures of the stages that the status store holds, or of those not in ``before``."""
    context = spark.sparkContext
    store, jvm = context._jsc.sc().statusStore(), context._jvm
    stages = store.stageList(None, False, False, context._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    total = {"shuffle_write": 0, "shuffle_read": 0, "spill": 0, "tasks": 0, "peak_memory": 0}
    ids = set()
    for i in range(stages.size()):
        s = stages.apply(i)
        ids.add(s.stageId())
        if before is None or s.stageId() not in before:
            total["shuffle_write"] += s.shuffleWriteBytes()
            total["shuffle_read"] += s.shuffleReadBytes()
            total["spill"] += s.diskBytesSpilled()
            total["tasks"] += s.numCompleteTasks()
            total["peak_memory"] = max(total["peak_memory"], s.peakExecutionMemory())
    return total | {"stages": len(ids)}
