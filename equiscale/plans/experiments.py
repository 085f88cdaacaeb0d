"""The published experiments on the given tables: each function returns rows of measurements, one at a time as they come.

A run counts the joined rows of each key, so that pairs are made but not kept.  Times are medians of ``repeat`` runs after one that warms up;
a run over ``limit_s`` is cancelled and counts as not finished, like one that fails for lack of memory.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from equiscale.operators import baselines
from equiscale.operators.adaptive import adaptive_join
from equiscale.operators.selfjoin import natural_self_join
from equiscale.operators.small_large import index_broadcast_join
from equiscale.operators.staged import staged_join, staged_join_basic
from equiscale.plans import lambda_probe, metrics
from equiscale.plans.config import JoinConfig
from equiscale.sources.io import read
from equiscale.sources.workloads import zipf

METHODS = {
    "staged": staged_join,
    "adaptive": adaptive_join,
    "staged_basic": staged_join_basic,
    "adaptive_basic": lambda a, b, on, how="inner", cfg=JoinConfig(): adaptive_join(a, b, on, how, cfg, hh="basic"),
    **baselines.BASELINES,
}


def _pairs(df: DataFrame) -> DataFrame:
    return df.groupBy("key").agg(F.count("*").alias("pairs"), F.sum("id").alias("s"), F.sum("rid").alias("t"))


def sides(spark: SparkSession, sf_dir: str, alpha: float, **options) -> tuple[DataFrame, DataFrame]:
    options = {"uniform_part": True} | options
    right = {k: v for k, v in options.items() if k != "left_only"}
    return zipf(spark, sf_dir, "left", alpha, **right), zipf(spark, sf_dir, "right", alpha, **right).withColumnsRenamed({"id": "rid", "pay": "rpay"})


def _timed(make, repeat: int, limit_s: float | None) -> dict:
    before = time.perf_counter()
    warm = metrics.time_join(make, 1, limit_s)
    if warm["dnf"]:
        return warm | {"first_s": round(time.perf_counter() - before, 3)}
    return metrics.time_join(make, repeat, limit_s) | {"first_s": round(warm["seconds"], 3)}


def skew_sweep(spark, sf_dir, methods=("staged", "adaptive", "staged_basic", "adaptive_basic", "shuffle_hash_join", "native_join", "planned_grid_join", "heavier_side_join", "key_range_join"), alphas=(0.0, 0.25, 0.5, 0.65, 0.75, 1.0), *, pay_bytes: int = 100, repeat: int = 3, limit_s: float | None = 600) -> Iterator[dict]:
    """Every method over the exponents of the power law; the payload goes through the joins."""
    for alpha in alphas:
        for name in methods:
            make = lambda f=METHODS[name], a=alpha: _with_payload(f(*sides(spark, sf_dir, a, pay_bytes=pay_bytes), "key"))
            yield {"experiment": "skew", "method": name, "alpha": alpha, "row_bytes": pay_bytes} | _timed(make, repeat, limit_s)


def _with_payload(df: DataFrame) -> DataFrame:
    """Counts that read the payload of both sides, so that it cannot be pruned."""
    return df.groupBy("key").agg(F.count("*").alias("pairs"), F.max(F.octet_length("pay")).alias("p"), F.max(F.octet_length("rpay")).alias("q"))


def strong_scaling(spark, sf_dir, tasks=(1, 2, 4, 8), methods=("staged", "adaptive", "shuffle_hash_join", "heavier_side_join", "planned_grid_join"), *, alpha: float = 0.65, repeat: int = 3, limit_s: float | None = 600) -> Iterator[dict]:
    """The same input over more partitions of every exchange; on one machine tasks stand for executors."""
    held = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for n in tasks:
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            for name in methods:
                yield {"experiment": "strong", "method": name, "tasks": n} | _timed(lambda f=METHODS[name]: _pairs(f(*sides(spark, sf_dir, alpha), "key")), repeat, limit_s)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)


def weak_scaling(spark, sf_dir, shares=(0.25, 0.5, 0.75, 1.0), methods=("staged", "adaptive", "planned_grid_join"), *, alpha: float = 0.65, repeat: int = 3, limit_s: float | None = 600) -> Iterator[dict]:
    """A growing share of both inputs: pairs grow with its square."""
    for share in shares:
        for name in methods:
            yield {"experiment": "weak", "method": name, "share": share} | _timed(lambda f=METHODS[name], p=share: _pairs(f(*sides(spark, sf_dir, alpha, share=p), "key")), repeat, limit_s)


def balanced_over_basic(spark, sf_dir, *, alpha: float = 1.0, repeat: int = 3) -> Iterator[dict]:
    """Speed-up of the balanced over the basic form, of both joins."""
    for name in ("staged", "adaptive"):
        t = {v: _timed(lambda f=METHODS[v]: _pairs(f(*sides(spark, sf_dir, alpha), "key")), repeat, None)["seconds"] for v in (name, f"{name}_basic")}
        yield {"experiment": "balanced", "method": name, "speed_up": metrics.speedup(t[f"{name}_basic"], t[name])}


def self_join_speed_up(spark, sf_dir, alphas=(0.0, 0.5, 1.0), *, repeat: int = 3) -> Iterator[dict]:
    """The natural self-join against the same join as an equi-join of two relations."""
    for alpha in alphas:
        rows = lambda a=alpha: zipf(spark, sf_dir, "left", a).select("key", "id")
        own = _timed(lambda: natural_self_join(rows(), "key", "id").groupBy("key").agg(F.count("*"), F.sum("id_1"), F.sum("id_2")), repeat, None)["seconds"]
        equi = _timed(lambda: staged_join(rows(), rows(), "key").groupBy("key").agg(F.count("*"), F.sum("id"), F.sum("id_r")), repeat, None)["seconds"]
        yield {"experiment": "self", "alpha": alpha, "natural_s": own, "equi_s": equi, "speed_up": metrics.speedup(equi, own)}


def small_large(spark, sf_dir, tenths=(2, 5, 10), *, repeat: int = 3) -> Iterator[dict]:
    """Right outer joins with a growing small side: by keys, by rows and by ids."""
    big = read(spark, sf_dir, "lineitem", ["l_partkey", "l_orderkey"]).withColumnRenamed("l_partkey", "key")
    for s in tenths:
        few = read(spark, sf_dir, "part", ["p_partkey", "p_size"]).filter(f"(p_partkey * 2654435761) % 10 < {s}").withColumnRenamed("p_partkey", "key")
        for name, f in (("keys", index_broadcast_join), ("rows", baselines.small_large_rows_outer), ("ids", baselines.small_large_ids_outer)):
            yield {"experiment": "small_large", "method": name, "tenths": s} | _timed(lambda g=f, r=few: g(big, r, "key", "right"), repeat, None)


def calibration(spark, sizes=(100, 1000), records: int = 100_000, repeat: int = 3) -> Iterator[dict]:
    """Lambda by row size, with the threshold that follows from it."""
    for row in lambda_probe.grid(spark, records, sizes, repeat):
        yield {"experiment": "lambda", "threshold": (1 + row["lambda"]) ** 1.5} | row


EXPERIMENTS = {"skew": skew_sweep, "strong": strong_scaling, "weak": weak_scaling, "balanced": balanced_over_basic, "self": self_join_speed_up, "small_large": small_large}
