"""Connected components of distributed edges by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, release


def _lowest(pairs: DataFrame) -> DataFrame:
    """(n, m): each node's smallest neighbour or itself; written, so that a hot node's edges can be split in the join that follows."""
    return cut(pairs.groupBy("u").agg(F.min("v").alias("m"))).select(F.col("u").alias("n"), F.least("u", "m").alias("m"))


def _large(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.join(_lowest(both), F.col("u") == F.col("n")).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    joined = down.join(_lowest(down), F.col("u") == F.col("n"))
    return joined.select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").filter("u <> v").distinct()


def _all_stars(edges: DataFrame) -> bool:
    """Whether every node is below one other node at most, and that one below none: then the edges are the answer."""
    ends = edges.select("u", F.lit(1).alias("below")).unionByName(edges.select(F.col("v").alias("u"), F.lit(0).alias("below")))
    seen = ends.groupBy("u").agg(F.sum("below").alias("n"), F.min("below").alias("above"))
    return seen.filter((F.col("n") > 1) | ((F.col("n") == 1) & (F.col("above") == 0))).isEmpty()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of the edges (u, v) but the roots, where root is the smallest node of its component."""
    now = cut(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct())
    for _ in range(max_rounds):
        if _all_stars(now):
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        last, between = now, cut(_large(now))
        now = cut(_small(between))
        release(last, between)
    raise RuntimeError("components did not settle")
