"""Pairs and sums of each key of a join, without a row for each pair.

Rows are weighted: a row says how many rows it stands for and the sum of their values.  Wherever a join has rows of one key together
(a piece, a lane of a grid, a broadcast side, a list) they are added up; hot keys, routes, grids and levels are the join's
own.  Two rows that meet stand for the product of their weights, so nothing is lost or estimated.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .keys import field


def join_totals(join, left: DataFrame, right: DataFrame, on: str, a: str, b: str) -> DataFrame:
    """k, pairs, sum_left (of ``a``), sum_right (of ``b``) of the rows of ``join(left, right, on)``, outer ones included."""
    one = F.lit(1).cast("long")
    l = left.select(field(left, on).alias("key"), one.alias("n"), field(left, a).cast("long").alias("s"))
    r = right.select(field(right, on).alias("key"), one.alias("m"), field(right, b).cast("long").alias("t"))
    n, m = (F.coalesce(F.col(c), F.lit(1)) for c in "nm")  # an unmatched row of an outer join counts once
    out = join(l, r, "key", weighted=True)
    return out.groupBy(F.col("key").alias("k")).agg(F.sum(n * m).alias("pairs"), F.sum(F.col("s") * m).alias("sum_left"), F.sum(F.col("t") * n).alias("sum_right"))
