"""SQL surface: functions and table functions for SQL callers."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="i int, j int")
class GridCells:
    """All cells of a row with lane ``own`` on the left of a grid of di x dj: (own, 0..dj-1)."""

    def eval(self, own: int, di: int, dj: int):
        for j in range(dj):
            yield own % max(1, di), j


@udtf(returnType="key string, f bigint")
class HotKeys:
    """Bounded summary of a TABLE argument's column ``key``: at most ``capacity`` counters."""

    def __init__(self):
        from equiscale.operators.hotkeys import SpaceSaving

        self._make, self._sketch = SpaceSaving, None

    def eval(self, row, capacity: int):
        if self._sketch is None:
            self._sketch = self._make(capacity)
        if row["key"] is not None:
            self._sketch.add(str(row["key"]))

    def terminate(self):
        for key, count, _ in (self._sketch.items() if self._sketch else ()):
            yield key, count


def register(spark: SparkSession) -> None:
    spark.udtf.register("grid_cells", GridCells)
    spark.udtf.register("hot_keys", HotKeys)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sublist_count(n BIGINT) RETURNS INT RETURN CAST(ceil(cbrt(n)) AS INT)")
