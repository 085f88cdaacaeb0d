"""Natural self-join: each unordered pair of rows of a key once, and each row with itself (unless told otherwise).

Basic: one list for a key, carried once.  A list over the threshold is cut into sub-lists; each sub-list is a triangle of its
own, each two of them a rectangle, and both go through further levels until they are short.  Balanced: rows of
hot keys are dealt over lanes first; two lanes meet in a cell of an equi-join, and the rows of one lane are a list as above.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from equiscale.functions.chunking import chunk, grid_lane
from equiscale.plans.config import JoinConfig
from equiscale.sources.io import cut

from .hotkeys import SORTED, hot_keys
from .keys import field, free, names, no_nulls
from .staged import levels_of, placed, planned_cells, respread

#: Rows of a list at most, before it is cut into lanes of an equi-join.
LIST_ROWS = 4096


def _emit(idx: DataFrame, by: list[str], cfg: JoinConfig) -> DataFrame:
    """(by, a, b): pairs of triangles (``rs`` null) and of rectangles, the row of the smaller id first."""
    first = idx.select(*by, F.explode("ls").alias("a"), "ls", "rs")
    later = (lambda x: F.col("a")["id"] <= x["id"]) if cfg.include_identity else (lambda x: F.col("a")["id"] < x["id"])
    partners = F.when(F.col("rs").isNull(), F.filter("ls", later)).otherwise(F.col("rs"))
    pairs = first.select(*by, "a", F.explode(partners).alias("b"))
    swap = F.col("a")["id"] > F.col("b")["id"]
    return pairs.select(*by, F.when(swap, F.col("b")).otherwise(F.col("a")).alias("a"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("b"))


def _cut_lists(idx: DataFrame, by: list[str], rule: str) -> DataFrame:
    """The next level: a triangle's sub-lists are triangles, each two of them a rectangle; a rectangle's are all crossed."""
    tri = idx.filter("rs is null").select(*by, chunk(F.col("ls"), rule).alias("cs"))
    tri = tri.select(*by, F.posexplode("cs").alias("p", "ls"), "cs")
    alone = tri.select(*by, "ls", F.lit(None).cast(idx.schema["rs"].dataType).alias("rs"))
    two = tri.select(*by, "ls", F.explode(F.slice("cs", F.col("p") + 2, F.size("cs"))).alias("rs"))
    rect = idx.filter("rs is not null").select(*by, F.explode(chunk(F.col("ls"), rule)).alias("ls"), chunk(F.col("rs"), rule).alias("cs"))
    return alone.unionByName(two).unionByName(rect.select(*by, "ls", F.explode("cs").alias("rs")))


def _hot(theta: float) -> Column:
    n = F.size("ls").cast("double")
    return F.when(F.col("rs").isNull(), n).otherwise(F.sqrt(n * F.size("rs"))) > F.lit(float(theta))


def _triangles(rows: DataFrame, by: list[str], cfg: JoinConfig, l_max: float) -> DataFrame:
    """All pairs within each group of ``by``, through one list a group and as many levels as ``l_max`` rows need."""
    idx = rows.groupBy(*by).agg(F.collect_list("row").alias("ls"))
    idx = idx.withColumn("rs", F.lit(None).cast(idx.schema["ls"].dataType))
    out = None
    for _ in range(levels_of(l_max, cfg) if l_max > cfg.theta else 0):
        pairs = _emit(idx.filter(~_hot(cfg.theta)), by, cfg)
        out = pairs if out is None else out.unionByName(pairs)
        idx = respread(_cut_lists(idx.filter(_hot(cfg.theta)), by, cfg.chunk_rule), cfg.partitions(rows.sparkSession))
    last = _emit(idx, by, cfg)  # whatever is left
    return last if out is None else out.unionByName(last)


def natural_self_join(df: DataFrame, on, row_id: str, cfg: JoinConfig = JoinConfig(), variant: str = "balanced", kappa: DataFrame | None = None) -> DataFrame:
    """keys, and every other column c as c_1 and c_2; the row of the smaller ``row_id`` (unique) comes first.

    ``kappa``: hot keys as ``hot_keys`` gives them.  Rows of null keys have no partner.
    """
    shown = names(on)
    keys = [f"__k{i}" for i in range(len(shown))]
    rest = [c for c in df.columns if c not in shown]
    row = F.struct(field(df, row_id).alias("id"), *[field(df, c).alias(f"c{i}") for i, c in enumerate(rest)])
    known = df.select(*[field(df, c).alias(k) for c, k in zip(shown, keys)], row.alias("row")).filter(no_nulls(keys))

    def present(pairs: DataFrame) -> DataFrame:
        out, taken = [F.col(k).alias(n) for k, n in zip(keys, shown)], list(shown)
        for side, mark in (("a", "_1"), ("b", "_2")):
            for i, c in enumerate(rest):
                taken.append(free(c + mark, taken))
                out.append(F.col(side)[f"c{i}"].alias(taken[-1]))
        return pairs.select(*out)

    if variant == "basic":
        longest = known.groupBy(*keys).agg(F.count("*").alias("f")).agg(F.max("f")).first()[0] or 1
        return present(_triangles(known, keys, cfg, longest))
    k_max = cfg.k_max_left or cfg.hot_budget(df.sparkSession, cfg.left_bytes or 100.0)
    found = kappa.toDF(*keys, "f") if kappa is not None else hot_keys(known, keys, k_max, cfg.theta, cfg.hot_method, capacity=cfg.capacity, fanout=cfg.fanout)
    hot = cut(found.select(*keys, F.col("f").alias("fl"), F.col("f").alias("fr")))
    n, pairs, least = hot.agg(F.count("*"), F.sum(F.col("fl").cast("double") * F.col("fl") / 2), F.min("fl")).first()
    cold = known.join(F.broadcast(hot.select(*keys)), keys, "left_anti")
    # a full table may have left out keys as frequent as its last; one from outside or from a sketch may have left out any
    if kappa is None and cfg.hot_method in ("exact", "prepartitioned"):
        longest = cfg.theta if n < min(k_max, SORTED) else least
    else:
        longest = cold.groupBy(*keys).agg(F.count("*").alias("f")).agg(F.max("f")).first()[0] or 1
    out = _triangles(cold, keys, cfg, longest)
    if n:
        plan = planned_cells(hot, cfg, pairs, cfg.executors(df.sparkSession), LIST_ROWS)
        own = placed(known.join(F.broadcast(hot.select(*keys)), keys))
        own = own.join(F.broadcast(plan.select(*keys, F.col("__dl").alias("__d"))), keys).withColumn("__lane", grid_lane(["__p"], F.col("__d"), cfg.seed).cast("long")).drop("__p")
        out = out.unionByName(_triangles(own, [*keys, "__lane"], cfg, 0).drop("__lane"))  # the levels are in the lanes
        # lane x meets every lane below it: its rows take all columns, theirs all rows
        first = own.filter("__lane > 0").select(*keys, F.col("__lane").alias("__x"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("__lane") - 1)).alias("__y"), F.col("row").alias("a"))
        second = own.filter("__lane < __d - 1").select(*keys, F.explode(F.sequence(F.col("__lane") + 1, F.col("__d") - 1)).alias("__x"), F.col("__lane").alias("__y"), F.col("row").alias("b"))
        met = first.join(second, [*keys, "__x", "__y"])
        swap = F.col("a")["id"] > F.col("b")["id"]
        out = out.unionByName(met.select(*keys, F.when(swap, F.col("b")).otherwise(F.col("a")).alias("a"), F.when(swap, F.col("a")).otherwise(F.col("b")).alias("b")))
    return present(out)


def self_join(df: DataFrame, left_on, right_on, cfg: JoinConfig = JoinConfig()) -> DataFrame:
    """Ordered self-join on different key columns."""
    from .adaptive import adaptive_join

    return adaptive_join(df, df, left_on, "inner", cfg, right_on=right_on)
