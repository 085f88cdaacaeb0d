"""The algorithms that the adaptive join is compared with.  All give the same rows."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from equiscale.functions.chunking import grid_lane
from equiscale.plans.config import JoinConfig
from equiscale.sources.io import cut

from .keys import Sides
from .small_large import BROADCAST_BYTES, in_pieces, must_be_small
from .staged import both_hot


def _plain(left, right, on, how, right_on, hint) -> DataFrame:
    sides = Sides.of(left, right, on, right_on)
    r = sides.right.hint(hint) if hint else sides.right
    return sides.present(sides.order(sides.left.join(r, sides.keys, how)))


def shuffle_hash_join(left, right, on, how="inner", *, right_on=None) -> DataFrame:
    """All rows of a key meet in one task."""
    return _plain(left, right, on, how, right_on, "shuffle_hash")


def sort_merge_join(left, right, on, how="inner", *, right_on=None) -> DataFrame:
    return _plain(left, right, on, how, right_on, "merge")


def broadcast_join(left, right, on, how="inner", *, right_on=None, weighted: bool = False) -> DataFrame:
    """The right side goes to every executor (inner, left, semi, anti); one that the driver cannot hold goes in pieces, see ``in_pieces``."""
    sides = Sides.of(left, right, on, right_on, weighted=weighted)
    out = in_pieces(sides, lambda x: x.left.join(F.broadcast(x.right), x.keys, how))
    return sides.present(out if how in ("left_semi", "left_anti") else sides.order(out), how in ("left_semi", "left_anti"))


def native_join(left, right, on, how="inner", *, right_on=None) -> DataFrame:
    """Spark's own choice, adaptive execution included."""
    return _plain(left, right, on, how, right_on, None)


#: Settings under which Spark splits skewed partitions of a shuffle join of even small tables.
SPLITTING = {"spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.skewJoin.enabled": "true", "spark.sql.adaptive.skewJoin.skewedPartitionFactor": "2", "spark.sql.adaptive.skewJoin.skewedPartitionThresholdInBytes": "64k", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "64k", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.join.preferSortMergeJoin": "true"}


def splitting_session(spark):
    """A session of the same application in which ``native_join`` splits skewed partitions; relations must be read through it."""
    own = spark.newSession()
    for k, v in SPLITTING.items():
        own.conf.set(k, v)
    for k in ("spark.sql.shuffle.partitions", "spark.sql.session.timeZone"):
        own.conf.set(k, spark.conf.get(k))
    return own


def _gridded(left: DataFrame, right: DataFrame, sides: Sides, grids: DataFrame, seed: int) -> DataFrame:
    """Join on (key, i, j); ``grids`` has keys, rows ``gr`` and columns ``gc``; other keys have one cell."""
    own = [df.join(F.broadcast(grids), sides.keys, "left").withColumns({"gr": F.coalesce("gr", F.lit(1)), "gc": F.coalesce("gc", F.lit(1))}) for df in (left, right)]
    l = sides.merged(own[0].withColumn("__i", grid_lane(left.columns, F.col("gr"), seed)), [*sides.keys, "gr", "gc", "__i"]).withColumn("__j", F.explode(F.sequence(F.lit(0), F.col("gc") - 1)))
    r = sides.merged(own[1].withColumn("__j", grid_lane(right.columns, F.col("gc"), seed + 1)), [*sides.keys, "gr", "gc", "__j"]).withColumn("__i", F.explode(F.sequence(F.lit(0), F.col("gr") - 1)))
    return sides.order(l.drop("gr", "gc").join(r.drop("gr", "gc"), [*sides.keys, "__i", "__j"]))


def _known(left, right, on, right_on, weighted: bool = False) -> Sides:
    return Sides.of(left, right, on, right_on, weighted=weighted).all_known()


def grid_join(left, right, on, n: int | None = None, cfg: JoinConfig = JoinConfig(), *, right_on=None, weighted: bool = False) -> DataFrame:
    """One square grid of about n cells for every hot key, in one round."""
    sides = _known(left, right, on, right_on, weighted)
    side = max(1, math.isqrt(n or left.sparkSession.sparkContext.defaultParallelism))
    kl, kr = both_hot(sides, cfg)
    grids = cut(kl.select(*sides.keys).unionByName(kr.select(*sides.keys)).distinct()).withColumns({"gr": F.lit(side), "gc": F.lit(side)})
    return sides.present(_gridded(sides.left, sides.right, sides, grids, cfg.seed))


def best_grid(a: float, b: float, budget: int) -> tuple[int, int]:
    """Rows x columns within ``budget`` cells with the least load of a cell: its input and its pairs."""
    found = (float("inf"), 1, 1)
    for r in range(1, max(1, budget) + 1):
        c = max(1, budget // r)
        found = min(found, (a / r + b / c + a * b / (r * c), r, c))
    return found[1], found[2]


def plan_grids(counts: list[tuple], n: int) -> list[tuple]:
    """(key.., rows, columns): each hot key's cells in proportion to its pairs."""
    total = sum(x[-2] * x[-1] for x in counts) or 1
    return [(*x[:-2], *best_grid(x[-2], x[-1], max(1, min(n, round(n * x[-2] * x[-1] / total))))) for x in counts]


def planned_grid_join(left, right, on, n: int | None = None, cfg: JoinConfig = JoinConfig(), *, right_on=None) -> DataFrame:
    """A grid for each hot key, planned on the driver over at most k_max keys; planning time grows with their number."""
    sides = _known(left, right, on, right_on)
    n = n or 4 * left.sparkSession.sparkContext.defaultParallelism
    kl, kr = both_hot(sides, cfg)
    hot = kl.withColumnRenamed("f", "fl").join(kr.withColumnRenamed("f", "fr"), sides.keys, "full").fillna(1, ["fl", "fr"])
    rows = [tuple(r) for r in hot.select(*sides.keys, "fl", "fr").collect()]
    schema = ", ".join(f"{k} {t}" for k, t in hot.select(*sides.keys).dtypes) + ", gr int, gc int"
    grids = left.sparkSession.createDataFrame(plan_grids(rows, n), schema)
    return sides.present(_gridded(sides.left, sides.right, sides, grids, cfg.seed))


def heavier_side_join(left, right, on, how="inner", cfg: JoinConfig = JoinConfig(), *, right_on=None, weighted: bool = False) -> DataFrame:
    """Rows of a hot key stay on the side that has more of them; the other side's are broadcast; cold keys shuffle.  Outer flavours pad by key.

    The published weakness of this method is that those rows must fit in memory: over ``cfg.broadcast_limit`` measured bytes it fails.
    """
    full = Sides.of(left, right, on, right_on, weighted=weighted)
    sides = _known(left, right, on, right_on, weighted)
    kl, kr = both_hot(sides, cfg)
    owner = cut(kl.withColumnRenamed("f", "fl").join(kr.withColumnRenamed("f", "fr"), sides.keys, "full").select(*sides.keys, (F.coalesce("fl", F.lit(0)) >= F.coalesce("fr", F.lit(0))).alias("__left")))
    own = [df.join(F.broadcast(owner), sides.keys, "left") for df in (sides.left, sides.right)]
    sent = lambda k, cond: must_be_small(sides.merged(part(k, cond), sides.keys), "heavier side", cfg.broadcast_limit)
    part = lambda k, cond: own[k].filter(cond).drop("__left")
    keeps_l, keeps_r = how in ("left", "full"), how in ("right", "full")
    cold = sides.order(sides.merged(part(0, "__left is null"), sides.keys).join(sides.merged(part(1, "__left is null"), sides.keys).hint("shuffle_hash"), sides.keys, how))
    a = sides.order(part(0, "__left").join(sent(1, "__left"), sides.keys, "left" if keeps_l else "inner"))
    b = sides.order(sent(0, "not __left").join(part(1, "not __left"), sides.keys, "right" if keeps_r else "inner"))
    out = cold.unionByName(a).unionByName(b)
    if keeps_r:  # keys owned by the other side that it lacks: some of the hot keys, few enough to broadcast
        out = out.unionByName(sides.pad_left(part(1, "__left").join(F.broadcast(part(0, "__left").select(*sides.keys).distinct()), sides.keys, "left_anti")))
    if keeps_l:
        out = out.unionByName(sides.pad_right(part(0, "not __left").join(F.broadcast(part(1, "not __left").select(*sides.keys).distinct()), sides.keys, "left_anti")))
    return full.present(full.with_nulls(out, how))


def pack_ranges(costs: list[float], bins: int) -> list[int]:
    """Bin of each range, the most costly first to the emptiest bin."""
    import heapq

    load = [(0.0, b) for b in range(bins)]
    out = [0] * len(costs)
    for i in sorted(range(len(costs)), key=lambda i: -costs[i]):
        w, b = heapq.heappop(load)
        out[i] = b
        heapq.heappush(load, (w + costs[i], b))
    return out


def key_range_join(left, right, on, parts: int | None = None, sample_factor: int = 10, *, right_on=None) -> DataFrame:
    """Key ranges cut from a sample, packed on tasks by estimated cost; a key is never divided.  Single-column keys."""
    sides = _known(left, right, on, right_on)
    k, spark = sides.keys[0], left.sparkSession
    if len(sides.keys) != 1:
        raise ValueError("key ranges need a single key column")
    parts = parts or 4 * spark.sparkContext.defaultParallelism
    want = sample_factor * parts
    counts: list[dict] = []
    for df in (sides.left, sides.right):
        n = df.count()
        rows = df.select(k).sample(min(1.0, want / max(1, n)), seed=3).groupBy(k).count().collect()  # about ``want`` rows
        scale = max(1.0, n / want)
        counts.append({r[0]: r[1] * scale for r in rows})
    keys = sorted(set(counts[0]) | set(counts[1]))
    cuts = keys[:: max(1, len(keys) // (4 * parts))] or [None]
    costs = [0.0] * len(cuts)
    at = -1
    for v in keys:
        while at + 1 < len(cuts) and v >= cuts[at + 1]:
            at += 1
        a, b = counts[0].get(v, 0), counts[1].get(v, 0)
        costs[max(at, 0)] += a + b + a * b
    bins = pack_ranges(costs, parts)
    if cuts == [None]:
        return sides.present(sides.order(sides.left.join(sides.right, k)))
    key_type = sides.left.schema[k].dataType
    table = F.array(*[F.lit(c).cast(key_type) for c in cuts])
    place = F.array(*[F.lit(b) for b in bins])
    # position of the last cut at or below the key
    nth = F.greatest(F.lit(0), F.size(F.filter(table, lambda c: c <= F.col(k))) - 1)
    own = [df.withColumn("__bin", F.get(place, nth)) for df in (sides.left, sides.right)]
    dealt = [df.repartitionById(parts, "__bin") for df in own]  # each bin is a task of its own
    return sides.present(sides.order(dealt[0].join(dealt[1].hint("shuffle_hash"), ["__bin", k])))


def _reported(big: DataFrame, small: DataFrame, on, right_on) -> tuple[Sides, DataFrame, DataFrame, int]:
    """(sides with small ids, matched (pid, id), all (pid, id), n); each of the n partitions of the large side stands for an executor.  The large side stays where it is."""
    sides = Sides.of(big, small, on, right_on)
    ided = cut(sides.right.withColumn("__id", F.monotonically_increasing_id()))
    n = max(1, sides.left.rdd.getNumPartitions())
    sides = sides.over(sides.left, ided)
    few = must_be_small(sides.known(ided).select(*sides.keys, "__id"), "small side", BROADCAST_BYTES)
    matched = sides.known(sides.left).select(F.spark_partition_id().alias("__pid"), *sides.keys).join(few, sides.keys).select("__pid", "__id").distinct()
    # every executor has all small rows: what it reports is made where they are, not sent there
    every = ided.select("__id", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("__pid"))
    return sides, cut(matched), every, n


def _outer(big, small, on, how, right_on, by_rows) -> DataFrame:
    sides, matched, every, n = _reported(big, small, on, right_on)
    missing = every.join(matched, ["__pid", "__id"], "left_anti")
    plain = sides.over(sides.left, sides.right.drop("__id"))
    if by_rows:
        # whole rows are sent and grouped
        rows = missing.join(must_be_small(sides.right, "small side", BROADCAST_BYTES), "__id")
        cols = [c for c in sides.right.columns if c != "__id"]
        lone = rows.groupBy("__id", *cols).agg(F.count("*").alias("__n")).filter(F.col("__n") == n).select(*cols)
    else:
        lone = sides.right.join(missing.groupBy("__id").agg(F.count("*").alias("__n")).filter(F.col("__n") == n).select("__id"), "__id", "left_semi")
    inner = plain.left.join(must_be_small(plain.right, "small side", BROADCAST_BYTES), plain.keys, "left" if how in ("left", "full") else "inner")
    out = plain.order(inner)
    if how in ("right", "full"):
        out = out.unionByName(plain.pad_left(lone.select(*plain.keys, *plain.rcols)))
    return plain.present(out)


def small_large_ids_outer(big, small, on, how="right", *, right_on=None) -> DataFrame:
    """Every executor reports ids of small rows it has no match for; an id that all report joins back."""
    return _outer(big, small, on, how, right_on, False)


def small_large_rows_outer(big, small, on, how="right", *, right_on=None) -> DataFrame:
    """The same with whole rows in place of ids."""
    return _outer(big, small, on, how, right_on, True)


def reported_rows(big, small, on, *, right_on=None) -> int:
    """Rows that all executors report together: what ids or rows cost."""
    _, matched, every, _ = _reported(big, small, on, right_on)
    return every.join(matched, ["__pid", "__id"], "left_anti").count()


BASELINES = {"shuffle_hash_join": shuffle_hash_join, "sort_merge_join": sort_merge_join, "broadcast_join": broadcast_join, "native_join": native_join, "grid_join": grid_join, "planned_grid_join": planned_grid_join, "heavier_side_join": heavier_side_join, "key_range_join": key_range_join}

__all__ = [*BASELINES, "reported_rows", "small_large_ids_outer", "small_large_rows_outer", "splitting_session"]
