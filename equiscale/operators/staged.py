"""The staged join: pairs of cold keys are emitted, lists of hot keys are cut and crossed, and the pieces spread anew, level by level.

Basic: levels start from whole lists.  Balanced: keys hot on both sides are found first and their rows
are dealt over a grid of padded keys at once, so that no task holds a whole hot list.  ``index='lists'`` works on arrays;
``index='cells'`` keeps flat rows and ends in one equi-join, which spills and streams.  Rows are dealt evenly over lanes, so
the size of a cell after any number of levels follows from the hot keys' frequencies: all levels are planned on
the small table of hot keys and run in one exchange (``levels='planned'``).  ``levels='counted'`` writes and counts each level instead.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from equiscale.functions.chunking import grid_lane, sublist_count
from equiscale.plans.config import JoinConfig
from equiscale.plans.cost import cube_root_ceil, level_bound
from equiscale.plans.metrics import avg_row_bytes
from equiscale.sources.io import cut

from . import index
from .hotkeys import hot_keys, partition_variance, shared_hot
from .keys import Sides, check_how, field, names


def respread(idx: DataFrame, n: int) -> DataFrame:
    """Rows dealt by a hash of all they hold, so one key's sub-lists go to many tasks and a task run again deals alike."""
    return idx.repartition(n, F.xxhash64(*[field(idx, c) for c in idx.columns]))


def _predicate(cfg: JoinConfig, floor: float = 0.0) -> Column:
    """Entries to be cut: hot ones of more than ``floor`` pairs."""
    if cfg.hot_predicate is not None:
        return cfg.hot_predicate(F.size("ls"), F.size("rs"))
    return index.is_hot(F.col("ls"), F.col("rs"), max(cfg.theta, math.sqrt(floor)))


def level(idx: DataFrame, sides: Sides, cfg: JoinConfig, floor: float = 0.0) -> tuple[DataFrame, DataFrame]:
    """(pairs of cold keys, index of the next level)."""
    cold, hot = index.split_local(idx, _predicate(cfg, floor))
    return index.emit_pairs(cold, sides), respread(index.cross_chunks(hot, sides, cfg.chunk_rule), cfg.partitions(idx.sparkSession))


def levels_of(l_max: float, cfg: JoinConfig) -> int:
    """Levels that lists of ``l_max`` rows on both sides need: as many as the bound says, or as cutting them takes if that is more."""
    n, taken = math.ceil(l_max), 0
    while n > cfg.theta and n > 1:
        n, taken = -(-n // cube_root_ceil(n)), taken + 1
    return max(1, taken, math.ceil(level_bound(l_max, cfg.lam)) + 1)


def _levels(idx: DataFrame, sides: Sides, cfg: JoinConfig, l_max: float, floor: float = 0.0) -> DataFrame:
    """All levels.  Static: as many as the bound says and one more that emits all that is left, so a wrong bound loses nothing.

    The order of rows in a collected list can differ each time that it is collected.  Hot lists are therefore written once,
    so that all levels cut the same sub-lists; which keys are cold does not depend on the order.  Entries of at most ``floor`` pairs are not cut.
    Weighted sub-lists are one row after the first cut, so nothing is left to cut further.
    """
    out = None
    if cfg.loop == "dynamic":
        while True:
            idx = cut(idx)
            pairs, idx = level(idx, sides, cfg)
            out = pairs if out is None else out.unionByName(pairs)
            idx = cut(idx)
            if idx.isEmpty():
                return out
    cold, hot = index.split_local(idx, _predicate(cfg, floor))
    out, idx = index.emit_pairs(cold, sides), cut(hot)
    idx = respread(index.cross_chunks(idx, sides, cfg.chunk_rule), cfg.partitions(idx.sparkSession))
    for _ in range(0 if sides.weighted else levels_of(l_max, cfg) - 1):
        pairs, idx = level(idx, sides, cfg, floor)
        out = out.unionByName(pairs)
    return out.unionByName(index.emit_pairs(idx, sides))


def _walk(left: DataFrame, right: DataFrame, on, cfg: JoinConfig, measure: Column) -> list[tuple[int, int, int, int]]:
    """(level, entries, hot entries, largest ``measure`` of an entry) of each level of the basic form, until none is hot."""
    sides = Sides.of(left, right, on)
    idx = index.build_joined_index(sides)
    rows = []
    while True:
        idx = cut(idx)
        n, hot, most = idx.agg(F.count("*"), F.count(F.when(_predicate(cfg), 1)), F.max(measure)).first()
        rows.append((len(rows), n, hot, most or 0))
        if not hot:
            return rows
        idx = level(idx, sides, cfg)[1]


def level_sizes(left: DataFrame, right: DataFrame, on, cfg: JoinConfig = JoinConfig()) -> DataFrame:
    """(level, entries, hot): index entries of each level of the basic form, until none is left."""
    rows = [r[:3] for r in _walk(left, right, on, cfg, F.lit(0))]
    return left.sparkSession.createDataFrame(rows, "level int, entries long, hot long")


def level_loads(left: DataFrame, right: DataFrame, on, cfg: JoinConfig = JoinConfig()) -> DataFrame:
    """(level, entries, heaviest): the pairs that the heaviest index entry of each level stands for, which bound the work of a task."""
    rows = [(at, n, most) for at, n, _, most in _walk(left, right, on, cfg, F.size("ls").cast("long") * F.size("rs"))]
    return left.sparkSession.createDataFrame(rows, "level int, entries long, heaviest long")


def _longest(sides: Sides) -> float:
    counts = [df.groupBy(*sides.keys).agg(F.count("*").alias("f")).agg(F.max("f")).first()[0] or 1 for df in (sides.left, sides.right)]
    return math.sqrt(counts[0] * counts[1]) if counts[0] * counts[1] else 1


def staged_join_basic(left: DataFrame, right: DataFrame, on, how: str = "inner", cfg: JoinConfig = JoinConfig(), *, right_on=None, weighted: bool = False) -> DataFrame:
    check_how(how)
    sides = Sides.of(left, right, on, right_on, cfg.null_safe, weighted)
    own = sides.all_known()
    pairs = _levels(index.build_joined_index(own, how), own, cfg, _longest(own) if cfg.loop == "static" else 1, list_floor(own, cfg))
    return sides.present(sides.with_nulls(pairs, how))


def list_floor(sides: Sides, cfg: JoinConfig) -> float:
    """Pairs up to which an entry of weighted lists stays whole: the same part of a task's fair share as for cells.  Their
    entries give one row each, so cutting them further only copies them."""
    if not sides.weighted:
        return 0.0
    a, b = (df.groupBy(*sides.keys).agg(F.count("*").alias(f)) for df, f in ((sides.left, "fl"), (sides.right, "fr")))
    pairs = a.join(b, sides.keys).agg(F.sum(F.col("fl").cast("double") * F.col("fr"))).first()[0]
    return cfg.cell_share * (pairs or 0.0) / cfg.executors(sides.left.sparkSession)


def split_shared(df: DataFrame, kappa: DataFrame, keys: list[str]) -> tuple[DataFrame, DataFrame]:
    """(rows of shared hot keys with the columns of ``kappa``, other rows), without a shuffle."""
    small = F.broadcast(kappa)
    return df.join(small, keys), df.join(small.select(*keys), keys, "left_anti")


def planned_cells(kappa: DataFrame, cfg: JoinConfig, pairs: float, tasks: int, longest: float = float("inf")) -> DataFrame:
    """``kappa`` (keys, fl, fr) with ``__dl`` and ``__dr``, the lanes of both lists after all levels, and ``__lv``, their number.

    Each level cuts both lists of a cell as the chunking rule says, while its lists are hot by their geometric mean and its pairs are over
    ``cell_share`` of a task's fair share of all pairs, or a list is over ``longest``.  The copies of a row are bounded by ``max_copies``.
    """
    floor = max(cfg.theta**2, cfg.cell_share * pairs / max(1, tasks))
    start = F.struct(F.col("fl").cast("double").alias("a"), F.col("fr").cast("double").alias("b"), F.lit(1).cast("long").alias("dl"), F.lit(1).cast("long").alias("dr"), F.lit(0).alias("n"))

    def step(x: Column, _: Column) -> Column:
        most = F.lit(cfg.max_copies).cast("double")
        cl = F.least(sublist_count(x["a"], x["b"], cfg.chunk_exponent).cast("double"), F.floor(most / x["dl"]))
        cr = F.least(sublist_count(x["b"], x["a"], cfg.chunk_exponent).cast("double"), F.floor(most / x["dr"]))
        more = (x["a"] * x["b"] > floor) | (F.greatest(x["a"], x["b"]) > longest)
        go = more & (F.greatest(cl, cr) > 1)
        nxt = F.struct(F.ceil(x["a"] / cl).cast("double").alias("a"), F.ceil(x["b"] / cr).cast("double").alias("b"), (x["dl"] * cl).cast("long").alias("dl"), (x["dr"] * cr).cast("long").alias("dr"), (x["n"] + 1).alias("n"))
        return F.when(go, nxt).otherwise(x)

    plan = F.aggregate(F.sequence(F.lit(1), F.lit(cfg.max_levels)), start, step)
    return kappa.withColumn("__plan", plan).select(*kappa.columns, F.col("__plan")["dl"].alias("__dl"), F.col("__plan")["dr"].alias("__dr"), F.col("__plan")["n"].alias("__lv"))


def placed(df: DataFrame) -> DataFrame:
    """The rows, written, each with its place ``__p``."""
    return cut(df.withColumn("__p", F.monotonically_increasing_id()))


def unravel(df: DataFrame, side: str, cfg: JoinConfig, level_no: int = 0, i: str = "__i", j: str = "__j", merge=None) -> DataFrame:
    """Rows of hot keys (with ``__dl`` and ``__dr``) over their key's grid: a left row takes one grid row and all columns, a right row the other way.

    ``df`` has the place of each row, written once: lanes by place are even, also among equal rows, and a task run again deals alike.
    ``merge`` (rows, columns) adds up the rows of a lane before they are copied.
    """
    seed = cfg.seed + 101 * level_no + (side == "right")
    own, other, a, b = ("__dl", "__dr", i, j) if side == "left" else ("__dr", "__dl", j, i)
    dealt = df.withColumn(a, grid_lane(["__p"], F.col(own), seed))
    if merge is not None:
        dealt = merge(dealt, [*[c for c in df.columns if c.startswith("__k")], "__dl", "__dr", a])
    return dealt.withColumn(b, F.explode(F.sequence(F.lit(0).cast("long"), F.col(other) - 1))).drop("__dl", "__dr")


def _cell_join(left: DataFrame, right: DataFrame, sides: Sides, plan: DataFrame, cfg: JoinConfig) -> DataFrame:
    """Inner join of placed rows of shared hot keys by grid cells."""
    by = list(sides.keys)
    if cfg.levels == "planned":
        small = F.broadcast(plan.select(*by, "__dl", "__dr"))
        merge = sides.merged if sides.weighted else None
        left, right = unravel(left.join(small, by), "left", cfg, merge=merge), unravel(right.join(small, by), "right", cfg, merge=merge)
        return sides.order(left.join(right, [*by, "__i", "__j"]))
    sizes = F.broadcast(plan.select(*by, "fl", "fr"))
    for t in range(cfg.max_levels):
        i, j = f"__i{t}", f"__j{t}"
        lanes = {"__dl": F.least(sublist_count(F.col("fl"), F.col("fr"), cfg.chunk_exponent), F.lit(cfg.max_copies)).cast("long"), "__dr": F.least(sublist_count(F.col("fr"), F.col("fl"), cfg.chunk_exponent), F.lit(cfg.max_copies)).cast("long")}
        sizes = sizes.withColumns(lanes).drop("fl", "fr")
        marked = [df.join(sizes, by, "left").withColumns({"__dl": F.coalesce("__dl", F.lit(1)), "__dr": F.coalesce("__dr", F.lit(1))}) for df in (left, right)]
        left, right = cut(unravel(marked[0], "left", cfg, t, i, j)), cut(unravel(marked[1], "right", cfg, t, i, j))
        by += [i, j]
        a, b = (df.groupBy(*by).agg(F.count("*").alias(n)) for df, n in ((left, "fl"), (right, "fr")))
        sizes = cut(a.join(b, by).filter(F.sqrt(F.col("fl").cast("double") * F.col("fr").cast("double")) > cfg.theta))
        if sizes.isEmpty():
            break
    return sides.order(sides.merged(left, by).join(sides.merged(right, by), by))


def plan_of(shared: DataFrame, cfg: JoinConfig) -> tuple[DataFrame, float]:
    """(written keys hot on both sides with frequencies and planned cells, the longest geometric mean)."""
    a, b = F.col("fl").cast("double"), F.col("fr").cast("double")
    pairs, longest = shared.agg(F.sum(a * b), F.max(F.sqrt(a * b))).first()
    return planned_cells(shared, cfg, pairs or 0.0, cfg.executors(shared.sparkSession)), longest or 1.0


def shared_plan(kl: DataFrame, kr: DataFrame, keys: list[str], cfg: JoinConfig) -> tuple[DataFrame, float]:
    return plan_of(cut(shared_hot(kl, kr, keys)), cfg)


def grid_levels(left: DataFrame, right: DataFrame, on, cfg: JoinConfig = JoinConfig(), *, right_on=None) -> DataFrame:
    """keys, fl, fr, rows and columns of its grid, levels and the largest cell's pairs by plan, of each key that is hot on both sides.

    The plan is shown as the threshold asks for it; joins also bound the copies of a row by ``max_copies``.
    """
    sides = Sides.of(left, right, on, right_on, cfg.null_safe).all_known()
    plan, _ = shared_plan(*both_hot(sides, cfg), sides.keys, cfg.but(max_copies=1 << 53))
    shown = [(F.col(k)["v"] if sides.null_safe else F.col(k)).alias(n) for k, n in zip(sides.keys, sides.names)]
    cell = F.ceil(F.col("fl") / F.col("__dl")) * F.ceil(F.col("fr") / F.col("__dr"))
    return plan.select(*shown, "fl", "fr", F.col("__dl").alias("grid_rows"), F.col("__dr").alias("grid_columns"), F.col("__lv").alias("levels"), cell.cast("long").alias("cell_pairs"))


def staged_join(left: DataFrame, right: DataFrame, on, how: str = "inner", cfg: JoinConfig = JoinConfig(), *, right_on=None, kappa: tuple[DataFrame, DataFrame] | None = None, weighted: bool = False) -> DataFrame:
    """Balanced form.  ``kappa``: hot keys of both sides (columns as ``hot_keys`` gives them for the left keys) if they are known already."""
    check_how(how)
    sides = Sides.of(left, right, on, right_on, cfg.null_safe, weighted)
    return sides.present(sides.with_nulls(staged_pairs(sides, how, cfg, keyed(kappa, sides)), how))


def keyed(kappa, sides: Sides):
    """The caller's hot keys in the inner form; the last column is the frequency."""
    if kappa is None:
        return None
    out = []
    for k in kappa:
        inner = k.toDF(*sides.keys, "f")
        out.append(inner.select(*[(F.struct(F.col(c).alias("v")) if sides.null_safe else F.col(c)).alias(c) for c in sides.keys], "f"))
    return tuple(out)


def both_hot(sides: Sides, cfg: JoinConfig) -> tuple[DataFrame, DataFrame]:
    """Written hot keys of both sides, at most as many as fit in memory."""
    opts = {"theta": cfg.theta, "method": cfg.hot_method, "capacity": cfg.capacity, "fanout": cfg.fanout, "refine": cfg.refine}
    spark, out = sides.left.sparkSession, []
    for own, other, k_max, width in ((sides.left, sides.right, cfg.k_max_left, cfg.right_bytes), (sides.right, sides.left, cfg.k_max_right, cfg.left_bytes)):
        k_max = k_max or cfg.hot_budget(spark, width or avg_row_bytes(other))
        out.append(cut(hot_keys(sides.known(own), sides.keys, k_max, **opts)))
    return tuple(out)


def staged_pairs(sides: Sides, how: str, cfg: JoinConfig, kappa=None) -> DataFrame:
    own = sides.all_known()
    kl, kr = kappa or both_hot(own, cfg)
    plan, l_max = shared_plan(kl, kr, own.keys, cfg)
    (hl, cl), (hr, cr) = split_shared(own.left, plan, own.keys), split_shared(own.right, plan, own.keys)
    hl, hr = (placed(df.drop("fl", "fr", "__lv", "__dl", "__dr")) for df in (hl, hr))
    if cfg.index == "cells":
        return own.order(own.merged(cl, own.keys).join(own.merged(cr, own.keys), own.keys, how)).unionByName(_cell_join(hl, hr, own, plan, cfg))
    idx = build_padded_index(own, hl, cl, hr, cr, how, cfg, plan)
    return _levels(idx, own, cfg, max(l_max ** (2 / 3), cfg.theta))


def build_padded_index(sides: Sides, hl, cl, hr, cr, how: str, cfg: JoinConfig, plan: DataFrame) -> DataFrame:
    """Hot rows over their grids and cold rows at (-1, -1) meet in one exchange; then the padding goes.

    Only cold keys can be one-sided: a shared hot key matches, and an empty cell of its grid means nothing.
    """
    zero = {"__i": F.lit(-1).cast("long"), "__j": F.lit(-1).cast("long")}
    # one level is dealt here, the others follow on lists
    lanes = F.broadcast(plan.select(*sides.keys, *[F.least(sublist_count(F.col(x), F.col(y), cfg.chunk_exponent), F.lit(cfg.max_copies)).cast("long").alias(d) for x, y, d in (("fl", "fr", "__dl"), ("fr", "fl", "__dr"))]))
    left = unravel(hl.join(lanes, sides.keys), "left", cfg).drop("__p").unionByName(cl.withColumns(zero))
    right = unravel(hr.join(lanes, sides.keys), "right", cfg).drop("__p").unionByName(cr.withColumns(zero))
    idx = index.build_joined_index(sides.over(left, right), "full", ["__i", "__j"])
    two = (F.size("ls") > 0) & (F.size("rs") > 0)
    one = {"inner": F.lit(False), "left": F.size("ls") > 0, "right": F.size("rs") > 0, "full": F.lit(True)}[how]
    return idx.filter(two | ((F.col("__i") < 0) & one)).drop("__i", "__j")


def spread_input(df: DataFrame, on, hot: DataFrame, *, factor: float = 1.0) -> DataFrame:
    """Deals anew the rows of those hot keys (columns as ``hot_keys`` gives them) that sit together in few partitions; other rows stay."""
    shown = names(on)
    keys = [f"__s{i}" for i in range(len(shown))]
    marked = df.select(*[field(df, c) for c in df.columns], *[field(df, c).alias(k) for c, k in zip(shown, keys)])
    n = max(1, df.rdd.getNumPartitions())
    spread = partition_variance(marked, keys).toDF(*keys, "__v", "__f")
    # rows spread evenly have a variance near their mean
    lumped = cut(spread.join(F.broadcast(hot.toDF(*keys, "__hot").select(*keys)), keys).filter(F.col("__v") > factor * F.col("__f") / n).select(*keys))
    stay, move = (marked.join(F.broadcast(lumped), keys, kind).select(*[field(marked, c) for c in df.columns]) for kind in ("left_anti", "left_semi"))
    return stay.unionByName(respread(move, n))
