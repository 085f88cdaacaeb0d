"""The adaptive join: both sides are split by whether a key is hot here and hot there, and each of the four pieces is joined its own way.

hot-hot: staged; hot-cold: the cold rows are few and are broadcast; cold-hot: the same with sides exchanged; cold-cold: a shuffle
join.  The union needs no deduplication, for every flavour.  Each side is split once: rows of keys that are hot on
either side are written by class, which also measures the pieces; the others are read again as they come.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from equiscale.plans.config import JoinConfig
from equiscale.plans.cost import prefer_broadcast
from equiscale.plans.metrics import row_width
from equiscale.sources.io import cut, shared_dir

from . import index
from .keys import Sides, check_how, names
from .small_large import index_broadcast_pairs
from .staged import _cell_join, _levels, both_hot, build_padded_index, keyed, list_floor, plan_of, staged_join

CLASSES = ("hh", "hc", "ch", "cc")


def route_map(kl: DataFrame, kr: DataFrame, keys: list[str]) -> DataFrame:
    """keys, fl, fr: either is null where the key isn't hot."""
    return kl.withColumnRenamed("f", "fl").join(kr.withColumnRenamed("f", "fr"), keys, "full")


def route():
    """Class of a row by where its key is hot."""
    return F.when(F.col("fl").isNotNull() & F.col("fr").isNotNull(), "hh").when(F.col("fl").isNotNull(), "hc").when(F.col("fr").isNotNull(), "ch").otherwise("cc")


def split_relation(df: DataFrame, routes: DataFrame, keys: list[str], how: str = "left") -> DataFrame:
    """Adds ``route``: both rounds of splitting in one broadcast join."""
    return df.join(F.broadcast(routes), keys, how).withColumn("route", route()).drop("fl", "fr")


class Pieces:
    """One side by class.  ``size`` has the measured rows and bytes of the written ones."""

    def __init__(self, df: DataFrame, routes: DataFrame, keys: list[str], every: bool):
        spark = df.sparkSession
        self.columns = df.columns
        marked = split_relation(df, routes, keys, "left" if every else "inner").withColumn("__p", F.monotonically_increasing_id())
        path = f"{shared_dir(spark)}/pieces-{uuid.uuid4().hex}"
        marked.write.partitionBy("route").parquet(path)
        self.written = spark.read.schema(marked.schema).parquet(path)
        rows = self.written.groupBy("route").agg(F.count("*").alias("n"), F.sum(row_width(self.written.select(*self.columns))).alias("b")).collect()
        self.size = {r["route"]: (r["n"], r["b"]) for r in rows}
        self.rest = None if every else df.join(F.broadcast(routes.select(*keys)), keys, "left_anti")

    def placed(self, name: str) -> DataFrame:
        return self.written.filter(F.col("route") == name).drop("route")

    def __getitem__(self, name: str) -> DataFrame:
        return self.rest if name == "cc" and self.rest is not None else self.placed(name).select(*self.columns)


def swap_sides(sides: Sides, left: DataFrame, right: DataFrame) -> Sides:
    """Sides exchanged for the piece whose right rows are many; ``order`` puts the columns back."""
    turned = [right.toDF(*[c.replace("__r_", "__l_", 1) if c.startswith("__r_") else c for c in right.columns]), left.toDF(*[c.replace("__l_", "__r_", 1) if c.startswith("__l_") else c for c in left.columns])]
    return Sides(*turned, sides.keys, sides.names, sides.null_safe, sides.right_names, sides.left_names, sides.weighted)


def _unswap(sides: Sides, pairs: DataFrame) -> DataFrame:
    back = pairs.toDF(*["__r_" + c[4:] if c.startswith("__l_") else "__l_" + c[4:] if c.startswith("__r_") else c for c in pairs.columns])
    return sides.order(back)


def _semi(sides: Sides, how: str, kappa_l: DataFrame) -> DataFrame:
    """Left semi and anti: hot left keys are looked up among the right keys once, and the verdict is broadcast."""
    left, right = sides.known(sides.left), sides.known(sides.right).select(*sides.keys)
    hot = F.broadcast(kappa_l.select(*sides.keys))
    there = F.broadcast(cut(right.join(hot, sides.keys, "left_semi").distinct()))  # some of the hot keys
    out = left.join(hot, sides.keys, "left_semi").join(there, sides.keys, how)
    out = out.unionByName(left.join(hot, sides.keys, "left_anti").join(right.distinct(), sides.keys, how))
    return out if how == "left_semi" else out.unionByName(sides.unknown(sides.left))


def adaptive_join(left: DataFrame, right: DataFrame, on, how: str = "inner", cfg: JoinConfig = JoinConfig(), *, right_on=None, kappa: tuple[DataFrame, DataFrame] | None = None, hh: str = "balanced", residual=None, weighted: bool = False) -> DataFrame:
    """``hh='basic'`` joins the hot-hot piece without its grid.  ``residual`` (columns -> condition, inner only) filters pairs.
    ``weighted``: rows of a piece or lane that have one key may be added up before they meet (see ``totals.join_totals``).

    A relation joined with itself on the same key has no key that is hot on one side alone: the staged join does all of it.
    """
    check_how(how)
    if how in ("right_semi", "right_anti"):
        turned = kappa and (kappa[1], kappa[0])
        return adaptive_join(right, left, on if right_on is None else right_on, how.replace("right", "left"), cfg, right_on=on, kappa=turned, hh=hh)
    if residual is not None and how != "inner":
        raise ValueError("a residual condition is for inner joins: elsewhere it belongs to the match")
    same = how not in ("left_semi", "left_anti") and hh == "balanced" and (right_on is None or names(on) == names(right_on)) and left.sameSemantics(right)
    if same:
        out = staged_join(left, right, on, how, cfg, right_on=right_on, kappa=kappa, weighted=weighted)
        return out if residual is None else out.filter(residual(out))
    sides = Sides.of(left, right, on, right_on, cfg.null_safe, weighted)
    own = sides.all_known()
    kl, kr = keyed(kappa, sides) or both_hot(own, cfg)
    if how in ("left_semi", "left_anti"):
        return sides.present(_semi(sides, how, kl), only_left=True)
    routes = cut(route_map(kl, kr, own.keys))
    plan, l_max = plan_of(routes.filter("fl is not null and fr is not null"), cfg)
    sl, sr = (Pieces(df, routes, own.keys, cfg.split == "all") for df in (own.left, own.right))
    preserve_l, preserve_r = how in ("left", "full"), how in ("right", "full")
    trusted = cfg.kappa_trusted
    parts = [own.order(own.merged(sl["cc"], own.keys).join(own.merged(sr["cc"], own.keys).hint("shuffle_hash"), own.keys, how))]

    # hot-hot: both sides have the key, so nothing is padded
    if "hh" in sl.size and "hh" in sr.size:
        if hh == "basic":
            pair = own.over(sl["hh"], sr["hh"])
            hot = _levels(index.build_joined_index(pair), pair, cfg, l_max, list_floor(pair, cfg))
        elif cfg.index == "lists":
            hl, hr = sl.placed("hh"), sr.placed("hh")
            idx = build_padded_index(own, hl, sl["hh"].limit(0), hr, sr["hh"].limit(0), "inner", cfg, plan)
            hot = _levels(idx, own, cfg, max(l_max ** (2 / 3), cfg.theta))
        else:
            hot = _cell_join(sl.placed("hh"), sr.placed("hh"), own, plan, cfg)
        parts.append(own.order(hot))
    if not trusted:
        # a key called hot may be absent on its side: pad its rows by key
        parts.append(own.order(_missing(own, sl["hh"], sr["hh"], preserve_l, preserve_r)))

    # hot-cold and cold-hot: at most k_max * theta cold rows
    def flavour(keeps_hot: bool, keeps_cold: bool) -> str:
        keeps_cold = keeps_cold and not trusted  # a key that really is hot there has a partner for every cold row
        return "full" if keeps_hot and keeps_cold else "left" if keeps_hot else "right" if keeps_cold else "inner"

    if "hc" in sl.size or "hc" in sr.size:
        parts.append(own.order(_hot_cold(own.over(sl["hc"], sr["hc"]), cfg, sl.size.get("hc"), sr.size.get("hc"), flavour(preserve_l, preserve_r))))
    if "ch" in sl.size or "ch" in sr.size:
        turned = swap_sides(own, sl["ch"], sr["ch"])
        parts.append(_unswap(own, _hot_cold(turned, cfg, sr.size.get("ch"), sl.size.get("ch"), flavour(preserve_r, preserve_l))))
    pairs = parts[0]
    for p in parts[1:]:
        pairs = pairs.unionByName(p)
    out = sides.present(sides.with_nulls(pairs, how))
    return out if residual is None else out.filter(residual(out))


def _missing(sides: Sides, hl: DataFrame, hr: DataFrame, preserve_l: bool, preserve_r: bool) -> DataFrame:
    """Rows of keys that only one side really has.  The distinct keys are some of the hot ones, so they are few enough to broadcast."""
    out = sides.pad_right(hl).limit(0)
    if preserve_l:
        out = out.unionByName(sides.pad_right(hl.join(F.broadcast(hr.select(*sides.keys).distinct()), sides.keys, "left_anti")))
    if preserve_r:
        out = out.unionByName(sides.pad_left(hr.join(F.broadcast(hl.select(*sides.keys).distinct()), sides.keys, "left_anti")))
    return out


def _hot_cold(sides: Sides, cfg: JoinConfig, big: tuple[int, int] | None, few: tuple[int, int] | None, how: str) -> DataFrame:
    """The left rows are of hot keys; the right slice is broadcast if the model says so and it fits by its measured size, else shuffled."""
    (n_big, b_big), (n_few, b_few) = big or (0, 0), few or (0, 0)
    use = cfg.broadcast == "always"
    if cfg.broadcast == "model":
        use = b_few <= cfg.broadcast_limit and prefer_broadcast(n_big, cfg.left_bytes or b_big / max(1, n_big), n_few, cfg.right_bytes or b_few / max(1, n_few), cfg.lam, cfg.executors(sides.left.sparkSession))
    sides = sides.over(sides.left, sides.merged(sides.right, sides.keys))
    if use:
        return index_broadcast_pairs(sides, how, checked=True)
    return sides.order(sides.merged(sides.left, sides.keys).join(sides.right.hint("merge"), sides.keys, how))


def piece_sizes(left: DataFrame, right: DataFrame, on, cfg: JoinConfig = JoinConfig(), *, right_on=None) -> DataFrame:
    """(side, route, n): rows of each piece."""
    own = Sides.of(left, right, on, right_on).all_known()
    routes = cut(route_map(*both_hot(own, cfg), own.keys))
    parts = [split_relation(df.select(*own.keys), routes, own.keys).groupBy("route").agg(F.count("*").alias("n")).select(F.lit(side).alias("side"), "route", "n") for side, df in (("left", own.left), ("right", own.right))]
    return parts[0].unionByName(parts[1])
