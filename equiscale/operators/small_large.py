"""Joins of a large relation with a small one that is broadcast; the large side never shuffles, in any flavour.

Spark has no broadcast form of a join that preserves the broadcast side.  Right and full outer are put
together: inner or left outer, and the small rows whose key no large row has, found by keys alone.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from equiscale.plans.metrics import measured, row_width
from equiscale.sources.io import cut, release, shared_dir

from .keys import Sides, TooLargeToBroadcast, check_how

#: Spark's own limit of a broadcast relation is 8 GB; beyond this many bytes, by the planner's estimate, the joins below go by shuffle.
BROADCAST_BYTES = 1 << 30


def estimated_bytes(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def small(df: DataFrame, limit: int = BROADCAST_BYTES, checked: bool = False) -> DataFrame:
    """Broadcast hint for a side that is small enough, by the planner's estimate or, if ``checked``, as its caller has measured; none beyond."""
    return F.broadcast(df) if checked or estimated_bytes(df) <= limit else df


def must_be_small(df: DataFrame, what: str, limit: float) -> DataFrame:
    """Broadcast hint for a side measured row by row; the method that needs it fails beyond ``limit`` bytes."""
    n, size = measured(df)
    if size > limit:
        raise TooLargeToBroadcast(f"{what}: {n} rows of {size} bytes are over the limit of {int(limit)} bytes for a broadcast")
    return F.broadcast(df)


#: Measured bytes of a side that the driver can build, hold and send at once: as a hash relation they take about six times as much.
PIECE_BYTES = 16 << 20


def _by_piece(df: DataFrame, piece) -> DataFrame:
    """The rows, written with one folder for each piece; they do not shuffle for it."""
    marked = df.withColumn("__piece", piece)
    path = f"{shared_dir(df.sparkSession)}/pieces-{uuid.uuid4().hex}"
    marked.write.partitionBy("__piece").parquet(path)
    out = df.sparkSession.read.schema(marked.schema).parquet(path)
    out._cut = path
    return out


def grouped_pieces(sizes: dict[int, int], n: int, limit: int) -> list[list[int]]:
    """All pieces 0 to n-1 in groups of at most ``limit`` bytes, or of one piece."""
    groups, held = [[]], 0
    for p in range(n):
        own = sizes.get(p, 0)
        if groups[-1] and held + own > limit:
            groups.append([])
            held = 0
        groups[-1].append(p)
        held += own
    return groups


def in_pieces(sides: Sides, join) -> DataFrame:
    """``join`` (sides -> rows), which broadcasts the right side.  A right side of more than PIECE_BYTES before its rows are added
    up is written in pieces by a hash of its keys; of added-up rows, measured bytes say which pieces go together.  If it takes several
    broadcasts, the left rows are written by piece once, without a shuffle; each broadcast meets the left rows of its keys and that
    result is written before the next one goes, so that the driver never has two."""
    right = sides.merged(sides.right, sides.keys)
    n = -(-measured(sides.right)[1] // PIECE_BYTES)
    if n <= 1:
        return join(sides.over(sides.left, right))
    piece = F.pmod(F.xxhash64(*sides.keys), F.lit(n)).cast("int")
    held = _by_piece(right, piece)
    groups = [[p] for p in range(n)]
    if sides.weighted:  # fewer rows than were measured
        rows = held.groupBy("__piece").agg(F.sum(row_width(held.select(*right.columns))).alias("b")).collect()
        groups = grouped_pieces({r["__piece"]: r["b"] for r in rows}, n, PIECE_BYTES)
    if len(groups) == 1:
        return join(sides.over(sides.left, held.drop("__piece")))
    own, out = _by_piece(sides.left, piece), None
    for group in groups:
        got = cut(join(sides.over(*(df.filter(F.col("__piece").isin(group)).drop("__piece") for df in (own, held)))))
        out = got if out is None else out.unionByName(got)
    release(own, held)
    return out


def build_index(sides: Sides) -> DataFrame:
    """keys, ``rs``: the small side's rows by key."""
    return sides.known(sides.right).groupBy(*sides.keys).agg(F.collect_list(F.struct(*sides.rcols, F.lit(0).alias("__"))).alias("rs"))


def _probe(sides: Sides, how: str, mode: str, checked: bool = False) -> DataFrame:
    left = sides.known(sides.left)
    if mode == "native":
        return sides.order(left.join(small(sides.known(sides.right), checked=checked), sides.keys, how))
    met = left.join(small(build_index(sides), checked=checked), sides.keys, how)
    met = met.withColumn("__b", F.explode_outer("rs") if how == "left" else F.explode("rs"))
    return met.select(*sides.keys, *sides.lcols, *[F.col("__b")[c].alias(c) for c in sides.rcols])


def joined_keys(sides: Sides, partition_set: bool = False, checked: bool = False) -> DataFrame:
    """Distinct small keys that a large row has.  Each task combines its own set before sets meet."""
    keys = small(sides.known(sides.right).select(*sides.keys).distinct(), checked=checked)
    met = sides.known(sides.left).select(*sides.keys).join(keys, sides.keys, "left_semi")
    if not partition_set:
        return met.distinct()
    schema = met.schema

    def one_set(batches):
        import pyarrow as pa

        seen: set = set()
        for batch in batches:
            seen.update(zip(*[c.to_pylist() for c in batch.columns]))
        yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(zip(*seen), _arrow(schema))] if seen else [pa.array([], f.type) for f in _arrow(schema)], schema.names)

    return met.mapInArrow(one_set, schema).distinct()


def _arrow(schema):
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(schema)


def unjoinable_keys(sides: Sides, joined: DataFrame) -> DataFrame:
    return sides.known(sides.right).select(*sides.keys).distinct().join(small(joined), sides.keys, "left_anti")


def right_anti_rows(sides: Sides, *, smaller_keyset: bool = False, partition_set: bool = False, joined: DataFrame | None = None, checked: bool = False) -> DataFrame:
    """Small rows of keys that no large row has.  ``smaller_keyset`` sends the smaller of the joined and the unjoinable keys."""
    right = sides.known(sides.right)
    joined = cut(joined if joined is not None else joined_keys(sides, partition_set, checked))
    if smaller_keyset:
        n = right.select(*sides.keys).distinct().count()
        if 2 * joined.count() > n:
            return right.join(small(cut(unjoinable_keys(sides, joined))), sides.keys, "left_semi")
    return right.join(small(joined), sides.keys, "left_anti")


def index_broadcast_join(big: DataFrame, small_df: DataFrame, on, how: str = "inner", *, right_on=None, mode: str = "native", opt_smaller_keyset: bool = False, opt_single_scan: bool = False, opt_partition_set: bool = False, variant: str = "whole", null_safe: bool = False) -> DataFrame:
    """``big`` is the left side.  ``mode='index'`` groups the small side by key first.  ``variant='semi_reduced'`` broadcasts keys, then only rows that join."""
    check_how(how)
    sides = Sides.of(big, small_df, on, right_on, null_safe)
    opts = {"smaller_keyset": opt_smaller_keyset, "partition_set": opt_partition_set}
    if how in ("left_semi", "left_anti"):
        keys = small(sides.known(sides.right).select(*sides.keys).distinct())
        out = sides.left.join(keys, sides.keys, how)
        return sides.present(out, only_left=True)
    if how == "right_semi":
        met = small(cut(joined_keys(sides, opt_partition_set)))
        return sides.present_right(sides.known(sides.right).join(met, sides.keys, "left_semi"))
    if how == "right_anti":
        return sides.present(sides.pad_left(right_anti_rows(sides, **opts)).unionByName(sides.pad_left(sides.unknown(sides.right))))
    return sides.present(sides.with_nulls(index_broadcast_pairs(sides, how, mode, opt_single_scan, variant, **opts), how))


def index_broadcast_pairs(sides: Sides, how: str, mode: str = "native", single_scan: bool = False, variant: str = "whole", checked: bool = False, **opts) -> DataFrame:
    """``checked``: the right side has been measured and fits."""
    joined = None
    if variant == "semi_reduced":
        joined = cut(joined_keys(sides))
        kept = sides.right.join(small(joined), sides.keys, "left_semi")
        reduced = sides.over(sides.left, kept)
        out = _probe(reduced, "left" if how in ("left", "full") else "inner", mode)
    elif single_scan and how in ("right", "full"):
        marked = sides.over(sides.left, sides.right.withColumn("__r_hit", F.lit(True)))
        both = cut(_probe(marked, "left" if how == "full" else "inner", mode))
        joined = both.filter("__r_hit").select(*sides.keys).distinct()
        out = both.drop("__r_hit")
    else:
        out = _probe(sides, "left" if how in ("left", "full") else "inner", mode, checked)
    if how in ("right", "full"):
        out = out.unionByName(sides.pad_left(right_anti_rows(sides, joined=joined, checked=checked, **opts)))
    return out


def chunked_broadcast_join(big: DataFrame, small_df: DataFrame, on, pieces: int, how: str = "inner", *, right_on=None) -> DataFrame:
    """A small side over the broadcast limit goes in pieces by key hash; each meets the large rows of its keys."""
    sides = Sides.of(big, small_df, on, right_on)
    out = None
    for p in range(pieces):
        mine = F.pmod(F.xxhash64(*sides.keys), F.lit(pieces)) == p
        piece = sides.over(sides.known(sides.left).filter(mine), sides.known(sides.right).filter(mine))
        pairs = index_broadcast_pairs(piece, how)
        out = pairs if out is None else out.unionByName(pairs)
    return sides.present(sides.with_nulls(out, how))
