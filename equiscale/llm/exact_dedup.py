"""Exact deduplication behind two passes over a Bloom filter, in DataFrame functions alone.

The filter is blocked: a row's hash chooses one 64-bit block and two bits in it.  Pass 1 merges the blocks as bit maps
(or) and adds up how many bits their rows have set; each task sends a block at most once.  A block whose rows have set more
bits than its map holds has been hit twice in some place.  Only those blocks are kept, one number each.
Pass 2 probes each row: in any other block no second row can equal it and it passes straight through, unshuffled.
Only the rows left, thin (id and digest), shuffle by digest, are grouped with partial aggregation and get their group
back in a join that adaptive execution may split when one group is hot.  Texts never shuffle.
The number of blocks grows with the rows up to ``max_blocks``, so the table of blocks to probe is at most 8 * ``max_blocks`` bytes and
may be broadcast.  Beyond that more rows pass as possibly repeated and shuffle, thin; results stay the same.

Defined results: null text is empty; equal means identical after A-Z are
lower-cased; the largest doc_id stays (null ids rank below all others); rows that repeat one
doc_id and text count in group_size and are all marked as that document is; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut, release, texts


def hashed(docs: DataFrame) -> DataFrame:
    """Thin rows: doc_id, digest of the normalised text, hash."""
    norm = texts(docs).select("doc_id", ascii_lower(F.col("text")).alias("norm"))
    return norm.select("doc_id", F.sha2("norm", 256).alias("text_sha256"), F.xxhash64("norm").alias("h"))


MAX_BLOCKS = 1 << 24


def filter_blocks(n_rows: int, bits_per_row: int = 256, max_blocks: int = MAX_BLOCKS) -> int:
    """Number of 64-bit blocks: a power of two with at least ``bits_per_row`` bits a row, as far as ``max_blocks`` allows."""
    return min(max_blocks, 1 << max(4, math.ceil(math.log2(max(1, n_rows) * bits_per_row / 64))))


def _block(blocks: int) -> Column:
    return F.col("h").bitwiseAND(F.lit(blocks - 1))


def repeated_blocks(rows: DataFrame, blocks: int) -> DataFrame:
    """(block): blocks in which some bit was set by more than one row.  A row's two bits may be one; it then counts once."""
    mixed = F.xxhash64("h")
    bit = lambda shift: F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(mixed, shift).bitwiseAND(F.lit(63)).cast("int"))
    own = rows.select(_block(blocks).alias("block"), bit(58).bitwiseOR(bit(52)).alias("bits"))
    merged = own.groupBy("block").agg(F.bit_or("bits").alias("map"), F.sum(F.bit_count("bits")).alias("n"))
    return merged.filter(F.col("n") > F.bit_count("map")).select("block")


def probe(rows: DataFrame, repeated: DataFrame, blocks: int) -> DataFrame:
    """doc_id, text_sha256, maybe: whether another row may have the same text."""
    hit = F.broadcast(repeated.select(F.col("block").alias("__b"), F.lit(True).alias("__hit")))  # at most ``blocks`` numbers
    return rows.join(hit, _block(blocks) == F.col("__b"), "left").select("doc_id", "text_sha256", F.coalesce("__hit", F.lit(False)).alias("maybe"))


def exact_groups(docs: DataFrame, *, bits_per_row: int = 256, max_blocks: int = MAX_BLOCKS) -> DataFrame:
    """One row for each document: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = cut(hashed(docs))
    blocks = filter_blocks(rows.count(), bits_per_row, max_blocks)
    probed = cut(probe(rows, cut(repeated_blocks(rows, blocks)), blocks))
    release(rows)
    single = probed.filter("not maybe").select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "text_sha256")
    again = probed.filter("maybe").select("doc_id", "text_sha256")
    groups = cut(again.groupBy("text_sha256").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))).withColumnRenamed("text_sha256", "__s")
    joined = again.join(groups, F.col("text_sha256") == F.col("__s")).select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")
    return single.unionByName(joined)


def drop_exact(docs: DataFrame, **options) -> DataFrame:
    """All columns of the documents that stay; of rows that repeat one id and text all stay."""
    keep = docs.columns
    gone = exact_groups(docs, **options).filter("not kept").select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, docs["doc_id"].eqNullSafe(F.col("__gone")), "left_anti").select(*[docs[c] for c in keep])


ORACLE_SQL = """
WITH n AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, (count(*) OVER w)::BIGINT AS group_size,
  doc_id IS NOT DISTINCT FROM max(doc_id) OVER w AS kept, sha256(t) AS text_sha256
FROM n WINDOW w AS (PARTITION BY t)
"""
