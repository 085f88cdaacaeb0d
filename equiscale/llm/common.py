"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import inspect

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from equiscale.sources.io import cut, release, shared_dir  # noqa: F401

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def trim() -> None:
    """Gives this worker's freed memory back to the system.  Spark reuses workers, which else keep the peak of every stage."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    give_back = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give_back is not None:
        give_back(0)


def lean(run):
    """A function over Arrow batches or over one group, with ``trim`` when its task or its group ends."""
    if inspect.isgeneratorfunction(run):

        def held(*args):
            yield from run(*args)
            trim()

    else:

        def held(*args):
            out = run(*args)
            trim()
            return out

    held.__signature__ = inspect.signature(run)  # Spark counts the arguments
    return held


def texts(docs: DataFrame) -> DataFrame:
    """Only (doc_id, text), null texts as empty: other columns can never clash."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def ascii_lower(col: Column) -> Column:
    """A-Z to a-z, every other code point untouched."""
    return F.translate(col, UPPER, UPPER.lower())


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_chunks(batch, limit: int = 2_000_000, id_col: str = "doc_id", text_col: str = "text"):
    """Slices of an Arrow batch of at most ``limit`` bytes of text (one longer text is a slice of its own)."""
    import numpy as np
    import pyarrow.compute as pc

    n = batch.num_rows
    if not n:
        return
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text_col))), 0)).astype(np.int64)
    ends = np.cumsum(sizes)
    at = 0
    while at < n:
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + limit, side="right")))
        yield batch.slice(at, to - at)
        at = to


def fold(col: Column, k: int) -> Column:
    """crc32 of the id as text, modulo ``k``."""
    return F.pmod(F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary")), F.lit(k))
