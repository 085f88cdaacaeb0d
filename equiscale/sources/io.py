"""Scans and sinks."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def read(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_format(spark: SparkSession, fmt: str, path: str, schema, **options) -> DataFrame:
    return spark.read.schema(schema).options(**options).format(fmt).load(path)


def write(df: DataFrame, path: str | None, fmt: str = "parquet", mode: str = "errorifexists", **options) -> None:
    out = df.write.mode(mode).options(**options).format(fmt)
    out.save() if fmt == "noop" else out.save(path)


def write_bucketed(df: DataFrame, table: str, on: list[str], n: int) -> None:
    df.write.bucketBy(n, *on).sortBy(*on).mode("overwrite").saveAsTable(table)


def read_bucketed(spark: SparkSession, table: str) -> DataFrame:
    return spark.table(table)


def write_split(df: DataFrame, path: str, column: str = "route") -> None:
    """One folder for each route; a read of one route prunes the others."""
    df.write.partitionBy(column).parquet(path)


def literal(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def shared_dir(spark: SparkSession) -> str:
    """A folder of this application below ``spark.checkpoint.dir``, which all executors share; it goes when the driver ends.

    Unset, a session with one machine's threads (tests) gets a temporary folder; on a cluster that is an error, as
    executors would write where neither the driver nor other executors can read.
    """
    top = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if not top:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        top = _LOCAL.setdefault(context.applicationId, "file://" + tempfile.mkdtemp(prefix="equiscale-"))
    folder = f"{top.rstrip('/')}/equiscale-{context.applicationId}"
    if folder not in _FOLDERS:
        _FOLDERS.add(folder)
        atexit.register(_remove, context._jvm, context._jsc.hadoopConfiguration(), folder)
    return folder


_LOCAL: dict[str, str] = {}
_FOLDERS: set[str] = set()


def _remove(jvm, conf, path: str) -> None:
    with contextlib.suppress(Exception):  # the driver's JVM may have ended already
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)


def cut(df: DataFrame) -> DataFrame:
    """Writes and reads again: lineage ends, and the size is known to the planner."""
    path = f"{shared_dir(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut = path
    _CUTS.append(path)
    return out


_CUTS: list[str] = []


def made() -> int:
    """How many tables ``cut`` has written so far; see ``sweep``."""
    return len(_CUTS)


def sweep(spark: SparkSession, since: int, keep: DataFrame) -> None:
    """Deletes what ``cut`` has written since ``made()`` was ``since``, but ``keep``: for work whose result is written and whose parts nobody else has."""
    context, kept = spark.sparkContext, getattr(keep, "_cut", None)
    for path in _CUTS[since:]:
        if path != kept:
            _remove(context._jvm, context._jsc.hadoopConfiguration(), path)
    _CUTS[since:] = [kept] if kept in _CUTS[since:] else []


def release(*cuts: DataFrame) -> None:
    """Deletes what ``cut`` has written, once nothing will read it any more."""
    for df in cuts:
        path = getattr(df, "_cut", None)
        if path is not None:
            context = df.sparkSession.sparkContext
            _remove(context._jvm, context._jsc.hadoopConfiguration(), path)
