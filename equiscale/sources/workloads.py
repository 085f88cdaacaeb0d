"""Skewed relations over the given tables.  The key expression is the same text in Spark and in standard SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .io import read

# fixed values: multipliers of the two sides' integer hash
MULTIPLIER = {"left": 2654435761, "right": 2246822519}


def _uniform(side: str, d: str) -> str:
    return f"((((o_orderkey + 1) * {MULTIPLIER[side]}) % 4294967296) + 0.5{d}) / 4294967296.0{d}"


def zipf_key(side: str, alpha: float, n_keys: int, spark_text: bool = True) -> str:
    """Inverse distribution function of a bounded power law on 0..n_keys-1."""
    d = "D" if spark_text else "::DOUBLE"
    u, top = _uniform(side, d), f"CAST({n_keys + 1} AS DOUBLE)"
    if alpha == 1:
        return f"CAST(floor(pow({top}, {u})) AS BIGINT) - 1"
    e = f"{1 - alpha}{d}"
    return f"CAST(floor(pow(1{d} + ({u}) * (pow({top}, {e}) - 1{d}), 1{d} / ({e}))) AS BIGINT) - 1"


def zipf(spark: SparkSession, sf_dir: str, side: str, alpha: float, *, n_keys: int | None = None, pay_bytes: int = 100, uniform_part: bool = False, key_scale: int = 1, share: float = 1.0) -> DataFrame:
    """key, id, pay.  ``key_scale`` multiplies keys (selectivity); ``uniform_part`` adds rows of nearly unique keys; ``share`` takes that part of the rows (weak scaling)."""
    orders = read(spark, sf_dir, "orders", ["o_orderkey"])
    n_keys = n_keys or max(1, orders.count() // 100)
    out = orders.select((F.expr(zipf_key(side, alpha, n_keys)) * key_scale).alias("key"), F.col("o_orderkey").alias("id"))
    if uniform_part:
        lines = read(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber"])
        n = lines.count()
        place = F.col("l_orderkey") * 8 + F.col("l_linenumber")
        key = F.lit(1_000_000_000).cast("long") + F.pmod(F.pmod((place + 1) * F.lit(MULTIPLIER[side]), F.lit(4294967296)), F.lit(2 * n + n // 7))
        out = out.unionByName(lines.select((key * key_scale).alias("key"), place.alias("id")))
    if share < 1:
        out = fraction(out, "id", share)
    return out.withColumn("pay", F.rpad(F.col("id").cast("string"), pay_bytes, "x"))


def zipf_sql(side: str, alpha: float, *, uniform_part: bool = False, share: float = 1.0) -> str:
    """The same rows in SQL (without payload)."""
    u = f"((((o_orderkey + 1) * {MULTIPLIER[side]}) % 4294967296) + 0.5::DOUBLE) / 4294967296.0::DOUBLE"
    top = "(SELECT CAST(greatest(1, count(*) // 100) + 1 AS DOUBLE) FROM orders)"
    if alpha == 1:
        key = f"CAST(floor(pow({top}, {u})) AS BIGINT) - 1"
    else:
        e = f"{1 - alpha}::DOUBLE"
        key = f"CAST(floor(pow(1::DOUBLE + ({u}) * (pow({top}, {e}) - 1::DOUBLE), 1::DOUBLE / ({e}))) AS BIGINT) - 1"
    rows = f"SELECT {key} AS key, o_orderkey AS id FROM orders"
    if uniform_part:
        place = "(l_orderkey * 8 + l_linenumber)"
        rows += f" UNION ALL SELECT 1000000000 + ((({place} + 1) * {MULTIPLIER[side]}) % 4294967296) % (SELECT 2 * count(*) + count(*) // 7 FROM lineitem) AS key, {place} AS id FROM lineitem"
    if share < 1:
        rows = f"SELECT * FROM ({rows}) WHERE {_share('id', share)}"
    return f"({rows})"


def _share(column: str, share: float) -> str:
    """Whether an integer hash of the column lies below ``share``, in either dialect."""
    return f"(({column} + 1) * 2654435761) % 4294967296 % 10000 < {int(10_000 * share)}"


def postings(spark: SparkSession, sf_dir: str, source: str | None = None) -> DataFrame:
    """Distinct (doc_id, token) of all documents, or of one source's."""
    docs = read(spark, sf_dir, "documents", ["doc_id", "source", "text"])
    docs = docs.filter(F.col("source") == source) if source else docs
    return docs.select("doc_id", F.explode(F.split("text", " ")).alias("token")).distinct()


def fraction(df: DataFrame, column: str, share: float) -> DataFrame:
    """The rows whose hash lies below ``share``: the weak-scaling sample."""
    return df.filter(_share(column, share))
