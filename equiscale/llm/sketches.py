"""Threshold-scaled document sketches in DataFrame functions alone.

A sketch keeps every distinct hash of a five-word shingle that lies below a
fixed fraction (1 / ``scale``) of the hash range, so sketches of any two texts, however
unequal, can be merged (union), compared and checked for containment.

Defined results: null text is empty; words are split at blanks; a text of one to four words
is one shingle; a text without words has an empty sketch.  Two sketches of which one is empty
have likeness 1 if both are empty and the texts equal, else 0.  Ties of doc_id are ordered by text, so
rows that repeat an id follow each other; null ids come first; the next of a single row is itself; texts of any length are read whole;
an empty table gives no rows; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, texts

WORDS, SCALE = 5, 4


def sketch(text: Column, words: int = WORDS, scale: int = SCALE) -> Column:
    """Sorted array of the retained shingle hashes."""
    own = F.transform(F.filter(F.split(text, "\\s+"), lambda w: w != ""), lambda w: F.xxhash64(w))

    def shingles(w: Column) -> Column:
        some = F.transform(F.sequence(F.lit(1), F.size(w) - (words - 1)), lambda i: F.xxhash64(*[F.get(w, i + (k - 1)) for k in range(words)]))
        return F.when(F.size(w) >= words, some).when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))

    whole = F.transform(F.array(own), shingles)[0]  # the words are bound once
    return F.array_sort(F.array_distinct(whole if scale == 1 else F.filter(whole, lambda h: h < F.lit(-(2**63) + 2**64 // scale))))


def fingerprint(sk: Column) -> Column:
    return F.array_join(F.transform(sk, lambda h: F.lower(F.lpad(F.hex(h), 16, "0"))), "")


def _shared(a: Column, b: Column) -> Column:
    return F.size(F.array_intersect(a, b))


def likeness(a: Column, b: Column, equal: Column) -> Column:
    """Estimated Jaccard similarity."""
    both = F.size(a) + F.size(b)
    return F.when((F.size(a) == 0) | (F.size(b) == 0), F.when(equal, 1.0).otherwise(0.0)).otherwise(_shared(a, b) / (both - _shared(a, b)))


def containment(a: Column, b: Column) -> Column:
    """Estimated part of a's shingles that b has too; null for an empty sketch."""
    return F.when(F.size(a) > 0, _shared(a, b) / F.size(a))


def merge(df: DataFrame, by: list[str], col: str) -> DataFrame:
    """Sketch of the union of each group's texts: hashes are made distinct before they meet."""
    return df.select(*by, F.explode(col).alias("h")).distinct().groupBy(*by).agg(F.array_sort(F.collect_list("h")).alias(col))


CELLS = 65536


def _ranges(rows: DataFrame, rows_per_range: int) -> DataFrame:
    """Adds ``__b``, a range number that ascends with doc_id; ranges are cut at about equal counts, whatever the ids are like.

    A cell is an interval of ids.  Cells of more than twice the wanted rows are cut into equal parts of the ids that they
    really hold, until none is left or each holds one id.  At most about CELLS ranges and some times as many cells are known to the driver.
    """
    spark = rows.sparkSession
    end = rows.agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.count("*").alias("n")).first()
    wanted = max(rows_per_range, -(-end["n"] // CELLS))
    out, used, heavy = rows.withColumn("__c", F.lit(0).cast("long")), 1, [(0, end["lo"] or 0, end["hi"] or 0, end["n"])]
    seen = []
    while heavy:
        cuts = []
        for cell, lo, hi, n in heavy:
            parts = min(CELLS, 4 * -(-n // wanted) + 1)
            cuts.append((cell, Decimal(lo), Decimal((hi - lo) // parts + 1), used))
            used += parts + 1  # the first part takes null ids
        table = F.broadcast(spark.createDataFrame(cuts, "__k long, __lo decimal(20,0), __w decimal(20,0), __base long"))
        part = F.coalesce(F.floor((F.col("doc_id").cast("decimal(20,0)") - F.col("__lo")) / F.col("__w")).cast("long") + 1, F.lit(0))
        out = out.join(table, F.col("__c") == F.col("__k"), "left").withColumn("__c", F.coalesce(F.col("__base") + part, F.col("__c"))).drop("__k", "__lo", "__w", "__base")
        seen = out.groupBy("__c").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.count("*").alias("n")).collect()
        heavy = [(r["__c"], r["lo"], r["hi"], r["n"]) for r in seen if r["lo"] is not None and r["n"] > 2 * wanted and r["hi"] > r["lo"]]
    before, numbered = 0, []
    for r in sorted(seen, key=lambda r: (r["lo"] is not None, r["lo"])):
        numbered.append((r["__c"], before // wanted))
        before += r["n"]
    table = F.broadcast(spark.createDataFrame(numbered, "__k long, __b long"))
    return out.join(table, F.col("__c") == F.col("__k")).drop("__c", "__k")


def with_next(docs: DataFrame, rows_per_range: int = 1000) -> DataFrame:
    """doc_id, text and the text of the next document by ascending doc_id (after the last: the first).

    Texts shuffle once, by range of doc_id; the first text of each range is passed to the range before it.
    """
    rows = _ranges(texts(docs), rows_per_range)
    dealt = rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "__b")
    paired = dealt.withColumn("__next", F.lead("text").over(Window.partitionBy("__b").orderBy(F.col("doc_id").asc_nulls_first(), F.col("text"))))
    head = rows.groupBy("__b").agg(F.min(F.coalesce("doc_id", F.lit(-(2**63)))).alias("d"))
    ring = head.select("__b", "d", F.lag("__b").over(Window.orderBy("__b")).alias("__p"), F.max("__b").over(Window.partitionBy(F.lit(0))).alias("m")).select("__b", "d", F.coalesce("__p", "m").alias("__p"))
    firsts = rows.withColumnRenamed("__b", "__r").join(F.broadcast(ring), (F.col("__r") == F.col("__b")) & (F.coalesce("doc_id", F.lit(-(2**63))) == F.col("d")))
    firsts = cut(firsts.groupBy("__p").agg(F.min("text").alias("f")))
    return paired.join(firsts, F.col("__b") == F.col("__p"), "left").select("doc_id", "text", F.coalesce("__next", "f").alias("next_text"))


def fingerprints(docs: DataFrame, *, words: int = WORDS, scale: int = SCALE) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    n = F.length("text").cast("long")
    half = F.floor(F.length("text") / 2).cast("int")
    rows = with_next(docs).withColumn("edited", F.concat(F.expr("substring(text, 1, length(text) - cast(floor(length(text) / 2) as int))"), F.substring("next_text", F.lit(1), half)))
    rows = rows.select("doc_id", n.alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"), sketch(F.col("text"), words, scale).alias("s"), sketch(F.col("edited"), words, scale).alias("e"), sketch(F.col("next_text"), words, scale).alias("x"), (F.col("text") == F.col("edited")).alias("same_e"), (F.col("text") == F.col("next_text")).alias("same_x"))
    return rows.select("doc_id", "n_chars", "edited_sha256", fingerprint(F.col("s")).alias("fingerprint"), fingerprint(F.col("e")).alias("edited_fingerprint"), likeness(F.col("s"), F.col("e"), F.col("same_e")).alias("near_edited"), likeness(F.col("s"), F.col("x"), F.col("same_x")).alias("near_next"))
