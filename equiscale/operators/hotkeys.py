"""Hot keys of a relation: at most ``k_max`` keys of at least ``theta`` rows, with their frequencies."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from equiscale.sources.io import cut

from .keys import field, free, names, no_nulls

METHODS = ("exact", "prepartitioned", "space_saving", "sketch", "freq_items", "sample")


class SpaceSaving:
    """Bounded counters: the item of the smallest count gives its place, and its count as error, to a new item."""

    def __init__(self, capacity: int):
        self.capacity, self.count, self.error, self.heap = capacity, {}, {}, []

    def add(self, item, n: int = 1, error: int = 0) -> None:
        if item in self.count:
            self.count[item] += n
            self.error[item] += error
            return
        if len(self.count) < self.capacity:
            self.count[item], self.error[item] = n, error
            heapq.heappush(self.heap, (n, item))
            return
        while True:  # heap entries are lower bounds, made true when they come up
            low, old = self.heap[0]
            now = self.count.get(old)
            if now is None:
                heapq.heappop(self.heap)
            elif now != low:
                heapq.heapreplace(self.heap, (now, old))
            else:
                break
        heapq.heapreplace(self.heap, (low + n, item))
        del self.count[old], self.error[old]
        self.count[item], self.error[item] = low + n, low + error

    def items(self):
        return sorted(((k, c, self.error[k]) for k, c in self.count.items()), key=lambda x: (-x[1], str(x[0])))

    @staticmethod
    def merge(parts: list[list[tuple]], capacity: int) -> list[tuple]:
        """Sums of counts and errors; a full summary that lacks an item may have hidden up to its smallest count of it."""
        floor = [min((c for _, c, _ in p), default=0) if len(p) >= capacity else 0 for p in parts]
        total: dict = {}
        for i, p in enumerate(parts):
            for k, c, e in p:
                t = total.setdefault(k, [0, 0, set()])
                t[0] += c
                t[1] += e
                t[2].add(i)
        out = []
        for k, (c, e, seen) in total.items():
            hidden = sum(f for i, f in enumerate(floor) if i not in seen)
            out.append((k, c + hidden, e + hidden))
        return sorted(out, key=lambda x: (-x[1], str(x[0])))[:capacity]


def _exact(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.groupBy(*keys).agg(F.count("*").alias("__f"))


#: Keys that are chosen by sorting, at most.
SORTED = 10_000


def _bounded(counts: DataFrame, keys: list[str], theta: float, k_max: int) -> DataFrame:
    """Up to SORTED keys, the most frequent ones, ties by key.  For a larger ``k_max`` all, if they are no more, else all
    above a frequency: a sixteenth of an octave is taken whole or not at all, so that no task sorts what all tasks have."""
    hot = counts.filter(F.col("__f") >= theta)
    if k_max <= SORTED:
        return hot.orderBy(F.desc("__f"), *keys).limit(k_max)
    hot = cut(hot)
    step = F.floor(16 * F.log2(F.col("__f"))).cast("int")
    sizes = sorted(((r[0], r[1]) for r in hot.groupBy(step.alias("s")).count().collect()), reverse=True)
    total, last = 0, None
    for s, n in sizes:
        total += n
        if total > k_max:
            break
        last = s
    if total <= k_max:
        return hot
    return hot.filter(step >= last) if last is not None else hot.orderBy(F.desc("__f"), *keys).limit(SORTED)


def _space_saving(df: DataFrame, keys: list[str], capacity: int, fanout: int) -> DataFrame:
    """Summaries of partitions of key hashes, merged in rounds of ``fanout``; (h, count, error)."""
    hashed = df.select(F.xxhash64(*keys).alias("__h"))

    def local(batches):
        import os

        import pyarrow as pa
        from pyspark import TaskContext

        sketch = SpaceSaving(capacity)
        for batch in batches:
            pairs = batch.column(0).value_counts()
            for k, n in zip(pairs.field(0).to_pylist(), pairs.field(1).to_pylist()):
                sketch.add(k, n)
        rows = sketch.items()
        pid = TaskContext.get().partitionId() if TaskContext.get() else os.getpid()
        yield pa.RecordBatch.from_arrays([pa.array([pid] * len(rows), pa.int64()), *[pa.array([r[i] for r in rows], pa.int64()) for i in range(3)]], ["pid", "h", "c", "e"])

    parts = hashed.mapInArrow(local, "pid long, h long, c long, e long")
    n = max(1, hashed.rdd.getNumPartitions())
    while True:

        def join(key, pdf):
            import pandas as pd

            rows = [list(g[["h", "c", "e"]].itertuples(index=False, name=None)) for _, g in pdf.groupby("pid")]
            out = pd.DataFrame(SpaceSaving.merge(rows, capacity), columns=["h", "c", "e"])
            out.insert(0, "pid", key[0])
            return out

        parts = parts.groupBy(F.floor(F.col("pid") / fanout).cast("long").alias("g")).applyInPandas(join, "pid long, h long, c long, e long")
        n = -(-n // fanout)
        if n <= 1:
            return parts.select("h", F.col("c"), F.col("e"))


def _candidates(df: DataFrame, keys: list[str], method: str, k_max: int, capacity: int, fanout: int) -> DataFrame:
    """(__h, __c): at most ``capacity`` candidate key hashes with the count that the summary gives, null if it gives none."""
    if method == "space_saving":
        return _space_saving(df, keys, capacity, fanout).select(F.col("h").alias("__h"), F.col("c").alias("__c"))
    hashed = df.select(F.xxhash64(*keys).alias("__h"))
    if method == "sketch":
        k = min(capacity, max(k_max, capacity // 2))  # more than asked for, so that ties are broken by key
        top = hashed.agg(F.expr(f"approx_top_k(__h, {k}, {capacity})").alias("t"))
        return top.select(F.explode("t").alias("x")).select("x.item", F.col("x.count").cast("long")).toDF("__h", "__c")
    if method == "freq_items":
        return hashed.freqItems(["__h"], 1.0 / capacity).select(F.explode("__h_freqItems").alias("__h"), F.lit(None).cast("long").alias("__c"))
    raise ValueError(f"method must be one of {METHODS}")


def hot_keys(df: DataFrame, on, k_max: int = 1000, theta: float = 24.4, method: str = "exact", *, capacity: int = 4096, fanout: int = 16, share: float = 0.1, refine: bool = True, exact: bool = False) -> DataFrame:
    """The keys and ``f`` (``f_`` if a key is called so).  Null keys are never hot.

    ``prepartitioned`` input has all rows of a key in one partition (the count then needs no exchange).  Sketches
    summarise key hashes; ``refine`` counts their candidates exactly, so that every key returned has its true count.  Without it
    the keys of the candidates get the summary's counts: too high by its error, or scaled up from a sample.  With ``exact``
    they are taken only if the summary has a counter for every key, so that it never dropped one; else all keys are counted.
    """
    shown = names(on)
    keys = [f"__h{i}" for i in range(len(shown))]
    known = df.select(*[field(df, n).alias(k) for n, k in zip(shown, keys)]).filter(no_nulls(keys))
    if exact and not refine and method in ("space_saving", "sketch") and known.select(F.xxhash64(*keys)).distinct().count() > capacity:
        method = "exact"
    if method in ("exact", "prepartitioned"):
        found = _bounded(_exact(known, keys), keys, theta, k_max)
    elif method == "sample":
        part = _exact(known.sample(share, seed=5), keys).withColumn("__f", F.round(F.col("__f") / share).cast("long"))
        found = _bounded(part, keys, theta, k_max)
        if refine:
            found = _bounded(_exact(known.join(F.broadcast(found.drop("__f")), keys, "left_semi"), keys), keys, theta, k_max)
    else:
        if method == "freq_items" and not refine:
            raise ValueError("freq_items gives no counts: it needs refine")
        cand = F.broadcast(_candidates(known, keys, method, k_max, capacity, fanout).groupBy("__h").agg(F.max("__c").alias("__c")))
        met = known.withColumn("__h", F.xxhash64(*keys)).join(cand, "__h")
        found = _bounded(met.groupBy(*keys).agg((F.count("*") if refine else F.max("__c")).alias("__f")), keys, theta, k_max)
    return found.toDF(*shown, free("f", shown))


def hot_summary(df: DataFrame, on, *, capacity: int = 4096, fanout: int = 16) -> DataFrame:
    """(h, c, e): key hashes with counts and error bounds of the merged bounded summaries."""
    keys = [f"__h{i}" for i in range(len(names(on)))]
    return _space_saving(df.select(*[field(df, n).alias(k) for n, k in zip(names(on), keys)]), keys, capacity, fanout)


def histogram_keys(df: DataFrame, on: str, eps: float = 0.01, accuracy: int | None = None) -> DataFrame:
    """Keys that fill at least one whole step of an eps-quantile histogram: coarser than a heavy-hitter summary of like space."""
    steps = round(1 / eps)
    marks = df.agg(F.percentile_approx(field(df, on), [i / steps for i in range(1, steps)], accuracy or int(4 / eps)).alias("q")).select(F.explode("q").alias("__h"))
    return marks.groupBy("__h").agg(F.count("*").alias("__n")).filter("__n > 1").toDF(on, free("steps", [on]))


def shared_hot(left_hot: DataFrame, right_hot: DataFrame, keys: list[str]) -> DataFrame:
    """Keys hot on both sides, with both frequencies."""
    return left_hot.withColumnRenamed("f", "fl").join(right_hot.withColumnRenamed("f", "fr"), keys)


def partition_variance(df: DataFrame, on) -> DataFrame:
    """Variance over partitions of each key's rows, and the rows ``f``: high where a key's rows sit together."""
    shown = names(on)
    keys = [f"__h{i}" for i in range(len(shown))]
    n = max(1, df.rdd.getNumPartitions())
    per = df.select(*[field(df, x).alias(k) for x, k in zip(shown, keys)]).groupBy(F.spark_partition_id().alias("__p"), *keys).agg(F.count("*").alias("__c"))
    mean = F.sum("__c") / n
    got = per.groupBy(*keys).agg((F.sum(F.col("__c") * F.col("__c")) / n - mean * mean).alias("__v"), F.sum("__c").alias("__f"))
    return got.toDF(*shown, free("variance", shown), free("f", shown))
