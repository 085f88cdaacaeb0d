"""Settings of the joins."""

from __future__ import annotations

from dataclasses import dataclass, replace

from .cost import hot_threshold, max_hot_keys


@dataclass(frozen=True)
class JoinConfig:
    lam: float = 7.4125
    hot_threshold: float | None = None
    hot_predicate: object = None  # callable (rows left, rows right) -> Column; replaces the geometric mean test of the list form
    k_max_left: int | None = None  # hot keys that are kept, at most; None: what fits in memory beside the rows they stand for
    k_max_right: int | None = None
    hot_method: str = "exact"
    capacity: int = 4096
    fanout: int = 16
    refine: bool = True
    n_executors: int | None = None  # None: the session's parallelism
    executor_memory: float | None = None  # bytes; None: the session's setting
    key_bytes: float = 8
    left_bytes: float | None = None  # of a row; None: measured
    right_bytes: float | None = None
    partitions_per_executor: int | None = None  # exchanges of levels get this many partitions an executor (3 to 5 are usual); None: the session's setting
    index: str = "cells"
    levels: str = "planned"  # of cells; planned: from the hot keys' frequencies, in one exchange; counted: each level is written and counted
    loop: str = "static"
    max_levels: int = 12
    cell_share: float = 0.125  # a cell is not cut further below this part of a task's fair share of all pairs; 0: until the threshold
    chunk_rule: str = "even"
    chunk_exponent: str = "equal"
    seed: int = 17
    split: str = "hot"  # rows that are written once, by class: those of hot keys, or all
    broadcast: str = "model"
    broadcast_limit: float = 512e6
    kappa_trusted: bool = True
    null_safe: bool = False
    include_identity: bool = True
    max_copies: int = 10_000

    def executors(self, spark) -> int:
        return self.n_executors or spark.sparkContext.defaultParallelism

    def partitions(self, spark) -> int:
        """Partitions of an exchange."""
        if self.partitions_per_executor:
            return self.partitions_per_executor * self.executors(spark)
        return int(spark.conf.get("spark.sql.shuffle.partitions"))

    def memory(self, spark) -> float:
        """Bytes of an executor's memory."""
        return self.executor_memory or size_of(spark.conf.get("spark.executor.memory", "1g"))

    def hot_budget(self, spark, other_row_bytes: float) -> int:
        """Hot keys for which the other side's cold rows and the keys themselves fit in an executor's memory."""
        return max(1, max_hot_keys(float("inf"), self.memory(spark), other_row_bytes, self.key_bytes, self.lam))

    @property
    def theta(self) -> float:
        return hot_threshold(self.lam) if self.hot_threshold is None else self.hot_threshold

    def but(self, **changes) -> JoinConfig:
        return replace(self, **changes)

    @classmethod
    def published_practice(cls, **changes) -> JoinConfig:
        """The thousand most frequent keys of at least a hundred rows."""
        return cls(hot_threshold=100, k_max_left=1000, k_max_right=1000, **changes)


def size_of(text: str) -> float:
    """Bytes of a setting such as 8g or 512m; a bare number is in MB."""
    text = text.strip().lower().removesuffix("b")
    unit = {"k": 2**10, "m": 2**20, "g": 2**30, "t": 2**40}.get(text[-1])
    return float(text[:-1]) * unit if unit else float(text) * 2**20
