"""Sub-lists of a key's rows as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def sublist_count(n: Column, other: Column | None = None, exponent: str = "equal") -> Column:
    """Number of sub-lists of a list of ``n`` rows: the cube root, or for ``general`` the power of the unequal-list model."""
    if exponent == "general" and other is not None:
        low, high = F.least(n, other).cast("double"), F.greatest(n, other).cast("double")
        x = F.log(high) / F.log(low)
        p = F.when(low > 1, (1 + x) / (1 + 2 * x)).otherwise(F.lit(2 / 3))
        return F.greatest(F.lit(1), F.ceil(F.round(F.pow(n.cast("double"), 1 - p), 9)).cast("int"))
    return F.greatest(F.lit(1), F.ceil(F.cbrt(n.cast("double"))).cast("int"))


def sublist_length(n: Column, rule: str = "even") -> Column:
    """Rows of a sub-list; always fewer than ``n`` for ``n`` over 1."""
    if rule == "power":
        return F.greatest(F.lit(1), F.least(F.ceil(F.round(F.pow(n.cast("double"), 2 / 3), 9)), n - 1)).cast("int")
    parts = sublist_count(n)
    return F.greatest(F.lit(1), F.ceil(n / parts)).cast("int")


def chunk(rows: Column, rule: str = "even") -> Column:
    """An array cut into contiguous sub-arrays; null for an empty one."""
    n = F.size(rows)
    length = sublist_length(n, rule)
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(n / length).cast("int") - 1)), lambda i: F.slice(rows, i * length + 1, length)))


def grid_lane(columns: list[str], parts: Column, seed: int) -> Column:
    """A row's lane in ``parts`` lanes: a function of its content alone, so a task run again gives it again."""
    return F.pmod(F.xxhash64(F.lit(seed), *columns), parts).cast("int")
