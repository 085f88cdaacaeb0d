"""Two relations in a common form: keys ``__k0..``, left columns ``__l_0..``, right columns ``__r_0..``.

Flat columns (no structs) keep column pruning down to the scans; numbered names cannot clash with the caller's.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

HOWS = {"inner", "left", "right", "full", "left_semi", "left_anti", "right_semi", "right_anti"}


class TooLargeToBroadcast(ValueError):
    """A method that can only broadcast a side was given one that does not fit."""


def field(df: DataFrame, name: str) -> Column:
    """The column of that very name, dots and quotes included."""
    return df["`" + name.replace("`", "``") + "`"]


def free(name: str, taken) -> str:
    """``name``, with underscores added until it is not taken."""
    while name in taken:
        name += "_"
    return name


def names(on) -> list[str]:
    return [on] if isinstance(on, str) else list(on)


def no_nulls(columns: list[str]) -> Column:
    out = F.lit(True)
    for c in columns:
        out = out & F.col(c).isNotNull()
    return out


def common_type(left: DataFrame, right: DataFrame, a: str, b: str) -> str | None:
    """The type to which Spark casts both keys to compare them; None if they have one type."""
    types = left.schema[a].dataType, right.schema[b].dataType
    for t in types:
        if isinstance(t, T.MapType) or "interval" in t.simpleString():
            raise TypeError(f"a key of type {t.simpleString()} has no equality that can be hashed")
    if types[0] == types[1]:
        return None
    both = left.select(field(left, a).alias("a")).crossJoin(right.select(field(right, b).alias("b")))
    equality = both.select((F.col("a") == F.col("b")).alias("e"))._jdf.queryExecution().analyzed().expressions().head().child()
    return equality.left().dataType().sql()


@dataclass
class Sides:
    left: DataFrame
    right: DataFrame
    keys: list[str]
    names: list[str]
    null_safe: bool
    left_names: list[str]
    right_names: list[str]
    weighted: bool = False  # columns are numbers that add up, so rows that lie together may be merged; see totals.py

    @classmethod
    def of(cls, left: DataFrame, right: DataFrame, on, right_on=None, null_safe: bool = False, weighted: bool = False) -> Sides:
        lon, ron = names(on), names(on if right_on is None else right_on)
        if len(lon) != len(ron):
            raise ValueError("both sides need the same number of key columns")
        keys = [f"__k{i}" for i in range(len(lon))]
        types = [common_type(left, right, a, b) for a, b in zip(lon, ron)]
        sides, rest = [], []
        for df, own, mark in ((left, lon, "__l_"), (right, ron, "__r_")):
            cols = []
            for key, to, c in zip(keys, types, own):
                k = field(df, c).cast(to) if to else field(df, c)
                if isinstance(df.schema[c].dataType, (T.FloatType, T.DoubleType)):
                    k = k + F.lit(0.0)  # one zero
                cols.append((F.struct(k.alias("v")) if null_safe else k).alias(key))
            rest.append([c for c in df.columns if c not in own])
            sides.append(df.select(*cols, *[field(df, c).alias(f"{mark}{i}") for i, c in enumerate(rest[-1])]))
        return cls(*sides, keys, lon, null_safe, *rest, weighted)

    def over(self, left: DataFrame, right: DataFrame) -> Sides:
        """The same form over other rows."""
        return replace(self, left=left, right=right)

    def merged(self, df: DataFrame, by: list[str]) -> DataFrame:
        """Rows of a weighted side that agree in ``by``, which has the keys, added up; plain rows as they are."""
        if not self.weighted:
            return df
        return df.groupBy(*by).agg(*[F.sum(c).alias(c) for c in df.columns if c.startswith(("__l_", "__r_"))])

    @property
    def lcols(self) -> list[str]:
        return [c for c in self.left.columns if c.startswith("__l_")]

    @property
    def rcols(self) -> list[str]:
        return [c for c in self.right.columns if c.startswith("__r_")]

    def known(self, df: DataFrame) -> DataFrame:
        """Rows without a null key: null matches nothing and never enters a shuffle."""
        return df if self.null_safe else df.filter(no_nulls(self.keys))

    def unknown(self, df: DataFrame) -> DataFrame:
        return df.limit(0) if self.null_safe else df.filter(~no_nulls(self.keys))

    def all_known(self) -> Sides:
        return self.over(self.known(self.left), self.known(self.right))

    def pad_right(self, df: DataFrame) -> DataFrame:
        """Left rows with nulls for the right columns."""
        return df.select(*self.keys, *self.lcols, *[F.lit(None).cast(self.right.schema[c].dataType).alias(c) for c in self.rcols])

    def pad_left(self, df: DataFrame) -> DataFrame:
        return df.select(*self.keys, *[F.lit(None).cast(self.left.schema[c].dataType).alias(c) for c in self.lcols], *self.rcols)

    def order(self, df: DataFrame) -> DataFrame:
        return df.select(*self.keys, *self.lcols, *self.rcols)

    def with_nulls(self, pairs: DataFrame, how: str) -> DataFrame:
        """Adds the preserved rows of null keys."""
        out = pairs
        if not self.null_safe:
            if how in ("left", "full"):
                out = out.unionByName(self.pad_right(self.unknown(self.left)))
            if how in ("right", "full"):
                out = out.unionByName(self.pad_left(self.unknown(self.right)))
        return out

    def _key_columns(self) -> list[Column]:
        return [(F.col(k)["v"] if self.null_safe else F.col(k)).alias(n) for k, n in zip(self.keys, self.names)]

    def present(self, pairs: DataFrame, only_left: bool = False) -> DataFrame:
        """Keys once, left columns, right columns; a right column whose name is taken gets ``_r`` until it is free."""
        taken = [*self.names, *self.left_names]
        out = [*self._key_columns(), *[F.col(f"__l_{i}").alias(n) for i, n in enumerate(self.left_names)]]
        for i, n in enumerate(() if only_left else self.right_names):
            while n in taken:
                n += "_r"
            taken.append(n)
            out.append(F.col(f"__r_{i}").alias(n))
        return pairs.select(*out)

    def present_right(self, rows: DataFrame) -> DataFrame:
        """Keys and right columns."""
        return rows.select(*self._key_columns(), *[F.col(f"__r_{i}").alias(free(n, self.names)) for i, n in enumerate(self.right_names)])


def check_how(how: str) -> None:
    if how not in HOWS:
        raise ValueError(f"how must be one of {sorted(HOWS)}")
