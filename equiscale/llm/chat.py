"""Perspective rotation of dialogues: each participant in turn is the assistant.

For every conversation and every participant (any speaker but the narrators,
``system`` by default) the dialogue is rendered with that participant as the
assistant and all others as named users.  The mask lists the spans (code
points, start:end) of the participant's own words with their end mark: only these are trained on.

Conversations of any length are bounded by ``segment``: turns are cut into
segments by turn number, one row for each segment and perspective.  No turn is left out: the parts of a
perspective, joined in order of ``part``, are the rendering of the whole dialogue, and each mask counts from the start of its part.

Defined results: null text is empty, null role is the role ``unknown``, null turns come
first in a part of their own (-1), null conv_id is one conversation of its own; exactly repeated rows
count once; turns with equal numbers are ordered by role and text; conversations of narrators alone give no row; texts of any length are
rendered whole; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"


def _pieces(perspective: Column, narrators: tuple[str, ...]):
    def piece(t: Column) -> Column:
        own = t["role"] == perspective
        head = F.when(own, F.lit(f"{OPEN}assistant\n")).when(t["role"].isin(*narrators), F.concat(F.lit(OPEN), t["role"], F.lit("\n"))).otherwise(F.concat(F.lit(f"{OPEN}user name="), t["role"], F.lit("\n")))
        return F.struct(F.concat(head, t["text"], F.lit(CLOSE)).alias("s"), F.length(head).alias("h"), own.alias("own"))

    return piece


def rotate_perspectives(turns: DataFrame, *, narrators: tuple[str, ...] = ("system",), segment: int = 256) -> DataFrame:
    """conv_id, part, perspective, n_turns, n_own, rendered, mask."""
    clean = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    parts = clean.groupBy("conv_id", F.coalesce(F.floor(F.col("turn") / segment), F.lit(-1)).cast("long").alias("part")).agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    speakers = clean.filter(~F.col("role").isin(*narrators)).select(F.col("conv_id").alias("c"), F.col("role").alias("perspective")).distinct()
    rows = parts.join(speakers, F.col("conv_id").eqNullSafe(F.col("c"))).withColumn("p", F.transform("turns", _pieces(F.col("perspective"), narrators)))
    starts = F.aggregate("p", F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("spans")), lambda acc, x: F.struct((acc["at"] + F.length(x["s"])).alias("at"), F.when(x["own"], F.concat(acc["spans"], F.array(F.concat((acc["at"] + x["h"]).cast("string"), F.lit(":"), (acc["at"] + F.length(x["s"])).cast("string"))))).otherwise(acc["spans"]).alias("spans")))
    return rows.select("conv_id", "part", "perspective", F.size("turns").cast("long").alias("n_turns"), F.size(F.filter("p", lambda x: x["own"])).cast("long").alias("n_own"), F.array_join(F.transform("p", lambda x: x["s"]), "").alias("rendered"), F.array_join(starts["spans"], ",").alias("mask"))


ORACLE_SQL = """
WITH clean AS (SELECT DISTINCT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text FROM conversations),
speakers AS (SELECT DISTINCT conv_id, role AS perspective FROM clean WHERE role <> 'system'),
pieces AS (
  SELECT c.conv_id, coalesce(floor(c.turn / 256.0)::BIGINT, -1) AS part, s.perspective, c.turn, c.role, c.text, c.role = s.perspective AS own,
    CASE WHEN c.role = s.perspective THEN '<|im_start|>assistant' || chr(10)
         WHEN c.role = 'system' THEN '<|im_start|>system' || chr(10)
         ELSE '<|im_start|>user name=' || c.role || chr(10) END AS head
  FROM clean c JOIN speakers s ON c.conv_id IS NOT DISTINCT FROM s.conv_id),
placed AS (
  SELECT *, head || text || '<|im_end|>' || chr(10) AS s,
    sum(length(head || text) + 11) OVER (PARTITION BY conv_id, part, perspective ORDER BY turn NULLS FIRST, role, text) AS ends FROM pieces)
SELECT conv_id, part, perspective, count(*)::BIGINT AS n_turns, (count(*) FILTER (WHERE own))::BIGINT AS n_own,
  string_agg(s, '' ORDER BY turn NULLS FIRST, role, text) AS rendered,
  coalesce(string_agg((ends - length(s) + length(head))::BIGINT || ':' || ends::BIGINT, ',' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE own), '') AS mask
FROM placed GROUP BY conv_id, part, perspective
"""
