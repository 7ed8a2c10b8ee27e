"""Choices that depend on sizes: the engine, sharing by broadcast, and how levels are kept."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a side up to which it is broadcast (about 100 MB of keys).
BROADCAST_ROWS = 1_000_000
#: Items of a root's sequences up to which one task mines it depth-first.
LOCAL_ROWS = 2_000_000


def small(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if its counted rows allow it; otherwise the join shuffles."""
    return F.broadcast(df) if rows <= limit else df


@dataclass(frozen=True)
class Plan:
    engine: str
    roots: int
    largest_root: int
    expected_rows: float


def estimate(items: DataFrame, minsup: int, maxgap: int | None, max_items: int) -> Plan:
    """Engine for mining items (sid, pos, item): local if every root fits a task, frontier if none does, hybrid between.

    The rows of level k are estimated from the exact mean of reachable items per row,
    which is the branching factor of the first step.
    """
    per_sid = items.groupBy("sid").agg(F.count("*").alias("n"), F.max("pos").alias("len"))
    total, sids, length = per_sid.agg(F.sum("n"), F.count("*"), F.avg("len")).first()
    if not total:
        return Plan("local", 0, 0, 0.0)
    roots = items.groupBy("item").agg(F.count_distinct("sid").alias("s")).where(F.col("s") >= minsup).agg(F.count("*"), F.max("s"), F.min("s")).first()
    mean = total / sids
    width = mean / max(length, 1)
    fan = width * (maxgap if maxgap is not None else length / 2)
    largest, least = (roots[1] or 0) * mean, (roots[2] or 0) * mean
    engine = "local" if largest <= LOCAL_ROWS else "frontier" if least > LOCAL_ROWS else "hybrid"
    return Plan(engine, roots[0], int(largest), float(total * fan ** (max_items - 1)))
