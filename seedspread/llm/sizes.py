"""Broadcast hints that stand behind a count of what is broadcast."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.runtime import materialize

#: Rows of a few longs each, or items of lists, up to which a table is broadcast (about 50 MB).
MAX_BROADCAST = 2_000_000


def few(df: DataFrame, limit: int = MAX_BROADCAST) -> DataFrame:
    """``df`` written out, with a broadcast hint if it has at most ``limit`` rows; beyond that the join shuffles."""
    held = materialize(df, "few")
    return F.broadcast(held) if held.count() <= limit else held


def small(df: DataFrame, lists: str, limit: int = MAX_BROADCAST) -> DataFrame:
    """The same for rows that hold a list column: its items count too."""
    held = materialize(df, "small")
    items = held.agg(F.count("*") + F.coalesce(F.sum(F.size(lists)), F.lit(0))).first()[0]
    return F.broadcast(held) if items <= limit else held
