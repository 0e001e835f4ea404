"""Choices between physical plans that need a look at sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A side above this many bytes is never broadcast.
BROADCAST_BYTES = 64 << 20


def broadcast_if_small(side: DataFrame, size_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Marks a side for broadcast only if its known size is within the limit; else the join shuffles."""
    return F.broadcast(side) if size_bytes <= limit else side


def combine_plan(stream: DataFrame, distinct_share: float | None = None) -> str:
    """'direct' for streams known to have nearly unique keys, else 'two_step', which holds for any skew.

    distinct_share is approx_count_distinct(key) / count(*) where the caller knows it.
    """
    return "direct" if distinct_share is not None and distinct_share > 0.9 else "two_step"


def distinct_share(stream: DataFrame) -> float:
    row = stream.agg(F.approx_count_distinct("item_key").alias("d"), F.count("*").alias("n")).first()
    return row["d"] / max(1, row["n"])


def choose_plan(size_bytes: int, limit: int = BROADCAST_BYTES) -> str:
    """How an estimate meets its pages: 'broadcast' under the limit, else 'page_join'."""
    return "broadcast" if size_bytes <= limit else "page_join"
