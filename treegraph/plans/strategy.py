"""Decisions that the optimizer can't take: what is small enough to broadcast, and which search to run."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes by the optimizer's own estimate up to which a side is broadcast; beyond it joins shuffle.
BROADCAST_BYTES = 256 << 20


def estimated_bytes(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def small(df: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if it is estimated to be small, else unchanged."""
    return F.broadcast(df) if estimated_bytes(df) <= limit else df


def choose_search(n_queries: int, n_nodes: int, dim: int) -> str:
    """exact while the products cost less than reading the nodes some hundred times, blocks while BLAS carries it, else approximate."""
    work = n_queries * n_nodes * dim
    return "exact" if work <= 2e9 else "blocks" if work <= 5e15 else "approximate"
