"""Choices made when a plan is built, each visible in ``explain``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Planned bytes, and counted rows, of a metadata side (a row per block, draw or server) that may be broadcast.
MOST_BROADCAST_BYTES, MOST_BROADCAST_ROWS = 8 << 20, 500_000


def small(side: DataFrame, most: int = MOST_BROADCAST_ROWS) -> DataFrame:
    """Broadcast a side that is known to be small; beyond that the join shuffles, and adaptive execution splits hot keys.

    The planner's own size decides where it is low enough (lists from the
    driver, stored tables); else rows are counted, up to the bound.
    """
    planned = int(str(side._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(side) if planned <= MOST_BROADCAST_BYTES or side.limit(most + 1).count() <= most else side


def choose_mode(n: int, d: int, k: int, iterations: int, rows_per_iteration: int, driver_bytes: int = 1 << 30) -> str:
    """'stats' when one scan for Gram matrices costs less than the iterations and K d^2 numbers fit, else 'rows'."""
    scan, steps = n * d * d, iterations * rows_per_iteration * d
    return "stats" if scan < steps and 4 * k * d * d <= driver_bytes else "rows"
