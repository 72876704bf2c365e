"""Semi joins that broadcast only what has been counted and found small."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most keys that may be broadcast (a few tens of MB); beyond it the join is shuffled.
BROADCAST_KEYS = 1_000_000


def keep_keys(df: DataFrame, keys: DataFrame, on: str, n_keys: int, limit: int = BROADCAST_KEYS) -> DataFrame:
    """Rows of ``df`` whose ``on`` is among ``keys`` (distinct; ``n_keys`` of them, counted before).

    Up to ``limit`` keys are broadcast so the wide side is filtered in its scan; more keys take a
    sort-merge semi join, which adaptive execution splits where a key is hot.
    """
    side = F.broadcast(keys.select(on)) if n_keys <= limit else keys.select(on).hint("merge")
    return df.join(side, on, "left_semi")


def drop_keys(df: DataFrame, keys: DataFrame, on: str, n_keys: int, limit: int = BROADCAST_KEYS) -> DataFrame:
    """Rows of ``df`` whose ``on`` is not among ``keys``; rows whose ``on`` is null stay."""
    side = F.broadcast(keys.select(on)) if n_keys <= limit else keys.select(on).hint("merge")
    return df.join(side, on, "left_anti")
