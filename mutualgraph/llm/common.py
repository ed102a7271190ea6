"""What the corpus operators share: words, and the package's storage and join helpers."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..storage import drop_stored, join_small, new_path, shared_dir, ship, store

#: Words are maximal runs of anything but the six ASCII white-space bytes.
WORD = r"[^\x20\x09-\x0D]+"


def partitions_for(spark: SparkSession, units: float, per_partition: float, least: int = 1) -> int:
    """Partitions so that none holds more than about `per_partition` units."""
    return max(least, int(-(-units // per_partition)))


__all__ = ["WORD", "drop_stored", "join_small", "new_path", "partitions_for", "shared_dir", "ship", "store"]
