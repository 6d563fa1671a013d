"""Choices above Catalyst: how large pieces should be, and whether to split at all."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import degrees

#: Bytes of a link in a piece's adjacency, and the share of a task's memory that a piece may take.
LINK_BYTES, SHARE = 200, 0.25


def recommend_size_limit(edges: DataFrame, memory_bytes: int, cores: int) -> int:
    """The largest piece that one task's share of memory holds, yet no fewer pieces than cores where the graph allows."""
    r = degrees(edges).agg(F.count("*").alias("n"), F.avg("degree").alias("d")).first()
    if not r["n"]:
        return 1
    fits = int(SHARE * memory_bytes / (LINK_BYTES * max(1.0, r["d"])))
    return max(1, min(fits, -(-r["n"] // max(1, cores))))


def choose_executor(edges: DataFrame, memory_bytes: int, replication: float | None = None) -> str:
    """serial for graphs that one task holds, flat where pieces would copy too much, else split."""
    m = edges.count()
    if m * LINK_BYTES <= SHARE * memory_bytes:
        return "serial"
    return "flat" if replication is not None and replication > 2 else "split"
