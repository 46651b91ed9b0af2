"""Triangles by their base edge, the one opposite the lowest vertex.

The base edges are taken in batches of what memory holds.  Each batch is sent
to every task and the edges are read once for it.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import MemoryModel
from ..tables import with_position

#: A batch is broadcast only up to this many edges; larger ones are joined by key.
BROADCAST_EDGES = 4_000_000
#: Batches that are scanned each in a plan of its own.
SCANS = 16


def base_batches(bases: DataFrame, mm: MemoryModel, alpha: float = 0.5) -> tuple[DataFrame, int]:
    """Base edges (mid, top) with their batch, and the size of a batch in edges."""
    size = max(1, int(alpha * mm.m))
    placed = with_position(bases.select(F.col("lo").alias("mid"), F.col("hi").alias("top")), "mid", "top")
    return placed.withColumn("batch", F.floor(F.col("position") / size)).drop("position"), size


def _close(edges: DataFrame, batch: DataFrame, small: bool, tip_filter: Column | None) -> DataFrame:
    """Triangles over the base edges of `batch`; `tip_filter` is over the column `a`."""
    batch = F.broadcast(batch) if small else batch
    low = edges.select(F.col("lo").alias("a"), F.col("hi").alias("mid"))
    high = edges.select(F.col("lo").alias("a"), F.col("hi").alias("top"))
    if tip_filter is not None:
        low, high = low.where(tip_filter), high.where(tip_filter)
    return low.join(batch, "mid").join(high, ["a", "top"]).select("a", F.col("mid").alias("b"), F.col("top").alias("c"))


def triangles_by_base(edges: DataFrame, bases: DataFrame, mm: MemoryModel, alpha: float = 0.5, mode: str = "scan", tip_filter: Column | None = None) -> DataFrame:
    """Triangles of `edges` (lo, hi) whose base lies in `bases` (lo, hi).

    `scan` reads the edges once a batch, in as many plans as there are
    batches; `keyed` has one plan in which edges are dealt to the batches that
    need them and the batch is part of both joins' keys.  Beyond `SCANS`
    batches a scan is done as `keyed`, so that the plan does not grow.
    """
    batches, size = base_batches(bases, mm, alpha)
    n = batches.agg(F.max("batch")).first()[0]
    if mode == "keyed" or (n or 0) >= SCANS:
        low = edges.select(F.col("lo").alias("a"), F.col("hi").alias("mid"))
        high = edges.select(F.col("lo").alias("a"), F.col("hi").alias("top"))
        if tip_filter is not None:
            low, high = low.where(tip_filter), high.where(tip_filter)
        low = low.join(batches.select("batch", "mid").distinct(), "mid")
        high = high.join(batches.select("batch", "top").distinct(), "top")
        wedges = low.join(batches, ["batch", "mid"])
        return wedges.join(high, ["batch", "a", "top"]).select("a", F.col("mid").alias("b"), F.col("top").alias("c"))
    if n is None:
        return edges.select(F.col("lo").alias("a"), F.col("hi").alias("b"), F.col("hi").alias("c")).where("false")
    small = size <= BROADCAST_EDGES
    parts = [_close(edges, batches.where(F.col("batch") == k).drop("batch"), small, tip_filter) for k in range(n + 1)]
    return reduce(DataFrame.unionByName, parts)
