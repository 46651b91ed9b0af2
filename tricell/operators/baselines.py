"""The methods that the cell methods are compared with."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MemoryModel
from .base import triangles_by_base
from .cells import enumerate_cells
from .recursive import enumerate_recursive


def naive_triangles(edges: DataFrame) -> DataFrame:
    """Wedges at the lowest vertex, closed by an edge; the optimiser picks the joins."""
    mid = edges.select(F.col("lo").alias("a"), F.col("hi").alias("b"))
    top = edges.select(F.col("lo").alias("a"), F.col("hi").alias("c"))
    base = edges.select(F.col("lo").alias("b"), F.col("hi").alias("c"))
    return mid.join(base, "b").join(top, ["a", "c"]).select("a", "b", "c")


def sort_wedge_triangles(edges: DataFrame, strict: bool = False) -> DataFrame:
    """Wedges sorted by their open end and merged with the edges; `strict` allows no hash or broadcast join at all."""
    mid = edges.select(F.col("lo").alias("a"), F.col("hi").alias("b"))
    base = edges.select(F.col("lo").alias("b"), F.col("hi").alias("c"))
    top = edges.select(F.col("lo").alias("a"), F.col("hi").alias("c"))
    wedges = mid.join(base.hint("merge") if strict else base, "b")
    return wedges.join(top.hint("merge"), ["a", "c"]).select("a", "b", "c")


def base_scan_triangles(edges: DataFrame, mm: MemoryModel, alpha: float = 0.5) -> DataFrame:
    """Base-edge batches over all edges: one scan of the edges for each batch of what memory holds."""
    return triangles_by_base(edges, edges, mm, alpha)


#: edges of an inner block, and pieces that the outer edges are cut into at least
BLOCK_EDGES = 2_000_000
OUTER_PIECES = 12
#: paths that a task holds at once
PATHS_AT_ONCE = 1 << 20
_OUTER, _BASE, _TOP = 0, 1, 2


def _loop(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The triangles of a piece of the outer edges with a block of bases and one of tops, paths in bounded pieces."""
    table = pa.Table.from_batches(batches)
    role, lo, hi = (table.column(x).to_numpy() for x in ("role", "lo", "hi"))
    ids, flat = np.unique(np.concatenate([lo, hi]), return_inverse=True)
    n = np.int64(len(ids))
    lo, hi = flat[: len(lo)], flat[len(lo) :]
    bases, closing = np.sort(lo[role == _BASE] * n + hi[role == _BASE]), np.sort(lo[role == _TOP] * n + hi[role == _TOP])
    a, b = lo[role == _OUTER], hi[role == _OUTER]
    if not (len(a) and len(bases) and len(closing)):
        return
    starts, tops = np.searchsorted(bases, np.arange(n + 1) * n), bases % n
    fan = starts[b + 1] - starts[b]
    ends = np.cumsum(fan)
    at = 0
    while at < len(a):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + PATHS_AT_ONCE, "right")))
        f = fan[at:to]
        row = np.repeat(np.arange(at, to), f)
        c = tops[np.arange(f.sum()) - np.repeat(np.cumsum(f) - f, f) + np.repeat(starts[b[at:to]], f)]
        want = a[row] * n + c
        hit = closing[np.minimum(np.searchsorted(closing, want), len(closing) - 1)] == want
        row, c = row[hit], c[hit]
        yield pa.RecordBatch.from_arrays([pa.array(ids[v]) for v in (a[row], b[row], c)], list("abc"))
        at = to


def nested_loop_triangles(edges: DataFrame) -> DataFrame:
    """A pipelined nested-loop join, for edges that nearly fit in memory.

    Each piece of the outer edges meets each block of bases and each block of
    tops.  Inside, an edge's partners are looked up in the sorted block, so
    not every two edges are compared; paths are closed as they come.
    """
    n = edges.count()
    blocks = max(1, -(-n // BLOCK_EDGES))
    pieces = max(OUTER_PIECES, blocks)
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    own = lambda k: F.pmod(F.xxhash64("lo", "hi"), F.lit(k)).cast("int")
    numbers = {_OUTER: (own(pieces), every(blocks), every(blocks)), _BASE: (every(pieces), own(blocks), every(blocks)), _TOP: (every(pieces), every(blocks), own(blocks))}
    roles = []
    for role, loops in numbers.items():
        part = edges.select("lo", "hi", F.lit(role).alias("role"))
        for name, number in zip(("piece", "base", "top"), loops, strict=True):
            part = part.select("*", number.alias(name))
        roles.append(part)
    dealt = roles[0].unionByName(roles[1]).unionByName(roles[2])
    tasks = max(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 2 * pieces * blocks**2)
    return dealt.repartition(tasks, "piece", "base", "top").groupBy("piece", "base", "top").applyInArrow(_loop, "a long, b long, c long")


def recursive_plain(ranked: DataFrame, seed: int = 1) -> DataFrame:
    """Recursive recolouring that does not serve subproblems' own hubs."""
    return enumerate_recursive(ranked, seed, local_hub_step=False, depth=3)


def cells_no_hub_step(ranked: DataFrame, mm: MemoryModel, seed: int = 1) -> DataFrame:
    return enumerate_cells(ranked, mm, seed, hub_step=False)


def cells_plain_hash(ranked: DataFrame, mm: MemoryModel, seed: int = 1) -> DataFrame:
    return enumerate_cells(ranked, mm, seed, family="xxhash")


def brute_triangles(edges: DataFrame) -> DataFrame:
    """All triples of vertices, tested; for tiny graphs."""
    ids = edges.select(F.explode(F.array("lo", "hi")).alias("id")).distinct()
    a, b, c = ids.toDF("a"), ids.toDF("b"), ids.toDF("c")
    triples = a.crossJoin(b).crossJoin(c)
    for x, y in (("a", "b"), ("b", "c"), ("a", "c")):
        triples = triples.join(edges.toDF(x, y), [x, y], "left_semi")
    return triples.select("a", "b", "c")
