"""Cliques and other patterns of k vertices by the same colouring, and 4-cycles without it."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb, isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.colours import colour
from ..model import MemoryModel, co_partitioned


def _cell_list(low: Column, high: Column, i: int, j: int, k: int, c: int) -> Column:
    """The cells of c^k that an edge serves as the pair (i, j) of a k-clique, as an array."""
    rest = [n for n in range(k) if n not in (i, j)]
    fixed = (low - 1).cast("long") * c ** (k - 1 - i) + (high - 1).cast("long") * c ** (k - 1 - j)
    free = F.sequence(F.lit(0).cast("long"), F.lit(c ** len(rest) - 1).cast("long"))

    def cell(f: Column) -> Column:
        out = fixed
        for p, n in enumerate(reversed(rest)):
            out = out + F.floor(f / c**p).cast("long") % c * c ** (k - 1 - n)
        return out

    return F.transform(free, cell)


def _cells(low: Column, high: Column, i: int, j: int, k: int, c: int) -> Column:
    """One row for each cell of c^k that an edge serves as the pair (i, j) of a k-clique."""
    return F.explode(_cell_list(low, high, i, j, k, c))


#: edges of a cell that a task may hold
HELD_EDGES = 8_000_000
#: partial cliques that are grown at once
GROWN_AT_ONCE = 1 << 19
#: bytes of a table of all pairs of vertices, which is read faster than sorted edges are searched
PAIR_BYTES = 1 << 27


def held_colours(edges: int, k: int, c: int) -> int:
    """At least c colours, and so many that a cell, of k (k - 1) / 2 of the c^2 classes of edges, can be held by a task."""
    if edges <= HELD_EDGES:
        return c
    return max(c, isqrt(-(-comb(k, 2) * edges // HELD_EDGES) - 1) + 1)


def _grow(lo: np.ndarray, hi: np.ndarray, shade: np.ndarray, shades: list[int], part: int = 0, parts: int = 1) -> Iterator[list[np.ndarray]]:
    """Cliques whose vertices in rank order have the colours `shades`, in bounded pieces.

    Of the first vertices, those that are `part` modulo `parts` count.  Edges are pairs of 0..n-1, `shade` the colours of these.  A piece is grown
    to its end before the next one, so that what is held at once does not
    depend on how many cliques or partial ones there are.
    """
    n, k = len(shade), len(shades)
    keys = np.sort(lo * np.int64(n) + hi)
    keys = keys[np.append(True, keys[1:] != keys[:-1])] if len(keys) else keys
    lo, hi = keys // n, keys % n
    table = None
    if n * n <= PAIR_BYTES:
        table = np.zeros(n * n, bool)
        table[keys] = True

    def linked(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        want = x * np.int64(n) + y
        return table[want] if table is not None else keys[np.minimum(np.searchsorted(keys, want), len(keys) - 1)] == want

    def side(i: int) -> tuple[np.ndarray, np.ndarray]:
        # the edges between places i and i + 1, by their lower ends
        own = (shade[lo] == shades[i]) & (shade[hi] == shades[i + 1])
        return np.searchsorted(lo[own], np.arange(n + 1)), hi[own]

    sides = [side(i) for i in range(1, k - 1)]

    def onward(known: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
        if len(known) == k:
            yield known
            return
        starts, tops = sides[len(known) - 2]
        fan = starts[known[-1] + 1] - starts[known[-1]]
        ends = np.cumsum(fan)
        at = 0
        while at < len(fan):
            before = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, before + GROWN_AT_ONCE, "right")))
            f = fan[at:to]
            row = np.repeat(np.arange(at, to), f)
            new = tops[np.arange(f.sum()) - np.repeat(np.cumsum(f) - f, f) + np.repeat(starts[known[-1][at:to]], f)]
            for v in known[-2::-1]:
                hit = linked(v[row], new)
                row, new = row[hit], new[hit]
            if len(new):
                yield from onward([*(v[row] for v in known), new])
            at = to

    first = (shade[lo] == shades[0]) & (shade[hi] == shades[1]) & (lo % parts == part)
    yield from onward([lo[first], hi[first]])


def _cell_cliques(batches: Iterator[pa.RecordBatch], k: int, c: int, parts: int, names: list[str]) -> Iterator[pa.RecordBatch]:
    """The cliques of one cell, from its edges as lists (lo, k_lo, k_hi, tops)."""
    table = pa.Table.from_batches(batches)
    part, cell = divmod(table.column("cell")[0].as_py(), c**k)
    shades = [cell // c ** (k - 1 - i) % c + 1 for i in range(k)]
    tops = table.column("tops").combine_chunks()
    sizes = np.diff(tops.offsets.to_numpy())
    hi = tops.flatten().to_numpy()
    lo, k_lo, k_hi = (table.column(x).to_numpy() for x in ("lo", "k_lo", "k_hi"))
    ids = np.unique(np.concatenate([lo, hi]))
    shade = np.zeros(len(ids), np.int32)
    at_lo, at_hi = np.searchsorted(ids, lo), np.searchsorted(ids, hi)
    shade[at_lo] = k_lo
    shade[at_hi] = np.repeat(k_hi, sizes)
    at_lo = np.repeat(at_lo, sizes)
    del table, tops, hi, lo
    for found in _grow(at_lo, at_hi, shade, shades, part, parts):
        yield pa.RecordBatch.from_arrays([pa.array(ids[v]) for v in found], names)


def enumerate_cliques(edges: DataFrame, k: int, mm: MemoryModel | None = None, seed: int = 1, colours: int | None = None) -> DataFrame:
    """Every k-clique v0 < ... < v(k-1) in rank order once, each in the cell of its colours.

    A cell's edges meet in one task, which grows the cliques by one vertex at
    a time in memory: what is moved is edges, never a partial clique.  There
    are more colours than asked for where a cell would not fit otherwise.
    """
    n = edges.count()
    return _dealt_cliques(edges, k, held_colours(n, k, colours or (mm.colours(n) if mm else 1)), seed)


def _dealt_cliques(edges: DataFrame, k: int, c: int, seed: int, parts: int = 1) -> DataFrame:
    """The cliques of all cells; each of a cell's parts has all its edges, and grows cliques from its share of the first vertices."""
    names = [f"v{i}" for i in range(k)]
    painted = edges.select("lo", "hi", colour(F.col("lo"), c, seed).alias("k_lo"), colour(F.col("hi"), c, seed).alias("k_hi"))
    lists = painted.groupBy("lo", "k_lo", "k_hi").agg(F.collect_list("hi").alias("tops"))
    own = F.array_distinct(F.concat(*[_cell_list(F.col("k_lo"), F.col("k_hi"), i, j, k, c) for i, j in combinations(range(k), 2)]))
    spread = lists.select(F.explode(own).alias("cell"), "lo", "k_lo", "k_hi", "tops")
    if parts > 1:
        part = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long")))
        spread = spread.select(part.alias("part"), "*").withColumn("cell", F.col("part") * c**k + F.col("cell")).drop("part")
    tasks = max(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 2 * parts * c**k)

    # by these annotations Spark passes batches on as they are found
    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _cell_cliques(batches, k, c, parts, names)

    solve.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    return spread.repartition(tasks, "cell").groupBy("cell").applyInArrow(solve, ", ".join(f"{v} long" for v in names))


#: tasks that the growth of cliques is dealt to
GROWTH_PARTS = 12


def cliques_by_growth(edges: DataFrame, k: int) -> DataFrame:
    """Cliques grown from edges in memory: one cell as far as a task can hold the edges.

    The first vertices are dealt to parts that each have all edges, so no wedge
    or partial clique is moved.
    """
    return _dealt_cliques(edges, k, held_colours(edges.count(), k, 1), 1, GROWTH_PARTS)


def four_cycles(edges: DataFrame) -> DataFrame:
    """(a, b, c, d): each 4-cycle a-b-c-d once; a is its least id and b < d."""
    both = edges.unionByName(edges.select(F.col("hi").alias("lo"), F.col("lo").alias("hi")))
    corner = both.toDF("a", "b").where("a < b").join(both.toDF("b", "c"), "b").where("a < c")
    other = corner.select("a", F.col("b").alias("d"), "c")
    return corner.join(other, ["a", "c"]).where("b < d").select("a", "b", "c", "d")


#: 4-cycles 0-1-2-3, each once: 0 is its least id and 1 < 3.
FOUR_CYCLE = (((0, 1), (0, 3), (1, 2), (2, 3)), ((0, 1), (0, 2), (0, 3), (1, 3)))
#: Two triangles on the edge 0-1, with or without the edge 2-3, each once.
DIAMOND = (((0, 1), (0, 2), (1, 2), (0, 3), (1, 3)), ((0, 1), (2, 3)))


def enumerate_pattern(edges: DataFrame, pattern: tuple, mm: MemoryModel | None = None, seed: int = 1, colours: int | None = None) -> DataFrame:
    """Every occurrence v0, ..., v(k-1) of a connected pattern, each in the cell of its colours.

    A pattern has its edges, each of which but the first touches one before
    it, and the pairs (i, j) with v(i) < v(j) that leave one of the
    occurrences that are alike.  Vertices are distinct.  An edge is dealt both
    ways, as a pattern's vertices have no rank order; inside a cell the joins
    are on the cell and the known vertices, as for cliques.
    """
    sides, order = pattern
    k = 1 + max(max(s) for s in sides)
    c = colours or (mm.colours(edges.count()) if mm else 1)
    co_partitioned(edges.sparkSession)
    names = [f"v{i}" for i in range(k)]
    both = edges.select("lo", "hi").unionByName(edges.select(F.col("hi").alias("lo"), F.col("lo").alias("hi")))

    def dealt(i: int, j: int) -> DataFrame:
        cell = _cells(colour(F.col("lo"), c, seed), colour(F.col("hi"), c, seed), i, j, k, c)
        kept = both.where("lo < hi") if (i, j) in order else both.where("lo > hi") if (j, i) in order else both
        return kept.select(cell.alias("cell"), F.col("lo").alias(names[i]), F.col("hi").alias(names[j])).repartition("cell")

    grown, known = dealt(*sides[0]), set(sides[0])
    for i, j in sides[1:]:
        new = {i, j} - known
        grown = grown.join(dealt(i, j), ["cell", *[names[v] for v in (i, j) if v in known]])
        for v in new:
            for w in known - {i, j} if len(new) == 1 else ():
                less = (v, w) in order, (w, v) in order
                x, y = F.col(names[v]), F.col(names[w])
                grown = grown.where(x < y if less[0] else y < x if less[1] else x != y)
        known |= new
    return grown.select(*names)
