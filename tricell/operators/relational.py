"""Cyclic three-table joins: tables in fifth normal form and their decompositions."""

from __future__ import annotations

from collections.abc import Sequence
from math import isqrt

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.colours import PRIME
from ..model import MemoryModel, co_partitioned
from ..tables import stored

#: The three relations by the attributes that they hold.
_PAIRS = ((0, 1), (1, 2), (0, 2))


def decompose(table: DataFrame, on: Sequence[str]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The three binary projections of a table of three attributes."""
    return tuple(table.select(on[i], on[j]).distinct() for i, j in _PAIRS)


def _shade(value: Column, share: int, seed: int) -> Column:
    return F.pmod(F.pmod(F.xxhash64(F.lit(seed), value), F.lit(PRIME)), F.lit(share)).cast("long")


def three_way_join(r: DataFrame, s: DataFrame, t: DataFrame, on: Sequence[str], mm: MemoryModel | None = None, seed: int = 1, shares: tuple[int, int, int] | None = None, project: Sequence[str] | None = None, hashed: bool = False) -> DataFrame:
    """Natural join of R(x, y), S(y, z), T(x, z): the triangles of a tripartite graph.

    Attributes may be of any type.  Each attribute has its own number of
    colours; `shares` fixes them, otherwise all are what memory asks for.
    With `project`, duplicates go first inside each cell, then overall.
    With `hashed`, T's rows of a task are held as a hash table, so that the
    paths x - y - z are never sorted.
    """
    if shares is None:
        c = mm.colours(sum(x.count() for x in (r, s, t))) if mm else 1
        shares = (c, c, c)
    co_partitioned(r.sparkSession)
    x, y, z = on
    steps = (shares[1] * shares[2], shares[2], 1)

    def deal(df: DataFrame, pair: tuple[int, int]) -> DataFrame:
        free = ({0, 1, 2} - set(pair)).pop()
        fixed = sum((_shade(F.col(on[i]), shares[i], seed + i) * steps[i] for i in pair), F.lit(0).cast("long"))
        cells = F.transform(F.sequence(F.lit(0), F.lit(shares[free] - 1)), lambda k: fixed + k * steps[free])
        dealt = df.select(F.explode(cells).alias("cell"), on[pair[0]], on[pair[1]])
        # twice as many partitions as cells, so that few hold two
        return dealt.repartition(2 * steps[0] * shares[0], "cell") if hashed else dealt.repartition("cell")

    closing = deal(t, _PAIRS[2]).hint("shuffle_hash") if hashed else deal(t, _PAIRS[2])
    joined = deal(r, _PAIRS[0]).join(deal(s, _PAIRS[1]), ["cell", y]).join(closing, ["cell", x, z])
    if project is None:
        return joined.select(x, y, z)
    return joined.select("cell", *project).dropDuplicates(["cell", *project]).select(*project).distinct()


#: rows of T that a task may hold as a hash table
HASHED_ROWS = 1_000_000


def shares_for(spark: SparkSession, rows: int) -> tuple[int, int, int]:
    """Shares whose cells keep every core at work and hold few enough of T's rows; T itself is sent once."""
    k = isqrt(max(2 * spark.sparkContext.defaultParallelism, -(-rows // HASHED_ROWS)) - 1) + 1
    return k, 1, k


def is_join_of_projections(table: DataFrame, on: Sequence[str], mm: MemoryModel | None = None) -> DataFrame:
    """One row: distinct rows of the table, rows of the rejoined projections, and how many of these are spurious."""
    rows = stored(table.select(*on).distinct(), "rows")
    shares = None if mm else shares_for(rows.sparkSession, rows.count())
    again = three_way_join(*decompose(rows, on), on, mm, shares=shares, hashed=not mm)
    counts = rows.agg(F.count("*").alias("true_rows")).crossJoin(again.agg(F.count("*").alias("joined_rows")))
    return counts.select("true_rows", "joined_rows", (F.col("joined_rows") - F.col("true_rows")).alias("spurious_rows"))


def best_shares(sizes: tuple[int, int, int], cells: int) -> tuple[int, int, int]:
    """Shares of at most `cells` cells in all that send the fewest rows for relations of these sizes."""
    best = (sum(sizes) * cells, (1, 1, 1))
    for a in range(1, cells + 1):
        for b in range(1, cells // a + 1):
            c = cells // (a * b)
            shares = (a, b, c)
            moved = sizes[0] * c + sizes[1] * a + sizes[2] * b
            best = min(best, (moved * 1.0 / (a * b * c) ** 0.5, shares))
    return best[1]
