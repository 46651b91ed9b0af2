"""Cells of consecutive ids that hold about equal weight, however the ids cluster."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import free_name

#: cells that the whole span of ids is cut in at first, and each heavy cell after that, as powers of two
_FIRST, _NEXT = 12, 4


def id_cells(sizes: DataFrame, limit: int, id_col: str = "id", weight_col: str = "weight") -> tuple[Callable[[DataFrame, str, str], DataFrame], int]:
    """Cuts ids where running sums of exact weights reach `limit`; returns (deal, cells).

    `deal(df, id_col, name)` adds to each row the number of its cell, 0 to
    cells - 1 in id order; each cell holds some row.  A cell is heavier than
    `limit` only if one id is.  Ids are counted by their leading bits; a group
    of more than `limit` is counted again by more of them, so what comes to
    the driver is about 16 numbers for each `limit` of weight.  Null ids go to
    the first cell.
    """
    bounds = sizes.agg(F.min(id_col).alias("lo"), F.max(id_col).alias("hi")).first()
    if bounds.lo is None:
        return lambda df, id_col, name: df.withColumn(name, F.lit(0).cast("long")), 1
    shift = 0
    while (bounds.hi >> shift) - (bounds.lo >> shift) >= 1 << _FIRST:
        shift += 1
    level = sizes.where(F.col(id_col).isNotNull())
    leaves: list[tuple[int, int, int, int]] = []  # least id, shift, leading bits, weight
    levels = []
    while True:
        levels.append(shift)
        found = level.groupBy(F.shiftright(id_col, shift).alias("head")).agg(F.sum(weight_col).alias("n")).collect()
        heavy = [(r.head,) for r in found if r.n > limit and shift]
        again = {head for (head,) in heavy}
        leaves += [(r.head << shift, shift, r.head, int(r.n or 0)) for r in found if r.head not in again]
        if not heavy:
            break
        kept = sizes.sparkSession.createDataFrame(heavy, "kept_head long")
        level = level.join(kept, F.shiftright(id_col, shift) == F.col("kept_head"), "left_semi")
        shift = max(0, shift - _NEXT)
    cell, filled, plan = -1, limit + 1, []
    for _, bits, head, n in sorted(leaves):
        if filled + n > limit:
            cell, filled = cell + 1, 0
        filled += n
        plan.append((bits, head, cell))
    table = sizes.sparkSession.createDataFrame(plan, "bits int, head long, cell long")

    def deal(df: DataFrame, id_col: str, name: str) -> DataFrame:
        columns, cells = df.columns, []
        for bits in levels:
            head, found = free_name(df, f"head_{bits}"), free_name(df, f"cell_{bits}")
            own = table.where(F.col("bits") == bits).select(F.col("head").alias(head), F.col("cell").alias(found))
            df = df.join(own, F.shiftright(id_col, bits) == F.col(head), "left")
            cells.append(F.col(found))
        return df.select(*columns, F.coalesce(*cells, F.lit(0).cast("long")).alias(name))

    return deal, cell + 1
