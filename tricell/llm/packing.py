"""Variable-capacity best-fit packing.

Documents are packed into sequences of several permitted lengths.  A document
longer than the longest length is cut; its full pieces are sequences of their
own.  What remains goes, largest first, to the open sequence with the least
room that still holds it.  If none does, a sequence is opened: for each
permitted length, the items still to come are tried from the largest down, and
the length that costs least for each word it would then carry is opened.  At
the end each sequence shrinks to the shortest permitted length that holds it.

Documents are dealt by hash to groups of about `group_rows`, each packed by one
task in memory that the group's size bounds; a group wastes at most a few
sequences.  Equal rows travel as one row with a count, at most `group_rows` of
them; no column of the table but id and size is read, so none can clash.

Defined results: a document without words has one row without a sequence; a
null id is an id like any other; repeated rows are packed each; ties go to the
least id, then the least piece; an empty table gives no rows.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .mixing import word_count
from .storage import materialise


@dataclass(frozen=True)
class PackConfig:
    """`overhead`: what a sequence costs beside its length."""

    lengths: tuple[int, ...] = (512, 1024, 2048, 4096)
    overhead: int = 16
    group_rows: int = 20_000


class _Coming:
    """The sizes still to be packed, as counts and a bit set."""

    def __init__(self, sizes: Iterable[int]):
        self.count: dict[int, int] = defaultdict(int)
        for s in sizes:
            self.count[s] += 1
        self.bits = 0
        for s in self.count:
            self.bits |= 1 << s

    def take(self, size: int) -> None:
        self.count[size] -= 1
        if not self.count[size]:
            self.bits &= ~(1 << size)

    def fill(self, room: int) -> int:
        """What the items would fill of `room`, from the largest down."""
        filled, limit = 0, room
        while limit > 0:
            limit = (self.bits & ((1 << (limit + 1)) - 1)).bit_length() - 1
            if limit <= 0:
                break
            n = min(self.count[limit], (room - filled) // limit)
            filled += n * limit
            limit = min(limit - 1, room - filled)
        return filled


def least_length(used: int, config: PackConfig) -> int:
    return min(c for c in config.lengths if c >= used)


def pack_sizes(sizes: list[int], config: PackConfig = PackConfig()) -> list[tuple[int, int]]:
    """(sequence, offset) for each of `sizes`, which come in descending order and fit the longest length."""
    coming = _Coming(sizes)
    by_room: dict[int, list[int]] = defaultdict(list)
    rooms = 0
    used: list[int] = []
    out = []
    for size in sizes:
        coming.take(size)
        above = rooms >> size
        if above:
            room = size + (above & -above).bit_length() - 1
            bin_ = by_room[room].pop()
            if not by_room[room]:
                rooms &= ~(1 << room)
        else:
            best = None
            for c in config.lengths:
                if c < size:
                    continue
                carried = size + coming.fill(c - size)
                rate = (least_length(carried, config) + config.overhead) / carried
                if best is None or rate < best[0]:
                    best = (rate, c)
            room, bin_ = best[1], len(used)
            used.append(0)
        out.append((bin_, used[bin_]))
        used[bin_] += size
        if room > size:
            by_room[room - size].append(bin_)
            rooms |= 1 << (room - size)
    return out


def _packer(config: PackConfig):
    longest = max(config.lengths)

    def pack(table: pa.Table) -> pa.Table:
        group = table.column("_group")[0].as_py()
        items, rows, next_bin = [], [], 0
        for id_, size, copies, first in zip(*[table.column(c).to_pylist() for c in ("id", "size", "copies", "first")], strict=True):
            for copy in range(first, first + copies):
                if not size:
                    rows.append((id_, copy, 0, 0, 0, None, None, None, None))
                for piece in range(-(-size // longest)):
                    length = min(longest, size - piece * longest)
                    if length == longest:
                        rows.append((id_, copy, piece, piece * longest, length, group << 32 | next_bin, 0, longest, longest))
                        next_bin += 1
                    else:
                        items.append((-length, id_ is not None, id_ or 0, piece, copy, id_))
        items.sort(key=lambda x: x[:5])
        placed = pack_sizes([-x[0] for x in items], config)
        used: dict[int, int] = defaultdict(int)
        for (bin_, _), x in zip(placed, items, strict=True):
            used[bin_] -= x[0]
        for (bin_, offset), x in zip(placed, items, strict=True):
            rows.append((x[5], x[4], x[3], x[3] * longest, -x[0], group << 32 | (next_bin + bin_), offset, least_length(used[bin_], config), used[bin_]))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
        columns = list(zip(*rows, strict=True)) or [[]] * 9
        return pa.table([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=_NAMES)

    return pack


_NAMES = ["doc_id", "copy", "piece", "start", "length", "bin_id", "bin_offset", "capacity", "used"]


def pack(docs: DataFrame, id_col: str = "doc_id", size_col: str = "size", config: PackConfig = PackConfig()) -> DataFrame:
    """One row a piece: doc_id, copy, piece, start, length, bin_id, bin_offset, capacity, used."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(size_col), F.lit(0)).cast("long").alias("size"))
    rows = materialise(rows.groupBy("id", "size").agg(F.count("*").alias("copies")), "sizes")
    groups = max(1, -(-(rows.agg(F.sum("copies")).first()[0] or 0) // config.group_rows))
    # a row of many copies is dealt in lots
    lots = F.sequence(F.lit(0), F.floor((F.col("copies") - 1) / config.group_rows))
    rows = rows.withColumn("first", F.explode(lots)).withColumn("first", F.col("first") * config.group_rows)
    rows = rows.withColumn("copies", F.least(F.col("copies") - F.col("first"), F.lit(config.group_rows)))
    dealt = rows.withColumn("_group", F.pmod(F.xxhash64("id", "size", "first"), F.lit(groups)))
    return dealt.groupBy("_group").applyInArrow(_packer(config), ", ".join(f"{n} long" for n in _NAMES))


def pack_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", config: PackConfig = PackConfig()) -> DataFrame:
    """`pack` with sizes in words of the text."""
    return pack(docs.select(F.col(id_col).alias("doc_id"), word_count(text_col).alias("size")), config=config)
