"""Mix sources to target weights, to the word.

Every source gets a target share of a budget by its weight, at most
`max_copies` times its own size; what a capped source leaves is shared out
again by weight.  A source takes all of its documents as often as its target
holds its size; the rest of the target is met by choosing documents:

* documents are counted by exact size, so a source is a histogram of sizes;
* sizes are drawn in proportion, then from the largest down, until at most
  `window` words are missing;
* a bounded-knapsack dynamic programme over the counts left, on bit sets,
  finds the largest sum that fits the missing words;
* of each size, the documents with the least seeded hashes are taken.

Only histograms are gathered, one source's at a time, and their length is
bounded by the number of different sizes.  Choosing by rank is split over
ranges of the hash, as many as leave about `rows_per_range` documents of the
most frequent source and size in each, so these need not meet in one task.

Defined results: a null text has size 0 and is taken for free, as its words
count nothing; rows with a null source form one source, the last; rows that
tie on hash and id are interchangeable; sources of size 0 have target 0; an
empty table gives no rows; columns named source_size, target or copies give
way, other names never clash.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import free_name, materialise

WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class MixConfig:
    """`weights` repeat over the sources in code-point order; `budget` is a share of all sizes."""

    weights: tuple[float, ...] = (3.0, 1.0, 2.0)
    budget: float = 1.5
    max_copies: int = 2
    window: int = 1 << 16
    rows_per_range: int = 20_000
    seed: int = 11


def word_count(column: str):
    return F.coalesce(F.regexp_count(F.col(column), F.lit(WORD)), F.lit(0)).cast("long")


def numbered(df: DataFrame, order: str, name: str) -> DataFrame:
    """`df` with its 0-based position in the order, without one task that sees all rows."""
    ranged = df.repartitionByRange(F.col(order)).sortWithinPartitions(order).withColumn("_at", F.monotonically_increasing_id())
    ranged = materialise(ranged, "numbered")
    part = F.shiftright("_at", 33)
    counts = ranged.groupBy(part.alias("_part")).agg(F.count("*").alias("_n"))  # a row a partition
    before = counts.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))
    row = F.col("_at") - F.shiftleft(F.col("_part"), 33)
    return ranged.withColumn("_part", part).join(before, "_part").withColumn(name, F.col("_before") + row).drop("_at", "_part", "_before")


def source_targets(sized: DataFrame, config: MixConfig = MixConfig()) -> DataFrame:
    """(source_key, source_size, weight, target) from rows with source_key and size."""
    sizes = sized.groupBy("source_key").agg(F.sum("size").alias("source_size"))
    indexed = numbered(sizes, "source_key", "_no")
    pattern = F.array(*[F.lit(float(w)) for w in config.weights])
    weight = F.element_at(pattern, (F.col("_no") % len(config.weights) + 1).cast("int"))
    sources = materialise(indexed.withColumn("weight", weight).drop("_no"), "sources")
    total = sources.agg(F.sum("source_size").alias("size"), F.sum("weight").alias("weight")).first()
    if not total.size:
        return sources.withColumn("target", F.lit(0.0))
    cap = F.col("source_size") * config.max_copies
    level, budget = None, config.budget * total.size
    share = budget / total.weight
    while share != level:
        level = share
        over = F.col("weight") * F.lit(level) > cap
        parts = sources.agg(F.sum(F.when(over, cap).otherwise(0)).alias("capped"), F.sum(F.when(over, 0.0).otherwise(F.col("weight"))).alias("open")).first()
        if not parts.open:
            break
        share = (budget - parts.capped) / parts.open
    return sources.withColumn("target", F.least(cap.cast("double"), F.col("weight") * F.lit(level)))


def choose_counts(sizes: np.ndarray, counts: np.ndarray, wanted: int, window: int) -> np.ndarray:
    """How many documents of each size to take so that their sizes sum to `wanted`, or as near below as is found."""
    taken = np.zeros(len(sizes), np.int64)
    total = int((sizes * counts).sum())
    if wanted <= 0 or not total:
        return taken
    if wanted >= total:
        return counts.copy()
    order = np.argsort(-sizes, kind="stable")
    missing = wanted
    if missing > window:
        # in proportion, in whole numbers; part of the window stays for the programme
        share = missing - window // 2
        taken = np.array([int(c) * share // total for c in counts], np.int64)
        missing -= int((taken * sizes).sum())
        for i in order:
            if missing <= window:
                break
            more = min(int(counts[i] - taken[i]), -(-(missing - window) // int(sizes[i])) if sizes[i] else 0)
            more = min(more, missing // int(sizes[i]) if sizes[i] else 0)
            taken[i] += more
            missing -= more * int(sizes[i])
    # bounded knapsack: reach[s] is set if some choice sums to s
    mask = (1 << (missing + 1)) - 1
    reach, steps = 1, []
    for i in order:
        size, left = int(sizes[i]), int(counts[i] - taken[i])
        if not 0 < size <= missing:
            continue
        left, lot = min(left, missing // size), 1
        while left > 0 and not reach >> missing & 1:
            lot = min(lot, left)
            steps.append((i, lot, reach))
            reach |= (reach << (size * lot)) & mask
            left -= lot
            lot *= 2
        if reach >> missing & 1:
            break
    at = reach.bit_length() - 1
    for i, lot, before in reversed(steps):
        if not before >> at & 1:
            taken[i] += lot
            at -= lot * int(sizes[i])
    return taken


def _solver(window: int):
    def solve(table: pa.Table) -> pa.Table:
        sizes, counts = table.column("size").to_numpy(), table.column("n").to_numpy()
        source_size, target = int(table.column("source_size")[0].as_py()), float(table.column("target")[0].as_py())
        whole = int(target // source_size) if source_size else 0
        rest = round(target - whole * source_size)
        order = np.argsort(sizes, kind="stable")
        chosen = np.zeros(len(sizes), np.int64)
        chosen[order] = choose_counts(sizes[order], counts[order], rest, window)
        return pa.table({"source_key": table.column("source_key"), "size": table.column("size"), "whole": pa.array([whole] * len(sizes), pa.int64()), "chosen": pa.array(chosen)})

    return solve


def source_key(column: str):
    """A string that orders as the sources do, nulls last."""
    return F.when(F.col(column).isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col(column)))


def mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", size_col: str = "size", config: MixConfig = MixConfig()) -> DataFrame:
    """`docs` with source_size, target and copies, how often the mix takes the row.

    Columns of `docs` with one of these names give way.
    """
    made = ("source_size", "target", "copies")
    docs = docs.select([c for c in docs.columns if c not in made])
    slim = docs.select(source_key(source_col).alias("source_key"), F.col(size_col).alias("size"), F.col(id_col).alias("id"))
    targets = materialise(source_targets(slim.select("source_key", "size"), config), "targets")
    kinds = materialise(slim.groupBy("source_key", "size").agg(F.count("*").alias("n")), "kinds")
    most = kinds.agg(F.max("n")).first()[0] or 1
    bits = max(1, (-(-most // config.rows_per_range) - 1).bit_length())
    in_range = lambda id_: F.shiftrightunsigned(F.xxhash64(F.lit(config.seed), F.col(id_)), 64 - bits)
    ranges = materialise(slim.groupBy("source_key", "size", in_range("id").alias("range")).agg(F.count("*").alias("n")), "ranges")
    plan = kinds.join(targets, "source_key").groupBy("source_key").applyInArrow(_solver(config.window), "source_key string, size long, whole long, chosen long")
    by_size = Window.partitionBy("source_key", "size").orderBy("range")
    before = ranges.withColumn("before", F.sum("n").over(by_size) - F.col("n"))
    quota = before.join(plan, ["source_key", "size"]).join(targets.select("source_key", "source_size", "target"), "source_key")
    key, size, at, hashed, whole, left = (free_name(docs, f"mix_{x}") for x in ("key", "size", "range", "hash", "whole", "quota"))
    quota = quota.select("source_key", "size", "range", "whole", F.col("chosen") - F.col("before"), "source_size", "target").toDF(key, size, at, whole, left, "source_size", "target")
    quota = materialise(quota, "quota")
    rows = docs.select("*", source_key(source_col).alias(key), F.col(size_col).alias(size), F.xxhash64(F.lit(config.seed), F.col(id_col)).alias(hashed), in_range(id_col).alias(at))
    rows = rows.join(quota, [key, size, at])
    rank = F.row_number().over(Window.partitionBy(key, size, at).orderBy(hashed, id_col))
    return rows.withColumn("copies", F.col(whole) + (rank <= F.col(left)).cast("long")).select(*docs.columns, *made)


def emit_mixture(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", config: MixConfig = MixConfig()) -> DataFrame:
    """The rows of `docs` as often as the mix takes them."""
    columns, words, copy = docs.columns, free_name(docs, "mix_words"), free_name(docs, "mix_copy")
    # the table's own columns travel as one, so that none gives way to the mix's
    whole = docs.select(F.struct(*columns).alias("row"), F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(text_col).alias(words))
    mixed = mix(whole, "id", "source", words, config)
    return mixed.where("copies > 0").withColumn(copy, F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select("row.*")
