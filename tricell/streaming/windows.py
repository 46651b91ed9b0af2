"""Windows over edge events, alike for streams and tables."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tumbling(events: DataFrame, ts: str, length: str, key: str) -> DataFrame:
    """(start, key, n)."""
    return events.groupBy(F.window(ts, length).alias("w"), key).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), key, "n")


def sliding(events: DataFrame, ts: str, length: str, step: str) -> DataFrame:
    """(start, n)."""
    return events.groupBy(F.window(ts, length, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, ts: str, gap: str, key: str) -> DataFrame:
    """(key, start, end, n)."""
    return events.groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def watermarked(events: DataFrame, ts: str, late: str, keys: list[str]) -> DataFrame:
    """Events without repeats; rows later than the watermark are dropped (streams only)."""
    return events.withWatermark(ts, late).dropDuplicatesWithinWatermark(keys)


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], ts: str, seconds: int, late: str | None = None) -> DataFrame:
    """Pairs of rows with equal keys at most so many seconds apart; columns but the keys get the prefixes left_ and right_.

    For streams give `late`: both sides then carry a watermark, so that the
    state that the join holds ends `seconds` and `late` after a row.  A row
    meets those of its own bucket of so many seconds and of the buckets beside
    it alone, not all that have its keys.
    """

    def named(df: DataFrame, side: str, bucket: Callable[[Column], Column]) -> DataFrame:
        at = F.col(ts)
        clock = F.unix_date(at.cast("date")).cast("long") * 86400 + F.hour(at) * 3600 + F.minute(at) * 60 + F.floor(F.second(at))
        whole = F.unix_seconds(at) if df.schema[ts].dataType.typeName() == "timestamp" else clock
        kept = df.withWatermark(ts, late) if late else df
        return kept.select(*[F.col(c).alias(f"{side}_{c}") for c in df.columns], bucket(F.floor(whole / max(seconds, 1))).alias(f"{side}_bucket_"))

    near_by = lambda b: F.explode(F.array(b - 1, b, b + 1))
    near = f"right_{ts} between left_{ts} - interval {seconds} seconds and left_{ts} + interval {seconds} seconds"
    on = " and ".join([*[f"left_{k} = right_{k}" for k in keys], near])
    out = named(left, "left", lambda b: b).join(named(right, "right", near_by), F.expr(f"left_bucket_ = right_bucket_ and {on}"))
    return out.drop("left_bucket_", "right_bucket_", *[f"right_{k}" for k in keys]).withColumnsRenamed({f"left_{k}": k for k in keys})


def running_degrees(edges: DataFrame) -> DataFrame:
    """(id, deg) of each vertex that an edge of the micro-batch touches; the state is one counter a vertex (streams only, mode update).

    Edges are counted as they come, so they have to be canonical and without repeats.
    """

    def count(key, chunks, state):
        n = state.get[0] if state.exists else 0
        for chunk in chunks:
            n += int(chunk["n"].sum())
        state.update((n,))
        yield pd.DataFrame({"id": [key[0]], "deg": [n]})

    ends = edges.select(F.explode(F.array("u", "v")).alias("id"), F.lit(1).cast("long").alias("n"))
    return ends.groupBy("id").applyInPandasWithState(count, "id long, deg long", "n long", "update", "NoTimeout")
