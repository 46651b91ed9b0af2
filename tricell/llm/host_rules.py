"""Quality rules judged by host.

Each document is put to fixed rules.  Failures are then counted by host, the
hosts' failure rates are shrunk with a beta prior fitted to all hosts by
moments, and a host whose shrunken rate passes `host_limit` takes all of its
documents with it.  A document is kept if it passes its own rules and its
host's verdict.

The texts are read once; counts by host are summed before they are shuffled,
so a host with a third of all rows costs one row a task.  Lines and words are
grouped by hash and then compared byte by byte.

Defined results: a null text has no words and fails; rows with a null host
form one host of their own; repeated rows each count; with fewer than two
hosts, or no spread between them, the prior weighs one document; an empty table
gives no rows; columns of the table are never part of the result, so none can
clash.  A text is scanned whole by one task, at about 100 bytes of memory for
each of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .storage import materialise

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True


@dataclass(frozen=True)
class HostRules:
    """`host_limit`: the shrunken failure rate from which a host is rejected."""

    min_words: int = 50
    repeat_percent: int = 50
    window: int = 3
    host_limit: float = 0.6


def repeated_words(words: ts.Words, number: np.ndarray, window: int) -> np.ndarray:
    """For each row, how many words lie in a window of that many words that occurs twice or more in the row.

    `number` says which word each is.
    """
    out = np.zeros(len(words.ptr) - 1, np.int64)
    n = len(words.hashes)
    if n < window:
        return out
    row = words.row
    valid = np.flatnonzero(row[: n - window + 1] == row[window - 1 :])
    grams = ts.window_numbers(number, words.ptr, valid, window)
    by_gram = np.lexsort((grams, row[valid]))
    order, grams = valid[by_gram], grams[by_gram]
    same = (grams[1:] == grams[:-1]) & (row[order][1:] == row[order][:-1])
    twice = np.zeros(len(order), bool)
    twice[1:] |= same
    twice[:-1] |= same
    covered = np.zeros(n, bool)
    for k in range(window):
        covered[order[twice] + k] = True
    np.add.at(out, row[covered], 1)
    return out


def duplicate_lines(texts: ts.Texts, words: ts.Words) -> np.ndarray:
    """For each row, how many lines with a word equal an earlier line of the row."""
    out = np.zeros(texts.rows, np.int64)
    if not len(words.starts):
        return out
    starts, ends = ts.run_bounds(texts.buf != 10, texts.offsets)
    held = np.searchsorted(words.starts, ends) > np.searchsorted(words.starts, starts)
    starts, ends = starts[held], ends[held]
    line = ts.numbered_runs(texts.buf, starts, ends)
    row = np.searchsorted(texts.offsets, starts, "right") - 1
    order = np.lexsort((line, row))
    same = (line[order][1:] == line[order][:-1]) & (row[order][1:] == row[order][:-1])
    np.add.at(out, row[order][1:][same], 1)
    return out


def _measurer(window: int):
    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for texts in ts.text_blocks(batch.column("text")):
                words = ts.scan_words(texts)
                number = ts.numbered_runs(texts.buf, words.starts, words.ends, words.hashes)
                points = ts.code_points(texts.buf)
                inside = np.zeros(len(texts.buf) + 1, np.int64)
                np.cumsum(_SYMBOL[texts.buf], out=inside[1:])
                chars = np.zeros(len(words.starts) + 1, np.int64)
                np.cumsum(points[words.ends] - points[words.starts], out=chars[1:])
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("id").slice(texts.first, texts.rows),
                        batch.column("host").slice(texts.first, texts.rows),
                        pa.array(words.counts.astype(np.int64)),
                        pa.array(np.diff(chars[words.ptr])),
                        pa.array(np.diff(inside[texts.offsets])),
                        pa.array(duplicate_lines(texts, words)),
                        pa.array(repeated_words(words, number, window)),
                    ],
                    ["id", "host", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"],
                )

    return measure


_MEASURES = "id long, host string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def beta_prior(hosts: DataFrame) -> tuple[float, float]:
    """(a, b) of the beta prior that the hosts' rates suggest, by moments weighted by documents."""
    total = hosts.agg(F.sum("docs").alias("n"), F.sum("failed").alias("k"), F.count("*").alias("hosts")).first()
    if not total.n:
        return 0.5, 0.5
    mean = total.k / total.n
    if not 0 < mean < 1:
        return mean + 1e-6, 1 - mean + 1e-6
    spread = hosts.agg(F.sum(F.col("docs") * F.pow(F.col("failed") / F.col("docs") - mean, 2)).alias("s"), F.sum(F.col("docs") * F.col("docs")).alias("q")).first()
    # the variance between hosts, after what sampling of documents adds
    between = (spread.s - (total.hosts - 1) * mean * (1 - mean)) / max(total.n - spread.q / total.n, 1e-9) if total.hosts > 1 else 0.0
    weight = mean * (1 - mean) / between - 1 if between > 1e-12 else float(total.n)
    weight = min(max(weight, 1.0), float(total.n))
    return mean * weight, (1 - mean) * weight


def judge_hosts(measured: DataFrame, rules: HostRules = HostRules()) -> DataFrame:
    """(host, docs, failed, host_rate, host_kept) from rows with host and base_failed."""
    hosts = measured.groupBy("host").agg(F.count("*").alias("docs"), F.sum(F.col("base_failed").cast("long")).alias("failed"))
    hosts = materialise(hosts, "hosts")
    a, b = beta_prior(hosts)
    rate = (F.col("failed") + F.lit(a)) / (F.col("docs") + F.lit(a + b))
    return hosts.withColumn("host_rate", rate).withColumn("host_kept", F.col("host_rate") < rules.host_limit)


def apply_host_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", rules: HostRules = HostRules()) -> DataFrame:
    """One row for each row of `docs`: measures, base_failed, the host's counts and rate, kept."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(host_col).cast("string").alias("host"), F.col(text_col).alias("text"))
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.repeat_percent * F.col("n_words"))
    measured = materialise(rows.mapInArrow(_measurer(rules.window), _MEASURES).withColumn("base_failed", failed), "measured")
    hosts = judge_hosts(measured, rules).withColumnRenamed("host", "named")
    joined = measured.join(hosts, F.col("host").eqNullSafe(F.col("named")), "left")
    return joined.select(
        F.col("id").alias(id_col), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~F.col("base_failed") & F.col("host_kept")).alias("kept"), "docs", "failed", "host_rate",
    )
