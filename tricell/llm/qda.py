"""Quality classifier: regularised quadratic discriminant over document statistics.

One pass over the texts turns each document into a few transformed statistics
(`FEATURES`).  Training needs only the count, sum and outer-product sum of each
class, summed where the rows lie, so all labelled rows count.  Each class
covariance is shrunk towards the pooled one and towards a multiple of the
identity; its Cholesky factor is computed once and kept in the model.  The raw
score is the difference of the two log densities by Mahalanobis distance, plus
the log prior odds; a two-parameter logistic calibration, fitted on a
histogram of raw scores, turns it into a probability.

Defined results: a null or empty text has all statistics at their value for no
words, and is scored like any other; labels with a null id or value are passed
over; of several labels of one id the greatest counts; if a class has no row
every score is the share of label 1; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .host_rules import duplicate_lines, repeated_words
from .storage import materialise

FEATURES = (
    "words", "word_length", "word_spread", "longest_word", "symbols", "capitals", "digits", "punctuation",
    "repeated_lines", "repeated_words", "distinct_words", "words_per_line", "sentence_ends", "capital_words", "bare_words", "shouts",
)


#: statistics are whole multiples of 1 / _UNIT, so that sums over rows are exact in any order
_UNIT = 4096


def _member(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[[ord(c) for c in chars]] = True
    return out


_UPPER, _LOWER, _DIGIT = _member("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _member("abcdefghijklmnopqrstuvwxyz"), _member("0123456789")
_SYMBOL, _PUNCTUATION, _END = _member("#*$%&|<>@^~_=+\\{}[]"), _member(".,;:!?'\"()-"), _member(".!?")


@dataclass(frozen=True)
class QdaConfig:
    """`pool`: weight of the pooled covariance; `ridge`: weight of the identity."""

    pool: float = 0.1
    ridge: float = 0.02
    bins: int = 400
    threshold: float = 0.3


def document_statistics(texts: ts.Texts) -> np.ndarray:
    """One row of `FEATURES` for each text."""
    words = ts.scan_words(texts)
    n = words.counts
    some = np.maximum(n, 1)
    buf = texts.buf

    def by_row(member: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(buf) + 1, np.int64)
        np.cumsum(member[buf], out=sums[1:])
        return np.diff(sums[texts.offsets])

    def by_word(values: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(values) + 1)
        np.cumsum(values, out=sums[1:])
        return np.diff(sums[words.ptr])

    points = ts.code_points(buf)
    length = points[words.ends] - points[words.starts]
    total = np.maximum(by_word(length), 1)
    mean = total / some
    spread = np.sqrt(np.maximum(by_word(length.astype(float) ** 2) / some - mean**2, 0))
    longest = np.zeros(texts.rows)
    full = np.flatnonzero(n)
    if len(full):
        longest[full] = np.maximum.reduceat(length, words.ptr[:-1][full])
    upper, lower = by_row(_UPPER), by_row(_LOWER)
    lines = np.maximum(by_row(_member("\n")) + 1, 1)
    row = words.row
    number = ts.numbered_runs(buf, words.starts, words.ends, words.hashes)
    order = np.lexsort((number, row))
    fresh = np.ones(len(order), bool)
    fresh[1:] = (number[order][1:] != number[order][:-1]) | (row[order][1:] != row[order][:-1])
    distinct = np.bincount(row[order][fresh], minlength=texts.rows)
    letters = np.zeros(len(buf) + 1, np.int64)
    np.cumsum(_UPPER[buf] | _LOWER[buf] | _DIGIT[buf] | (buf >= 128), out=letters[1:])
    capitals = np.zeros(len(buf) + 1, np.int64)
    np.cumsum(_UPPER[buf], out=capitals[1:])
    bare = letters[words.ends] == letters[words.starts]
    loud = (capitals[words.ends] - capitals[words.starts] >= 2) if len(buf) else bare
    ends = _END[buf[words.ends - 1]] if len(words.ends) else bare
    first = _UPPER[buf[words.starts]] if len(words.starts) else bare
    share = lambda x, of: np.sqrt(x / of)
    return np.stack(
        [
            np.log1p(n), np.log(mean), np.log1p(spread), np.log1p(longest), share(by_row(_SYMBOL), total), share(upper, np.maximum(upper + lower, 1)),
            share(by_row(_DIGIT), total), share(by_row(_PUNCTUATION), total), share(duplicate_lines(texts, words), lines), share(repeated_words(words, number, 3), some),
            distinct / some, np.log1p(n / lines), share(by_word(ends), some), share(by_word(first), some), share(by_word(bare), some), share(by_word(loud), some),
        ],
        axis=1,
    )


def _statistics(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    d = len(FEATURES)
    for batch in batches:
        for texts in ts.text_blocks(batch.column("text")):
            x = np.round(document_statistics(texts) * _UNIT) / _UNIT
            ptr = np.arange(0, texts.rows * d + 1, d, dtype=np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("id").slice(texts.first, texts.rows), pa.ListArray.from_arrays(ptr, x.ravel())], ["id", "x"])


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy().reshape(len(column), len(FEATURES))


def _moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    d = len(FEATURES)
    n, s, q = np.zeros(2, np.int64), np.zeros((2, d), np.int64), np.zeros((2, d, d), np.int64)
    for batch in batches:
        x, y = np.round(_matrix(batch.column("x")) * _UNIT).astype(np.int64), batch.column("y").to_numpy()
        for k in (0, 1):
            own = x[y == k]
            n[k] += len(own)
            s[k] += own.sum(0)
            q[k] += own.T @ own
    flat = [np.concatenate([[n[k]], s[k], q[k].ravel()]) for k in (0, 1)]
    yield pa.RecordBatch.from_arrays([pa.array(np.repeat([0, 1], len(flat[0]))), pa.array(np.tile(np.arange(len(flat[0])), 2)), pa.array(np.concatenate(flat))], ["y", "slot", "v"])


@dataclass
class QdaModel:
    """Centre and scale of the statistics; by class the mean, the Cholesky factor's inverse and its log determinant."""

    centre: np.ndarray
    scale: np.ndarray
    means: list[np.ndarray]
    inverse_factors: list[np.ndarray]
    log_determinants: list[float]
    log_odds: float
    constant: float | None = None
    slope: float = 1.0
    shift: float = 0.0

    def raw(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.zeros(len(x))
        z = (x - self.centre) / self.scale
        logs = []
        for mean, factor, det in zip(self.means, self.inverse_factors, self.log_determinants, strict=True):
            y = (z - mean) @ factor.T
            logs.append(-0.5 * (y * y).sum(1) - det)
        return np.clip(logs[1] - logs[0] + self.log_odds, -60, 60)

    def probability(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        return 1 / (1 + np.exp(-(self.slope * self.raw(x) + self.shift)))


def model_from_moments(n: np.ndarray, s: np.ndarray, q: np.ndarray, config: QdaConfig) -> QdaModel:
    d = s.shape[1]
    if not n.min():
        blank = np.zeros(d)
        return QdaModel(blank, blank + 1, [], [], [], 0.0, constant=float(n[1] / n.sum()) if n.sum() else 0.5)
    total = n.sum()
    centre = s.sum(0) / total
    scale = np.sqrt(np.maximum(np.diag(q.sum(0)) / total - centre**2, 1e-12))
    scale[scale < 1e-5] = 1.0
    means, covariances = [], []
    for k in (0, 1):
        mean = s[k] / n[k]
        covariances.append((q[k] / n[k] - np.outer(mean, mean)) / np.outer(scale, scale))
        means.append((mean - centre) / scale)
    pooled = (n[0] * covariances[0] + n[1] * covariances[1]) / total
    factors, dets = [], []
    for k in (0, 1):
        c = (1 - config.pool) * covariances[k] + config.pool * pooled
        c = (1 - config.ridge) * c + config.ridge * max(np.trace(c) / d, 1e-9) * np.eye(d)
        root = np.linalg.cholesky((c + c.T) / 2)
        factors.append(np.linalg.inv(root))
        dets.append(float(np.log(np.diag(root)).sum()))
    return QdaModel(centre, scale, means, factors, dets, float(np.log(n[1] / n[0])))


def logistic_fit(x: np.ndarray, ones: np.ndarray, n: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a logistic curve through a histogram, by damped Newton steps."""
    a, b = 0.1, 0.0
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -40, 40)))
        w = n * p * (1 - p)
        g = np.array([((ones - n * p) * x).sum() - 1e-3 * a, (ones - n * p).sum()])
        h = np.array([[(w * x * x).sum() + 1e-3, (w * x).sum()], [(w * x).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        step *= min(1.0, 2.0 / max(np.abs(step).max(), 1e-12))
        a, b = max(a + step[0], 1e-3), b + step[1]
        if np.abs(step).max() < 1e-9:
            break
    return float(a), float(b)


def statistics_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Stored (id, x): the statistics of each row's whole text."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return materialise(rows.mapInArrow(_statistics, "id long, x array<double>"), "statistics")


def fit(table: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", config: QdaConfig = QdaConfig()) -> QdaModel:
    """`labels` holds the rows that may be learnt from."""
    d = len(FEATURES)
    usable = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("y")).where("id is not null and y in (0, 1)")
    usable = usable.groupBy("id").agg(F.max("y").alias("y"))
    known = table.join(usable, "id").select("x", "y")
    flat = np.zeros((2, 1 + d + d * d))
    for r in known.mapInArrow(_moments, "y long, slot long, v long").groupBy("y", "slot").agg(F.sum(F.col("v").cast("decimal(38,0)")).alias("v")).collect():
        flat[r.y, r.slot] = int(r.v) / _UNIT ** min(2, 0 if r.slot == 0 else 1 if r.slot <= d else 2)
    model = model_from_moments(flat[:, 0], flat[:, 1 : d + 1], flat[:, d + 1 :].reshape(2, d, d), config)
    if model.constant is None:
        step = 120 / config.bins

        def bins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                at = np.floor((model.raw(_matrix(batch.column("x"))) + 60) / step).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(at), batch.column("y").cast(pa.int64())], ["bin", "y"])

        hist = known.mapInArrow(bins, "bin long, y long").groupBy("bin").agg(F.sum("y").alias("ones"), F.count("*").alias("n")).collect()
        x, ones, n = (np.array([r[i] for r in hist], float) for i in range(3))
        model.slope, model.shift = logistic_fit((x + 0.5) * step - 60, ones, n)
    return model


def score(table: DataFrame, model: QdaModel) -> DataFrame:
    """(id, score) for each row of a statistics table."""

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(model.probability(_matrix(batch.column("x"))))], ["id", "score"])

    return table.mapInArrow(apply, "id long, score double")
