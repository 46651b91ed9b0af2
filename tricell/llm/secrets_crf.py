"""Secret scan: fixed patterns, and a linear-chain conditional random field.

Three patterns give the base spans.  The field tags tokens as begin, inside or
outside of a secret, from each token's shape, the words before and after it,
the separators around it and a feature of the whole file.  Of the word before,
the whole and its last part (`key` of `aws_access_key`) have learnt weights, of
the word after, the whole and its first part; words share `WORD_BUCKETS` hashed
weights and are compared without case.  The field is trained on a bounded sample
of windows around the base spans of `positives` documents and of `negatives`
others (by least hash of the id), so it learns what the patterns' secrets look
like and finds others that stand in such a place without such a key.  Spans that overlap no base
span are added; base spans stay as they are.

Decoding is exact.  A token that speaks so firmly for outside that no
transition could outweigh it is cut out beforehand, by its shape alone where
no surroundings could help, else by its whole score; Viterbi runs over what
lies between such tokens, all runs of a block in step.

Positions are code points, ends exclusive.  Defined results: a null or empty
text has no span; without any base span in the table the field is untrained
and adds nothing; repeated rows are scanned alike; an empty table gives no
rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .storage import materialise

KINDS = ("assign", "access", "hex", "crf")
# Fixed patterns and least lengths of the base spans.
_ASSIGN = re.compile(rb"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
_ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
LEAST = {"assign": 12, "access": 18, "hex": 16}


#: Hashed words have so many weights.
WORD_BUCKETS = 1 << 10


@dataclass(frozen=True)
class CrfConfig:
    """Bounds of the training sample and settings of the training.

    A sampled document gives at most `windows` windows of `reach` tokens to
    either side: around its first `windows` - 4 base spans, its two longest
    tokens and two evenly spread ones.  Scanning has no such bound.
    """

    positives: int = 1500
    negatives: int = 500
    windows: int = 8
    reach: int = 6
    steps: int = 150
    rate: float = 0.1
    penalty: float = 1e-3
    seed: int = 3


def _member(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[[ord(c) for c in chars]] = True
    return out


_DIGITS = _member("0123456789")
_UPPER = _member("ABCDEFGHIJKLMNOPQRSTUVWXYZ")
_LOWER = _member("abcdefghijklmnopqrstuvwxyz")
_HEX = _member("0123456789abcdef")
_JOINT = _member("+/_.-")
_WIDE = np.arange(256) >= 128
_TOKEN = _DIGITS | _UPPER | _LOWER | _JOINT | _WIDE
_ASSIGNS, _QUOTES, _BREAK = _member("=:"), _member("\"'"), _member("\n")


def base_spans(texts: ts.Texts) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, kind, start, end) of the base spans, in byte positions of the block."""
    rows, kinds, starts, ends = [], [], [], []
    data = texts.buf.tobytes()

    def per_row(mask: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(mask) + 1, np.int64)
        np.cumsum(mask, out=sums[1:])
        return np.flatnonzero(np.diff(sums[texts.offsets]))

    for r in per_row(_ASSIGNS[texts.buf]):
        for m in _ASSIGN.finditer(data, texts.offsets[r], texts.offsets[r + 1]):
            if m.end(1) - m.start(1) >= LEAST["assign"]:
                rows.append(r), kinds.append(0), starts.append(m.start()), ends.append(m.end())
    at = data.find(b"AKIA")
    while at >= 0:
        r = int(np.searchsorted(texts.offsets, at, "right")) - 1
        end = int(texts.offsets[r + 1])
        m = _ACCESS.match(data, at, end)
        if m and m.end() - at >= LEAST["access"]:
            rows.append(r), kinds.append(1), starts.append(at), ends.append(m.end())
        at = data.find(b"AKIA", m.end() if m else at + 1)
    s, e = ts.run_bounds(_HEX[texts.buf], texts.offsets)
    long = e - s >= LEAST["hex"]
    s, e = s[long], e[long]
    row = np.searchsorted(texts.offsets, s, "right") - 1
    out = [np.concatenate([np.array(x, np.int64), y]) for x, y in ((rows, row), (kinds, np.full(len(s), 2)), (starts, s), (ends, e))]
    order = np.lexsort((out[1], out[2], out[0]))
    return tuple(x[order] for x in out)


# Sizes of the feature groups; the first are a token's own, the rest its surroundings'.
_LENGTHS, _CHARSETS, _SHARES, _SWITCHES = 10, 10, 5, 5
_OWN = (_LENGTHS, _CHARSETS, _SHARES, _SWITCHES, _LENGTHS * _CHARSETS)
# a word that is missing has the last bucket
_AROUND = (16, _CHARSETS + 1, _CHARSETS + 1, 2, 4, *[WORD_BUCKETS + 1] * 4)
_GROUPS = _OWN + _AROUND
_BASE = np.concatenate([[0], np.cumsum(_GROUPS)])


@dataclass
class Tokens:
    starts: np.ndarray
    ends: np.ndarray
    row: np.ndarray
    shape: np.ndarray  # length, charset, digit share, switches in one number
    features: np.ndarray  # column of each group's active weight


def _shape(texts: ts.Texts, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    def count(member: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(texts.buf) + 1, np.int32)
        np.cumsum(member[texts.buf], out=sums[1:], dtype=np.int32)
        return sums[ends] - sums[starts]

    n = ends - starts
    digits, upper, lower, hexes, joints = count(_DIGITS), count(_UPPER), count(_LOWER), count(_HEX), count(_JOINT)
    wide = n - digits - upper - lower - joints
    length = np.searchsorted([4, 8, 12, 16, 20, 28, 36, 48, 64], n, "right")
    charset = np.select(
        [wide > 0, digits == n, (lower == n), (upper == n), (hexes == n), (digits == 0) & (joints == 0), joints == 0, digits == 0, (upper > 0) & (lower > 0)],
        [0, 1, 2, 3, 4, 5, 6, 7, 8],
        9,
    )
    share = np.searchsorted([1e-9, 0.1, 0.3, 0.6], digits / np.maximum(n, 1), "right")
    kind = np.zeros(256, np.int8)
    kind[_DIGITS], kind[_UPPER], kind[_LOWER] = 1, 2, 3
    k = kind[texts.buf]
    change = np.zeros(len(k) + 1, np.int32)
    if len(k) > 1:
        np.cumsum(k[1:] != k[:-1], out=change[2:], dtype=np.int32)
    switches = change[ends] - change[np.minimum(starts + 1, ends)] if len(ends) else n
    switch = np.searchsorted([1, 3, 6, 12], switches, "right")
    return ((length * _CHARSETS + charset) * _SHARES + share) * _SWITCHES + switch


def _parts(shape: np.ndarray) -> list[np.ndarray]:
    rest, switch = np.divmod(shape, _SWITCHES)
    rest, share = np.divmod(rest, _SHARES)
    length, charset = np.divmod(rest, _CHARSETS)
    return [length, charset, share, switch, length * _CHARSETS + charset]


def tokens_of(texts: ts.Texts) -> Tokens:
    """All tokens with their shapes; the features are filled in by `surroundings`."""
    starts, ends = ts.run_bounds(_TOKEN[texts.buf], texts.offsets)
    row = np.repeat(np.arange(texts.rows), np.diff(np.searchsorted(starts, texts.offsets)))
    return Tokens(starts, ends, row, _shape(texts, starts, ends), np.zeros((0, 0), np.int32))


def surroundings(texts: ts.Texts, t: Tokens, which: np.ndarray) -> np.ndarray:
    """Active weight columns of all groups, for the tokens `which`."""
    n = len(t.starts)
    before, after = which - 1, which + 1
    has_before = (before >= 0) & (t.row[np.maximum(before, 0)] == t.row[which])
    has_after = (after < n) & (t.row[np.minimum(after, n - 1)] == t.row[which])
    gap_from = np.where(has_before, t.ends[np.maximum(before, 0)], texts.offsets[t.row[which]])

    def within(member: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(texts.buf) + 1, np.int32)
        np.cumsum(member[texts.buf], out=sums[1:], dtype=np.int32)
        return (sums[t.starts[which]] - sums[gap_from]) > 0

    gap = within(_ASSIGNS) + 2 * within(_QUOTES) + 4 * within(_BREAK) + 8 * (gap_from == t.starts[which])
    charset = _parts(t.shape)[1]
    left = np.where(has_before, charset[np.maximum(before, 0)], _CHARSETS)
    right = np.where(has_after, charset[np.minimum(after, n - 1)], _CHARSETS)
    digits = (np.bincount(t.row, weights=_parts(t.shape)[2] > 0, minlength=texts.rows) / np.maximum(np.bincount(t.row, minlength=texts.rows), 1))[t.row[which]]
    firm = np.searchsorted([0.02, 0.1, 0.3], digits, "right")
    words = _words(texts, t, np.maximum(before, 0), has_before, np.minimum(after, n - 1), has_after) if n else [np.zeros(0, np.int64)] * 4
    groups = [*_parts(t.shape[which]), gap, left, right, (~has_after).astype(int), firm, *words]
    return np.stack([g + b for g, b in zip(groups, _BASE[:-1], strict=True)], 1).astype(np.int32)


def _words(texts: ts.Texts, t: Tokens, before: np.ndarray, has_before: np.ndarray, after: np.ndarray, has_after: np.ndarray) -> list[np.ndarray]:
    """Buckets of the word before, its last part, the word after and its first part."""
    folded = ts.fold_case(texts.buf)
    joints = np.append(np.flatnonzero(_JOINT[texts.buf]), len(texts.buf))
    passed = np.searchsorted(joints, t.ends[before])
    tail = np.maximum(t.starts[before], np.where(passed > 0, joints[passed - 1] + 1, 0))
    stop = np.minimum(t.ends[after], joints[np.searchsorted(joints, t.starts[after])])

    def bucket(starts: np.ndarray, ends: np.ndarray, there: np.ndarray) -> np.ndarray:
        return np.where(there, (ts.run_hashes(folded, starts, ends) % np.uint64(WORD_BUCKETS)).astype(np.int64), WORD_BUCKETS)

    return [
        bucket(t.starts[before], t.ends[before], has_before), bucket(tail, t.ends[before], has_before),
        bucket(t.starts[after], t.ends[after], has_after), bucket(t.starts[after], stop, has_after),
    ]


@dataclass
class CrfModel:
    """`weights`: a row of three tag scores for each feature column; `moves`: from tag to tag; tags begin, inside, outside."""

    weights: np.ndarray
    moves: np.ndarray

    def __post_init__(self) -> None:
        shapes = np.arange(_LENGTHS * _CHARSETS * _SHARES * _SWITCHES)
        own = sum(self.weights[p + b] for p, b in zip(_parts(shapes), _BASE, strict=False))
        around = [self.weights[a:b] for a, b in zip(_BASE[len(_OWN) : -1], _BASE[len(_OWN) + 1 :], strict=True)]
        margin = own[:, 2] - np.maximum(own[:, 0], own[:, 1])
        for g in around:
            margin = margin + np.minimum(g[:, 2] - g[:, 0], g[:, 2] - g[:, 1]).min()
        self.firm = 2 * (self.moves.max() - self.moves.min()) + 1e-9
        #: shapes that are outside whatever stands around them
        self.outside = margin > self.firm

    def scores(self, features: np.ndarray) -> np.ndarray:
        """Scores of the three tags, group by group."""
        out = np.zeros((len(features), 3))
        for column in features.T:
            out += self.weights[column]
        return out

    def decode(self, scores: np.ndarray, heads: np.ndarray, sizes: np.ndarray, open_left: np.ndarray, open_right: np.ndarray) -> np.ndarray:
        """Best tags of runs of tokens; `open_*` marks runs that begin or end a text rather than beside an outside token."""
        tags = np.full(len(scores), 2)
        if not len(heads):
            return tags
        order = np.argsort(-sizes, kind="stable")
        heads, sizes, open_left, open_right = heads[order], sizes[order], open_left[order], open_right[order]
        longest = int(sizes[0])
        best = scores[heads] + np.where(open_left[:, None], 0, self.moves[2])
        back = []
        for t in range(1, longest):
            alive = int(np.searchsorted(-sizes, -t, "left"))
            step = best[:alive, :, None] + self.moves
            back.append(step.argmax(1))
            best[:alive] = step.max(1) + scores[heads[:alive] + t]
        final = best + np.where(open_right[:, None], 0, self.moves[:, 2])
        tag = final.argmax(1)
        for t in range(longest - 1, -1, -1):
            alive = int(np.searchsorted(-sizes, -t, "left"))
            tags[heads[:alive] + t] = tag[:alive]
            if t:
                tag[:alive] = np.take_along_axis(back[t - 1], tag[:alive, None], 1)[:, 0]
        return tags


def _log_sum(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis, keepdims=True))).squeeze(axis)


def train(windows: list[tuple[np.ndarray, np.ndarray]], config: CrfConfig = CrfConfig()) -> CrfModel:
    """Likelihood training by adaptive gradient steps over all windows at once."""
    weights, moves = np.zeros((_BASE[-1], 3)), np.zeros((3, 3))
    longest = max(len(y) for _, y in windows)
    n = len(windows)
    x = np.zeros((n, longest, len(_GROUPS)), np.int32)
    y = np.full((n, longest), 2)
    valid = np.zeros((n, longest), bool)
    for i, (f, tags) in enumerate(windows):
        x[i, : len(tags)], y[i, : len(tags)], valid[i, : len(tags)] = f, tags, True
    pair = valid[:, 1:] & valid[:, :-1]
    true_moves = np.zeros((3, 3))
    np.add.at(true_moves, (y[:, :-1][pair], y[:, 1:][pair]), 1)
    truth = np.eye(3)[y]
    flat = x[valid]
    m = [np.zeros_like(weights), np.zeros_like(moves)]
    v = [np.zeros_like(weights), np.zeros_like(moves)]
    for turn in range(1, config.steps + 1):
        score = np.zeros((n, longest, 3))
        for g in range(len(_GROUPS)):
            score += weights[x[:, :, g]]
        ahead, behind = np.zeros_like(score), np.zeros_like(score)
        ahead[:, 0] = score[:, 0]
        for t in range(1, longest):
            new = _log_sum(ahead[:, t - 1, :, None] + moves, 1) + score[:, t]
            ahead[:, t] = np.where(valid[:, t, None], new, ahead[:, t - 1])
        for t in range(longest - 2, -1, -1):
            new = _log_sum(moves + (score[:, t + 1] + behind[:, t + 1])[:, None, :], 2)
            behind[:, t] = np.where(valid[:, t + 1, None], new, 0)
        total = _log_sum(ahead[:, -1], 1)
        chance = np.exp(ahead + behind - total[:, None, None])
        gap = (truth - chance)[valid]
        grad = np.zeros_like(weights)
        for g, (low, high) in enumerate(zip(_BASE[:-1], _BASE[1:], strict=True)):
            for k in range(3):
                grad[low:high, k] = np.bincount(flat[:, g] - low, weights=gap[:, k], minlength=high - low)
        both = ahead[:, :-1, :, None] + moves + (score + behind)[:, 1:, None, :] - total[:, None, None, None]
        moved = np.exp(np.where(pair[:, :, None, None], both, -np.inf)).sum((0, 1))
        grads = [grad / n - config.penalty * weights, (true_moves - moved) / n - config.penalty * moves]
        for i, (p, g) in enumerate(zip((weights, moves), grads, strict=True)):
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.99 * v[i] + 0.01 * g * g
            p += config.rate * (m[i] / (1 - 0.9**turn)) / (np.sqrt(v[i] / (1 - 0.99**turn)) + 1e-8)
    return CrfModel(weights, moves)


def _weak_tags(t: Tokens, spans: tuple[np.ndarray, ...]) -> np.ndarray:
    """Tags that the base spans give the tokens; of an assignment, its value."""
    tags = np.full(len(t.starts), 2)
    for kind, start, end in zip(*spans[1:], strict=True):
        i, j = np.searchsorted(t.ends, start, "right"), np.searchsorted(t.starts, end, "left")
        if kind == 0:
            inside = np.flatnonzero(t.ends[i:j] - t.starts[i:j] >= LEAST["assign"])
            if not len(inside):
                continue
            i += int(inside[0])
        if j > i:
            tags[i] = 0
            tags[i + 1 : j] = np.where(tags[i + 1 : j] == 0, 0, 1)
    return tags


def _windows(config: CrfConfig):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for texts in ts.text_blocks(batch.column("text")):
                t = tokens_of(texts)
                spans = base_spans(texts)
                tags = _weak_tags(t, spans)
                ptr = np.searchsorted(t.row, np.arange(texts.rows + 1))
                cut: list[np.ndarray] = []
                for r in range(texts.rows):
                    low, high = ptr[r], ptr[r + 1]
                    if low == high:
                        continue
                    marks = low + np.flatnonzero(tags[low:high] == 0)
                    # beside the secrets, the longest tokens and an even spread teach what is outside
                    hard = low + np.argsort(-(t.ends[low:high] - t.starts[low:high]), kind="stable")[:2]
                    even = np.linspace(low, high - 1, 2).astype(int)
                    for c in dict.fromkeys([*marks[: config.windows - 4], *hard, *even]):
                        cut.append(np.arange(max(low, c - config.reach), min(high, c + config.reach + 1)))
                if not cut:
                    continue
                which = np.concatenate(cut)
                ends = np.cumsum([len(w) for w in cut])[:-1]
                out_f = [f.ravel().tolist() for f in np.split(surroundings(texts, t, which), ends)]
                out_t = [w.tolist() for w in np.split(tags[which], ends)]
                yield pa.RecordBatch.from_arrays([pa.array(out_f, pa.list_(pa.int32())), pa.array(out_t, pa.list_(pa.int32()))], ["features", "tags"])

    return make


def _marker(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for texts in ts.text_blocks(batch.column("text")):
            marked = np.zeros(texts.rows, bool)
            marked[base_spans(texts)[0]] = True
            yield pa.RecordBatch.from_arrays([batch.column("id").slice(texts.first, texts.rows), pa.array(marked)], ["id", "marked"])


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", config: CrfConfig = CrfConfig()) -> CrfModel | None:
    """Train on windows of a bounded sample of `docs`; nothing if no document has a base span."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).where("id is not null")
    turn = F.xxhash64(F.lit(config.seed), F.col("id"))
    marks = materialise(rows.mapInArrow(_marker, "id long, marked boolean").withColumn("turn", turn), "marks")
    ids: list[tuple[int]] = []
    for value, limit in ((True, config.positives), (False, config.negatives)):
        own = marks.where(F.col("marked") == value).select("id", "turn").distinct().orderBy("turn", "id").limit(limit).collect()
        if value and not own:
            return None
        ids += [(r.id,) for r in own]
    # at most positives + negatives ids, and one text of each
    sample = rows.join(F.broadcast(spark.createDataFrame(sorted(set(ids)), "id long")), "id").groupBy("id").agg(F.min("text").alias("text"))
    found = sample.mapInArrow(_windows(config), "features array<int>, tags array<int>").collect()
    found = sorted((tuple(r.tags), tuple(r.features)) for r in found)
    return train([(np.array(f, np.int32).reshape(len(t), -1), np.array(t)) for t, f in found], config)


def field_spans(texts: ts.Texts, model: CrfModel) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, start, end) of the runs that the field tags as secrets, in byte positions."""
    t = tokens_of(texts)
    which = np.flatnonzero(~model.outside[t.shape])
    if not len(which):
        return which, which, which
    scores = model.scores(surroundings(texts, t, which))
    unsure = scores[:, 2] - np.maximum(scores[:, 0], scores[:, 1]) <= model.firm
    which, scores = which[unsure], scores[unsure]
    if not len(which):
        return which, which, which
    n = len(t.starts)
    new = np.ones(len(which), bool)
    new[1:] = (which[1:] != which[:-1] + 1) | (t.row[which[1:]] != t.row[which[:-1]])
    heads = np.flatnonzero(new)
    sizes = np.diff(np.append(heads, len(which)))
    first, last = which[heads], which[heads + sizes - 1]
    open_left = (first == 0) | (t.row[np.maximum(first - 1, 0)] != t.row[first])
    open_right = (last == n - 1) | (t.row[np.minimum(last + 1, n - 1)] != t.row[last])
    tags = model.decode(scores, heads, sizes, open_left, open_right)
    # a span begins at a begin tag, or at an inside tag that follows no other secret token
    secret = tags != 2
    starts = secret & (tags == 0)
    joined = np.zeros(len(tags), bool)
    joined[1:] = secret[:-1] & ~new[1:]
    starts |= secret & ~joined
    begin = np.flatnonzero(starts)
    stop = secret.copy()
    stop[:-1] &= starts[1:] | ~secret[1:] | new[1:]
    end = np.flatnonzero(stop)
    return t.row[which[begin]], t.starts[which[begin]], t.ends[which[end]]


def scan_block(texts: ts.Texts, model: CrfModel | None) -> list[list[tuple[int, int, int]]]:
    """For each row its (start, kind, end) spans in code points, in order."""
    row, kind, start, end = base_spans(texts)
    if model is not None:
        r, s, e = field_spans(texts, model)
        # base spans of one row may overlap each other, so each is met on its own
        free = np.ones(len(r), bool)
        low, high = np.searchsorted(s, start, "left"), np.searchsorted(s, end, "left")
        for i, j, b, f in zip(low, high, start, end, strict=True):
            i = max(0, i - 1)
            free[i:j] &= ~((s[i:j] < f) & (e[i:j] > b))
        row, kind = np.append(row, r[free]), np.append(kind, np.full(int(free.sum()), 3))
        start, end = np.append(start, s[free]), np.append(end, e[free])
    points = ts.code_points(texts.buf)
    out: list[list[tuple[int, int, int]]] = [[] for _ in range(texts.rows)]
    for r, k, s, e in zip(row, kind, start, end, strict=True):
        base = points[texts.offsets[r]]
        out[r].append((int(points[s] - base), int(k), int(points[e] - base)))
    for spans in out:
        spans.sort()
    return out


def _scanner(model: CrfModel | None):
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for texts in ts.text_blocks(batch.column("text")):
                spans = [[{"kind": KINDS[k], "start": s, "end": e} for s, k, e in x] for x in scan_block(texts, model)]
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(texts.first, texts.rows), pa.array(spans, kind)], ["id", "spans"])

    return scan


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: CrfModel | None = None) -> DataFrame:
    """One row for each row of `docs`: its id and its spans (kind, start, end), by start and kind."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_scanner(model), "id long, spans array<struct<kind: string, start: bigint, end: bigint>>").withColumnRenamed("id", id_col)
