"""Vectorised scanning of Arrow string columns.

Words are maximal runs of bytes outside space and 0x09-0x0D; in UTF-8 no byte
of a multi-byte character falls in that set, so byte scanning equals the
code-point rule ``[^\\x20\\x09-\\x0D]+``.  A run's 64-bit hash chains its 8-byte
lanes through a finaliser, one numpy pass a lane for all runs at once; long runs
are cut in pieces whose hashes are hashed again.  Where equality decides a
result, `numbered_runs` compares the bytes of runs with equal hashes.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import sha256

import numpy as np
import pyarrow as pa

U64 = np.uint64
BLOCK = 1 << 20
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
_FOLDED = np.arange(256, dtype=np.uint8)
_FOLDED[65:91] += 32
#: longest run that is hashed lane by lane; a longer one is hashed over its pieces' hashes
_PIECE = 64
#: by number of bytes: the lane's bits that belong to the run
_LANE_BITS = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)


def give_back_memory() -> None:
    """Return what is free to the system: Spark's workers live on after a task, and what they keep counts for the executor."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser that spreads every input bit over the word."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def _lanes(buf: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on, as one number; past the end there are zeros."""
    padded = np.zeros(len(buf) + 8, np.uint8)
    padded[: len(buf)] = buf
    return np.ndarray(len(buf) + 1, "<u8", padded, strides=(1,))


def fold_case(buf: np.ndarray) -> np.ndarray:
    """A-Z as a-z."""
    return _FOLDED[buf]


def _chained(lanes: np.ndarray, starts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Hashes of runs of at most `_PIECE` bytes: every lane goes through the finaliser with all before it."""
    out = mix(size.astype(np.uint64) + U64(0x9E3779B97F4A7C15))
    left = np.arange(len(starts))
    for at in range(0, int(size.max(initial=0)), 8):
        left = left[size[left] > at]
        lane = lanes[starts[left] + at] & _LANE_BITS[np.minimum(size[left] - at, 8)]
        out[left] = mix((out[left] + U64(0xD1B54A32D192ED03)) ^ mix(lane + U64(at + 1)))
    return out


def run_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte ranges; equal bytes give equal hashes."""
    size = ends - starts
    long = np.flatnonzero(size > _PIECE)
    lanes = _lanes(buf)
    if not len(long):
        return _chained(lanes, starts, size)
    out = np.empty(len(starts), np.uint64)
    short = np.flatnonzero(size <= _PIECE)
    out[short] = _chained(lanes, starts[short], size[short])
    pieces = -(-size[long] // _PIECE)
    first = np.cumsum(pieces) - pieces
    head = np.repeat(starts[long], pieces) + _PIECE * (np.arange(pieces.sum()) - np.repeat(first, pieces))
    parts = _chained(lanes, head, np.minimum(head + _PIECE, np.repeat(ends[long], pieces)) - head)
    out[long] = mix(run_hashes(parts.view(np.uint8), 8 * first, 8 * (first + pieces)) ^ mix(size[long].astype(np.uint64)))
    return out


def equal_runs(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, others: np.ndarray, other_ends: np.ndarray) -> np.ndarray:
    """Whether the bytes of each range equal those of its other, compared lane by lane."""
    size = ends - starts
    same = size == other_ends - others
    lanes = _lanes(buf)
    for low, high in cuts(np.where(same, -(-size // 8), 0)):
        rows = np.arange(low, high)[same[low:high]]
        n = -(-size[rows] // 8)
        at = 8 * (np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n))
        row = np.repeat(rows, n)
        kept = _LANE_BITS[np.minimum(size[row] - at, 8)]
        same[row[((lanes[starts[row] + at] ^ lanes[others[row] + at]) & kept) != 0]] = False
    return same


def cuts(n: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows that have about `BLOCK` of `n` together; a row of more comes alone."""
    total, at = np.cumsum(n), 0
    while at < len(n):
        to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + BLOCK, "right")))
        yield at, to
        at = to


def numbered_runs(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray | None = None) -> np.ndarray:
    """A number for each range, equal if and only if the bytes are.

    Ranges are grouped by hash; then each is compared with its group's first.
    """
    if not len(starts):
        return np.zeros(0, np.int64)
    hashes = run_hashes(buf, starts, ends) if hashes is None else hashes
    _, first, number = np.unique(hashes, return_index=True, return_inverse=True)
    rep = first[number]
    later = np.flatnonzero(rep != np.arange(len(rep)))
    same = equal_runs(buf, starts[later], ends[later], starts[rep[later]], ends[rep[later]])
    taken: dict[bytes, int] = {}
    for i in later[~same]:  # ranges whose hash collides with another one's, if ever
        number[i] = taken.setdefault(buf[starts[i] : ends[i]].tobytes(), len(first) + len(taken))
    return number.astype(np.int64)


def paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A number for each pair (a, b) of numbers, equal if and only if the pairs are."""
    return np.unique(a * (int(b.max(initial=0)) + 1) + b, return_inverse=True)[1].astype(np.int64)


@dataclass
class Texts:
    """Some consecutive rows of a string column; null reads as empty."""

    first: int
    buf: np.ndarray
    offsets: np.ndarray

    @property
    def rows(self) -> int:
        return len(self.offsets) - 1


@dataclass
class Words:
    """Words of a `Texts`; row r owns words ptr[r]:ptr[r + 1]."""

    starts: np.ndarray
    ends: np.ndarray
    hashes: np.ndarray
    ptr: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.ptr)

    @property
    def row(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ptr) - 1), self.counts)


def text_blocks(column: pa.Array, limit: int = BLOCK) -> Iterator[Texts]:
    """Cut a column in runs of rows of about `limit` bytes; a longer text comes alone."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_null(column.type):
        column = column.cast(pa.string())
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    n = len(column)
    if not n:
        return
    _, offset_buf, data = column.buffers()
    offsets = np.frombuffer(offset_buf, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    whole = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield Texts(at, whole[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
        at = to


def run_bounds(mask: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of true bytes; no run crosses a row bound."""
    starts, ends = mask.copy(), mask.copy()
    starts[1:] &= ~mask[:-1]
    ends[:-1] &= ~mask[1:]
    heads = offsets[:-1][offsets[:-1] < len(mask)]
    starts[heads] = mask[heads]
    tails = offsets[1:][offsets[1:] > 0] - 1
    ends[tails] = mask[tails]
    return np.flatnonzero(starts), np.flatnonzero(ends) + 1


def scan_words(texts: Texts, folded: bool = False) -> Words:
    """All words with their hashes; `folded` makes A-Z equal a-z."""
    starts, ends = run_bounds(~IS_SPACE[texts.buf], texts.offsets)
    hashes = run_hashes(fold_case(texts.buf) if folded else texts.buf, starts, ends)
    return Words(starts, ends, hashes, np.searchsorted(starts, texts.offsets))


def shingles(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of `width` words by row, and where each row's runs begin.

    A row of fewer words, but at least one, has its whole sequence as its only run.
    """
    counts = words.counts
    sizes = np.where(counts == 0, 0, np.maximum(counts - width + 1, 1))
    ptr = np.concatenate([[0], np.cumsum(sizes)])
    out = np.empty(ptr[-1], np.uint64)
    full = counts >= width
    n = len(words.hashes)
    if n >= width and full.any():
        rolled = np.zeros(n - width + 1, np.uint64)
        for k in range(width):
            rolled = mix(rolled * U64(3) + words.hashes[k : n - width + 1 + k] + U64(k + 1))
        keep = np.repeat(full, sizes)
        index = np.arange(ptr[-1]) - np.repeat(ptr[:-1], sizes) + np.repeat(words.ptr[:-1], sizes)
        out[keep] = rolled[index[keep]]
    for r in np.flatnonzero((counts > 0) & ~full):
        h = np.zeros(1, np.uint64)
        for k, w in enumerate(words.hashes[words.ptr[r] : words.ptr[r + 1]]):
            h = mix(h * U64(3) + w + U64(k + 1))
        out[ptr[r]] = h[0]
    return out, ptr


def _sets(grams: np.ndarray, ptr: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values of each row, sorted, and where each row's begin."""
    if not len(grams):
        return grams, ptr
    row = np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))
    order = np.lexsort((grams, row))
    grams, row = grams[order], row[order]
    first = np.ones(len(grams), bool)
    first[1:] = (grams[1:] != grams[:-1]) | (row[1:] != row[:-1])
    return grams[first], np.searchsorted(row[first], np.arange(len(ptr)))


def shingle_sets(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes by row, and where each row's set begins."""
    return _sets(*shingles(words, width))


def window_numbers(number: np.ndarray, ptr: np.ndarray, index: np.ndarray, width: int) -> np.ndarray:
    """Numbers of the word windows that begin at `index`, equal if and only if their words are.

    `number` says which word each is; a window ends with its row.
    """
    end = ptr[1:][np.searchsorted(ptr, index, "right") - 1]
    out = np.zeros(len(index), np.int64)
    for k in range(width):
        out = paired(out, np.where(index + k < end, number[np.minimum(index + k, len(number) - 1)] + 1, 0))
    return out


def exact_shingle_sets(texts: Texts, width: int, folded: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """As `shingle_sets`, with numbers that are equal in these texts if and only if the shingles' bytes are."""
    words = scan_words(texts, folded)
    sizes = np.where(words.counts == 0, 0, np.maximum(words.counts - width + 1, 1))
    ptr = np.concatenate([[0], np.cumsum(sizes)])
    if not ptr[-1]:
        return np.zeros(0, np.int64), ptr
    number = numbered_runs(fold_case(texts.buf) if folded else texts.buf, words.starts, words.ends, words.hashes)
    index = np.arange(ptr[-1]) - np.repeat(ptr[:-1], sizes) + np.repeat(words.ptr[:-1], sizes)
    return _sets(window_numbers(number, words.ptr, index, width), ptr)


def word_digests(texts: Texts, words: Words, folded: bool = True) -> list[bytes]:
    """SHA-256 of each row's sequence of words."""
    buf = fold_case(texts.buf) if folded else texts.buf
    size = words.ends - words.starts + 1
    total = np.concatenate([[0], np.cumsum(size)])
    at = np.arange(total[-1]) + np.repeat(words.starts - total[:-1], size)
    joined = np.append(buf, np.uint8(32))[np.minimum(at, len(buf))]
    joined[total[1:] - 1] = 32
    bounds = total[words.ptr].tolist()
    view = memoryview(joined)
    return [sha256(view[a:b]).digest() for a, b in zip(bounds, bounds[1:])]


def code_points(buf: np.ndarray) -> np.ndarray:
    """For each byte position, and the end, how many code points begin before it."""
    out = np.zeros(len(buf) + 1, np.int64)
    np.cumsum((buf & 0xC0) != 0x80, out=out[1:])
    return out
