"""Toxicity by the nearest labelled examples, under exact TF-IDF cosine.

Fitting takes a bounded sample of labelled rows (`per_class` of each label, by
least hash of the id).  Terms are runs of letters and digits, A-Z as a-z; the
vocabulary is every term of the sample, none is left out.  Document
frequencies of that vocabulary are counted over all documents.  A term's idf
is raised, never lowered, by how firmly the sample ties it to toxic documents,
so that a few telling terms are not lost in a long text; `sharpness` 0 gives
plain TF-IDF.

A document is scored against the examples exactly.  Blocks of alike examples
hold each common term's greatest weight; a block's weights of these terms are
read only if its bounds, with what the postings of the other terms give its
examples, can reach the k-th best similarity.  Blocks that are read are
multiplied out for many documents at once in single precision; whatever comes
within its error of the k-th best is summed again in double precision, over
the examples' weights as they are held (single precision).  The neighbours
vote by 1 / (distance + softening), weighted so that the sample stands for the
classes' true shares; a monotone calibration, fitted on the examples with each
left out in turn, turns votes into scores.

The model (at most 2 * per_class sparse vectors) is all that is sent to the
executors; texts are never shuffled.

Defined results: a null, empty or unrelated text has no term and gets the rate
of such examples, or of all labels if there are none; labels with a null id or
value are passed over; of several labels of one id the greatest counts, of
several texts of one labelled id the least; without any example every score is
0; repeated rows get equal scores; an empty table gives no rows.  A text is
scanned whole by one task, at about 100 bytes of memory for each of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import cached_property
from hashlib import blake2b

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .storage import materialise


@dataclass(frozen=True)
class ToxicityConfig:
    """`per_class` bounds the labelled rows that are fitted; `threshold` is where a document counts as toxic."""

    per_class: int = 2_000
    neighbours: int = 31
    softening: float = 0.1
    sharpness: float = 1.5
    block: int = 64
    threshold: float = 0.3
    seed: int = 5


_LETTER = np.zeros(256, bool)
_LETTER[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def term_hashes(texts: ts.Texts) -> tuple[np.ndarray, np.ndarray]:
    """(row, term) of every term occurrence: the runs of letters and digits."""
    starts, ends = ts.run_bounds(_LETTER[texts.buf], texts.offsets)
    row = np.repeat(np.arange(texts.rows), np.diff(np.searchsorted(starts, texts.offsets)))
    return row, ts.run_hashes(ts.fold_case(texts.buf), starts, ends)


class Vocabulary:
    """Numbers of known terms; a table on the leading bits of their hashes leads to each."""

    def __init__(self, terms: np.ndarray):
        self.terms = np.unique(terms)
        self._shift = np.uint64(64 - max(1, int(2 * len(self.terms) + 1).bit_length()))
        self._from = np.searchsorted(self.terms, np.arange((1 << (64 - int(self._shift))) + 1, dtype=np.uint64)[:-1] << self._shift).astype(np.int32)

    def __len__(self) -> int:
        return len(self.terms)

    def numbers(self, term: np.ndarray) -> np.ndarray:
        """The number of each term, -1 for an unknown one."""
        out = np.full(len(term), -1, np.int32)
        if not len(self.terms):
            return out
        at = self._from[term >> self._shift]
        left = np.flatnonzero(at < len(self.terms))
        while len(left):
            found, wanted = self.terms[at[left]], term[left]
            out[left[found == wanted]] = at[left[found == wanted]]
            left = left[found < wanted]
            at[left] += 1
            left = left[at[left] < len(self.terms)]
        return out


def vectors(texts: ts.Texts, vocabulary: Vocabulary) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, term, count) of the vocabulary's terms in each text, in this order."""
    row, term = term_hashes(texts)
    number = vocabulary.numbers(term)
    hit = number >= 0
    keys, counts = np.unique(row[hit] * max(len(vocabulary), 1) + number[hit], return_counts=True)
    return keys // max(len(vocabulary), 1), keys % max(len(vocabulary), 1), counts


def _slices(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The positions starts[0]:ends[0], starts[1]:ends[1] and so on, one after the other."""
    n = ends - starts
    return np.arange(n.sum()) + np.repeat(starts - (np.cumsum(n) - n), n)


class BlockMaxIndex:
    """Unit vectors of examples by term, with the greatest weight of each common term in each block of examples.

    `read` counts the blocks whose common weights were read for a document, `skipped` those that bounds ruled out.
    """

    #: terms of the most examples, which are bounded by blocks and held densely
    common = 512
    #: blocks that are visited before any bound is compared
    first = 4
    #: documents that are searched at once
    batch = 128
    #: more than the rounding errors of single precision
    slack = 1e-5

    def __init__(self, n_terms: int, example: np.ndarray, term: np.ndarray, weight: np.ndarray, block: int):
        self.block, self.read, self.skipped = block, 0, 0
        self.n = int(example.max()) + 1 if len(example) else 0
        self.n_terms = n_terms
        if ((example[1:] < example[:-1]) | ((example[1:] == example[:-1]) & (term[1:] <= term[:-1]))).any():
            order = np.lexsort((term, example))
            example, term, weight = example[order], term[order], weight[order]
        ptr = np.searchsorted(example, np.arange(self.n + 1, dtype=example.dtype))
        held = np.zeros(n_terms, np.int64)
        for low in range(0, len(term), 1 << 20):
            np.add.at(held, term[low : low + (1 << 20)], 1)
        top = np.argsort(-held, kind="stable")[: self.common]
        self.rank = np.full(n_terms, -1, np.int32)
        self.rank[top] = np.arange(len(top))
        blocks = -(-self.n // block)
        self.dense = np.zeros((blocks * block, len(top)), weight.dtype)
        for e in range(self.n):
            own = slice(ptr[e], ptr[e + 1])
            rank = self.rank[term[own]]
            self.dense[e, rank[rank >= 0]] = weight[own][rank >= 0]
        # alike examples share blocks: sorted by their signs along the main directions
        self.example_at = np.arange(self.n)
        if blocks > 1:
            most = self.dense[: self.n, :256]
            main = np.linalg.eigh(most.T @ most)[1][:, ::-1][:, 1:9]
            self.example_at = np.lexsort(((most @ main) > 0).T[::-1])
            self.dense[: self.n] = self.dense[self.example_at]
        self.at = np.argsort(self.example_at).astype(np.int32)
        self.most = self.dense.reshape(blocks, block, len(top)).max(1, initial=0).T.copy()
        held[top] = 0
        self.post_ptr = np.concatenate([[0], np.cumsum(held)])
        self.post_at, self.post_weight = np.empty(self.post_ptr[-1], np.int32), np.empty(self.post_ptr[-1], weight.dtype)
        free = self.post_ptr[:-1].copy()
        # some examples at a time: what is sorted stays small beside the index
        for low in range(0, self.n, 1024):
            part = slice(ptr[low], ptr[min(low + 1024, self.n)])
            t, w, e = term[part], weight[part], np.repeat(self.at[low : low + 1024], np.diff(ptr[low : low + 1025]))
            order = np.argsort(t, kind="stable")
            order = order[self.rank[t[order]] < 0]
            found, n = np.unique(t[order], return_counts=True)
            to = _slices(free[found], free[found] + n)
            self.post_at[to], self.post_weight[to] = e[order], w[order]
            free[found] += n

    def nearest(self, terms: np.ndarray, weights: np.ndarray, k: int, without: int = -1) -> list[tuple[float, int]]:
        """The k examples of greatest cosine over 0, ties by least number."""
        return self.nearest_of_each(np.array([0, len(terms)]), terms, weights, k, [without])[0]

    def nearest_of_each(self, ptr: np.ndarray, terms: np.ndarray, weights: np.ndarray, k: int, without: list[int] | None = None) -> list[list[tuple[float, int]]]:
        """`nearest` for each document; number d has the terms ptr[d]:ptr[d + 1]."""
        found: list[list[tuple[float, int]]] = []
        for low in range(0, len(ptr) - 1, self.batch):
            part = ptr[low : low + self.batch + 1]
            cut = slice(part[0], part[-1])
            found += self._search(part - part[0], terms[cut], weights[cut], k, without[low : low + self.batch] if without else [-1] * (len(part) - 1))
        return found

    def _search(self, ptr: np.ndarray, terms: np.ndarray, weights: np.ndarray, k: int, without: list[int]) -> list[list[tuple[float, int]]]:
        docs, width = len(ptr) - 1, len(self.dense)
        if not self.n:
            return [[] for _ in range(docs)]
        row, rank = np.repeat(np.arange(docs), np.diff(ptr)), self.rank[terms]
        query = np.zeros((docs, self.dense.shape[1]))
        query[row[rank >= 0], rank[rank >= 0]] = weights[rank >= 0]
        exact = np.zeros((docs, width))
        for d in range(docs):
            own = slice(ptr[d], ptr[d + 1])
            rare = rank[own] < 0
            t = terms[own][rare]
            to = _slices(self.post_ptr[t], self.post_ptr[t + 1])
            w = np.repeat(weights[own][rare], self.post_ptr[t + 1] - self.post_ptr[t])
            exact[d] = np.bincount(self.post_at[to], weights=w * self.post_weight[to], minlength=width)
        got, near = exact.astype(np.float32), query.astype(np.float32)
        blocked = got.reshape(docs, -1, self.block)
        bound = near @ self.most + blocked.max(2)
        order = np.argsort(-bound, 1, kind="stable")
        new, visited = np.zeros(bound.shape, bool), np.zeros(bound.shape, bool)
        np.put_along_axis(new, order[:, : self.first], True, 1)
        hidden = [(d, self.at[e]) for d, e in enumerate(without) if e >= 0]
        for last in (False, True):
            for b in np.flatnonzero(new.any(0)):
                d = np.flatnonzero(new[:, b])
                blocked[d, b] += near[d] @ self.dense[b * self.block : (b + 1) * self.block].T
            visited |= new
            for d, at in hidden:
                got[d, at] = 0
            seen = np.where(visited[:, :, None], blocked, 0).reshape(docs, width)
            least = np.partition(seen, -k, 1)[:, -k] if width >= k else np.zeros(docs, np.float32)
            if not last:
                new = ~visited & (bound >= least[:, None] - self.slack) & (bound > 0)
        self.read += int(visited.sum())
        self.skipped += int((~visited).sum())
        out = []
        for d in range(docs):
            at = np.flatnonzero((seen[d] >= least[d] - self.slack) & (seen[d] > 0))
            e = self.example_at[at]
            score = np.round(exact[d, at] + self.dense[at] @ query[d], 9)
            best = np.lexsort((e, -score))
            out.append([(float(score[i]), int(e[i])) for i in best[score[best] > 0][:k]])
        return out


@dataclass
class ToxicityModel:
    """Example e has the terms ptr[e]:ptr[e + 1]; the index over them is built where it is first used."""

    config: ToxicityConfig
    terms: np.ndarray
    scale: np.ndarray
    ids: np.ndarray
    toxic: np.ndarray
    share: np.ndarray
    ptr: np.ndarray
    term: np.ndarray
    count: np.ndarray
    plain_rate: float
    steps: tuple[np.ndarray, np.ndarray] = field(default_factory=lambda: (np.zeros(0), np.zeros(0)))
    #: the model as the executors hold it, without the steps
    sent: Broadcast | None = None

    @cached_property
    def vocabulary(self) -> Vocabulary:
        return Vocabulary(self.terms)

    @cached_property
    def index(self) -> BlockMaxIndex:
        example = np.repeat(np.arange(len(self.ids), dtype=np.int32), np.diff(self.ptr))
        weight = np.empty(len(self.term), np.float32)
        for low in range(0, len(self.ids), 1024):
            ptr = self.ptr[low : low + 1025]
            part = slice(ptr[0], ptr[-1])
            weight[part] = self.units(ptr - ptr[0], self.term[part], self.count[part])
        return BlockMaxIndex(len(self.terms), example, self.term, weight, self.config.block)

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("vocabulary", "index", "sent")} | {"sent": None}

    def units(self, ptr: np.ndarray, terms: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Weights that give each document of one term or more a vector of length 1."""
        w = (1 + np.log(counts, dtype=np.float64)) * self.scale[terms]
        row = np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))
        return w / np.sqrt(np.bincount(row, weights=w * w, minlength=len(ptr) - 1))[row]

    def vote(self, near: list[tuple[float, int]]) -> float:
        weight = toxic = 0.0
        for similarity, e in near:
            w = self.share[e] / (1 - min(similarity, 1.0) + self.config.softening)
            weight += w
            toxic += w * self.toxic[e]
        return toxic / weight if weight else self.plain_rate

    def score(self, ptr: np.ndarray, terms: np.ndarray, counts: np.ndarray, without: list[int] | None = None) -> list[tuple[float, list[tuple[float, int]]]]:
        """(score, neighbours) of each document; number d has the terms ptr[d]:ptr[d + 1]."""
        out = []
        for near in self.index.nearest_of_each(ptr, terms, self.units(ptr, terms, counts), self.config.neighbours, without):
            raw = self.vote(near)
            if near and len(self.steps[0]):
                raw = float(np.interp(raw, *self.steps))
            out.append((raw, near))
        return out


def firmness(term: np.ndarray, toxic: np.ndarray, n_terms: int, labels: np.ndarray) -> np.ndarray:
    """Each term's log odds ratio between toxic and other examples in standard errors, with half an example added to each.

    `term` and `toxic` have an entry for each term of each example, `labels` one for each example.
    """
    p = np.bincount(term, weights=toxic, minlength=n_terms) + 0.5
    n = np.bincount(term, minlength=n_terms) - p + 1.0
    odds = np.log(p / (labels.sum() + 1 - p)) - np.log(n / ((labels == 0).sum() + 1 - n))
    return odds / np.sqrt(1 / p + 1 / n)


def monotone(raw: np.ndarray, truth: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators: points of a rising calibration curve."""
    pools: list[list[float]] = []
    for i in np.argsort(raw, kind="stable"):
        pools.append([raw[i] * weight[i], truth[i] * weight[i], weight[i]])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], last, strict=True)]
    return np.array([p[0] / p[2] for p in pools]), np.array([p[1] / p[2] for p in pools])


def _distinct_terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for texts in ts.text_blocks(batch.column("text")):
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(term_hashes(texts)[1]).view(np.int64))], ["term"])


def _vector_rows(vocabulary: Broadcast):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Vocabulary(vocabulary.value)
        for batch in batches:
            for texts in ts.text_blocks(batch.column("text")):
                row, term, count = vectors(texts, known)
                ptr = np.searchsorted(row, np.arange(texts.rows + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("id").slice(texts.first, texts.rows),
                        batch.column("label").slice(texts.first, texts.rows),
                        pa.ListArray.from_arrays(ptr, pa.array(term.astype(np.int32))),
                        pa.ListArray.from_arrays(ptr, pa.array(count.astype(np.int32))),
                    ],
                    ["id", "label", "terms", "counts"],
                )

    return make


def _frequencies(vocabulary: Broadcast):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Vocabulary(vocabulary.value)
        total, held = 0, np.zeros(len(known), np.int64)
        for batch in batches:
            total += batch.num_rows
            for texts in ts.text_blocks(batch.column("text")):
                held += np.bincount(vectors(texts, known)[1], minlength=len(known))
        hit = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(hit, -1)), pa.array(np.append(held[hit], total))], ["term", "n"])

    return count


def _votes(model: Broadcast):
    """The vote on each example by the others."""

    def vote(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for batch in batches:
            e = batch.column("e").to_numpy()
            ptr = np.concatenate([[0], np.cumsum(m.ptr[e + 1] - m.ptr[e])])
            at = _slices(m.ptr[e], m.ptr[e + 1])
            raw = [s for s, _ in m.score(ptr, m.term[at], m.count[at], e.tolist())]
            yield pa.RecordBatch.from_arrays([pa.array(e), pa.array(raw, pa.float64())], ["e", "raw"])

    return vote


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", config: ToxicityConfig = ToxicityConfig()) -> ToxicityModel:
    """`labels` holds the rows that may be learnt from; all of `docs` counts for document frequencies."""
    spark = docs.sparkSession
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    usable = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label in (0, 1)")
    usable = usable.groupBy("id").agg(F.max("label").alias("label"))
    sizes = {r.label: r.n for r in usable.groupBy("label").agg(F.count("*").alias("n")).collect()}
    turn = F.xxhash64(F.lit(config.seed), F.col("id"))
    picked = [r for value in (0, 1) for r in usable.where(F.col("label") == value).orderBy(turn, "id").limit(config.per_class).collect()]
    none = np.zeros(0, np.int64)
    if not picked:
        return ToxicityModel(config, none.view(np.uint64), np.zeros(0), none, np.zeros(0), np.zeros(0), np.zeros(1, np.int64), none, none, 0.0)
    # at most 2 * per_class rows of two numbers, and one text of each id
    chosen = F.broadcast(spark.createDataFrame([(r.id, r.label) for r in picked], "id long, label int"))
    sample = materialise(texts.join(chosen, "id").groupBy("id", "label").agg(F.min("text").alias("text")), "examples")
    taken = {v: sum(r.label == v for r in picked) for v in (0, 1)}
    share_of = {v: sizes.get(v, 0) / max(taken[v], 1) for v in (0, 1)}
    terms = np.sort(sample.mapInArrow(_distinct_terms, "term long").distinct().toArrow().column("term").to_numpy().view(np.uint64))
    sent = spark.sparkContext.broadcast(terms)

    found = texts.mapInArrow(_frequencies(sent), "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    held = np.zeros(len(terms) + 1, np.int64)
    held[found.column("term").to_numpy()] = found.column("n").to_numpy()
    del found
    rows = sample.mapInArrow(_vector_rows(sent), "id long, label int, terms array<int>, counts array<int>").toArrow().sort_by("id").combine_chunks()
    label, size = rows.column("label").to_numpy().astype(float), pc.list_value_length(rows.column("terms")).to_numpy()
    share = np.where(label == 1, share_of[1], share_of[0])
    plain = size == 0
    rate = float((share * label)[plain].sum() / share[plain].sum()) if plain.any() else sizes.get(1, 0) / sum(sizes.values())
    term, count = (pc.list_flatten(rows.column(c)).to_numpy() for c in ("terms", "counts"))
    # no count is cut: the type is the least that holds them all
    count = count.astype(np.min_scalar_type(int(count.max(initial=0))))
    ids = rows.column("id").to_numpy()
    del rows
    sent.destroy()
    scale = (np.log((held[-1] + 1) / (held[:-1] + 1)) + 1) * (1 + np.maximum(firmness(term, np.repeat(label, size), len(terms), label), 0)) ** config.sharpness
    model = ToxicityModel(config, terms, scale, ids[~plain], label[~plain], share[~plain], np.concatenate([[0], np.cumsum(size[~plain])]), term, count, rate)
    if len(model.ids):
        drawn = spark.range(len(model.ids)).select(F.col("id").alias("e")).repartition(-(-len(model.ids) // 512))
        model.sent = spark.sparkContext.broadcast(model)
        votes = drawn.mapInArrow(_votes(model.sent), "e long, raw double").toArrow().sort_by("e")
        model.steps = monotone(votes.column("raw").to_numpy(), model.toxic, model.share)
    return model


def _scorer(sent: Broadcast, steps: tuple[np.ndarray, np.ndarray], text_col: str, kept: list[str], evidence: bool):
    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = replace(sent.value, steps=steps)
        model.__dict__ |= {"vocabulary": sent.value.vocabulary, "index": sent.value.index}
        known: dict[bytes, tuple] = {}
        for batch in batches:
            for texts in ts.text_blocks(batch.column(text_col)):
                row, term, count = vectors(texts, model.vocabulary)
                ptr = np.searchsorted(row, np.arange(texts.rows + 1))
                scores, near = np.full(texts.rows, model.plain_rate), [[] for _ in range(texts.rows)]
                if len(known) > 20_000:
                    known.clear()
                keys = {r: blake2b(term[ptr[r] : ptr[r + 1]].tobytes() + count[ptr[r] : ptr[r + 1]].tobytes(), digest_size=16).digest() for r in np.flatnonzero(np.diff(ptr))}
                new = {key: r for r, key in keys.items() if key not in known}
                rows = np.array([*new.values()], int)
                at = _slices(ptr[rows], ptr[rows + 1])
                found = model.score(np.concatenate([[0], np.cumsum(ptr[rows + 1] - ptr[rows])]), term[at], count[at])
                known |= zip(new, found if evidence else [(s, ()) for s, _ in found], strict=True)
                del found
                for r, key in keys.items():
                    scores[r], near[r] = known[key]
                columns = [batch.column(c).slice(texts.first, texts.rows) for c in kept] + [pa.array(scores)]
                if evidence:
                    columns.append(pa.array([[{"example": int(model.ids[e]), "similarity": s, "toxic": int(model.toxic[e])} for s, e in x] for x in near], _EVIDENCE))
                yield pa.RecordBatch.from_arrays(columns, [*kept, "toxicity"] + ["evidence"] * evidence)
        known.clear()
        ts.give_back_memory()

    return score


_EVIDENCE = pa.list_(pa.struct([("example", pa.int64()), ("similarity", pa.float64()), ("toxic", pa.int32())]))


def score_documents(docs: DataFrame, model: ToxicityModel, text_col: str = "text", keep: list[str] | None = None, evidence: bool = False) -> DataFrame:
    """Columns `keep` of `docs` (all by default) with toxicity and, if asked, the neighbours as evidence.

    Columns of `docs` named toxicity or evidence give way.
    """
    keep = [c for c in (docs.columns if keep is None else keep) if c not in ("toxicity", "evidence")]
    needed = docs.select(*dict.fromkeys([*keep, text_col]))
    fields = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep] + ["toxicity double"]
    if evidence:
        fields.append("evidence array<struct<example: bigint, similarity: double, toxic: int>>")
    sent = model.sent or docs.sparkSession.sparkContext.broadcast(model)
    return needed.mapInArrow(_scorer(sent, model.steps, text_col, keep, evidence), ", ".join(fields))
