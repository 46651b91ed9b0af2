"""Near-duplicate documents: banded MinHash with sequential Bayesian verification.

1. One pass over the texts gives each document its shingle set's size, the
   SHA-256 of its words, a signature and its band keys; only these are stored.
2. Documents of equal words are linked to the least id among them, so a
   group of copies costs one row from here on.
3. In each band bucket every member is compared with one pivot (the member
   that shares most buckets), first by signature: batches of positions are
   compared one after the other, and a pair is given up once the posterior
   probability that its similarity reaches the threshold falls under `miss`.
   Survivors are compared on their full sets.
4. In buckets that still hold several groups, the members outside the largest
   one are compared with all members, in blocks of bounded size: first by
   signature, each pair in the first bucket that it shares, which leaves the
   members that are in a pair not ruled out; then those members of a bucket on
   full sets.  A block holds a bounded number of shingles, names a member once
   and yields a forest of links, never all pairs.
5. Components of all links that the full sets confirm.

Signatures are made of shingle hashes; a link is made of equal bytes only.
No step emits all pairs of a group, caps a bucket or leaves candidates out.

Defined results: a null or wordless text has an empty set and no link; a row
with a null id is kept, with a null component; rows that share an id are one
node; copies of a row give equal output rows; an empty table gives no rows;
no column of the table but id and text is read, so none can clash.  A text is
scanned whole by one task.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from math import comb

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textscan as ts
from .components import connected_components
from .storage import free_name, materialise


@dataclass(frozen=True)
class NearDupConfig:
    """`percent`: least similarity of a link, in hundredths.

    With 40 bands of 5 rows a pair at similarity 0.8 shares no band with
    probability 1.3e-7; `miss` bounds what pruning may lose besides.
    """

    width: int = 5
    percent: int = 80
    rows: int = 5
    bands: int = 40
    batch: int = 40
    miss: float = 1e-7
    block: int = 512
    shingles_a_block: int = 1 << 18
    seed: int = 7

    @property
    def positions(self) -> int:
        return self.rows * self.bands


def least_matches(config: NearDupConfig) -> list[tuple[int, int]]:
    """(positions compared, matches that a pair needs to stay alive) for each batch.

    Under a uniform prior the similarity after m matches in n positions is
    Beta(m + 1, n - m + 1), whose tail above t is a binomial sum over n + 1.
    """
    t = config.percent / 100
    out = []
    for n in range(config.batch, config.positions + 1, config.batch):
        tail = 0.0
        for m in range(n + 1):
            tail += comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
            if tail >= config.miss:
                out.append((n, m))
                break
    return out


def surviving(left: np.ndarray, right: np.ndarray, steps: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """Indices of the signature pairs that no batch prunes, and their matches."""
    alive = np.arange(len(left))
    matches = np.zeros(len(left), np.int32)
    at = 0
    for n, least in steps:
        matches[alive] += (left[alive, at:n] == right[alive, at:n]).sum(1, dtype=np.int32)
        alive = alive[matches[alive] >= least]
        at = n
    return alive, matches[alive]


def _permutations(config: NearDupConfig) -> tuple[np.ndarray, np.ndarray]:
    random = np.random.Generator(np.random.PCG64(config.seed))
    factors = random.integers(1, 2**63, config.positions, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    return factors, random.integers(0, 2**63, config.positions, dtype=np.uint64)


def _minima(grams: np.ndarray, heads: np.ndarray, factors: np.ndarray, masks: np.ndarray) -> np.ndarray:
    """For each non-empty set that begins at one of `heads`, its least value under each permutation."""
    out = np.empty((len(heads), len(factors)), np.uint64)
    for k in range(len(factors)):
        out[:, k] = np.minimum.reduceat((grams ^ masks[k]) * factors[k], heads)
    return out


def _low_bits(minima: np.ndarray) -> np.ndarray:
    """16 bits of each minimum, enough to compare positions."""
    return (ts.mix(minima) & np.uint64(0xFFFF)).astype(np.uint16)


def _band_keys(low: np.ndarray, config: NearDupConfig) -> np.ndarray:
    """One key for each band of each signature, alike where the signatures are; a key's remainder by the bands is its band."""
    bands = np.arange(config.bands, dtype=np.uint64)
    keys = np.zeros((len(low), config.bands), np.uint64)
    for k in range(config.rows):
        keys = ts.mix(keys * np.uint64(3) + low[:, k :: config.rows] + bands)
    return (keys >> np.uint64(8)) * np.uint64(config.bands) + bands


def _signer(config: NearDupConfig) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ts.give_back_memory()
        factors, masks = _permutations(config)
        for batch in batches:
            for texts in ts.text_blocks(batch.column("text")):
                words = ts.scan_words(texts, folded=True)
                grams, ptr = ts.shingle_sets(words, config.width)
                n = np.diff(ptr)
                full = np.flatnonzero(n)
                minima = np.zeros((texts.rows, config.positions), np.uint64)
                if len(full):
                    minima[full] = _minima(grams, ptr[:-1][full], factors, masks)
                low = _low_bits(minima)
                keys = _band_keys(low, config)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("id").slice(texts.first, texts.rows),
                        pa.array(n.astype(np.int64)),
                        pa.array(ts.word_digests(texts, words), pa.binary()),
                        pa.ListArray.from_arrays(
                            np.arange(0, texts.rows * config.bands + 1, config.bands, dtype=np.int32), keys.view(np.int64).ravel()
                        ),
                        pa.array([r.tobytes() for r in low], pa.binary()),
                    ],
                    ["id", "n_shingles", "digest", "keys", "sig"],
                )

    return sign


_SIGNED = "id long, n_shingles long, digest binary, keys array<long>, sig binary"


def _signatures(column: pa.Array, config: NearDupConfig) -> np.ndarray:
    """The binary column as a matrix, one signature a row."""
    _, offsets, data = column.buffers()
    width = 2 * config.positions
    first = np.frombuffer(offsets, np.int32)[column.offset] if len(column) else 0
    flat = np.frombuffer(data, np.uint8, len(column) * width, first) if len(column) else np.zeros(0, np.uint8)
    return flat.view(np.uint16).reshape(len(column), config.positions)


def _pair_pruner(config: NearDupConfig):
    steps = least_matches(config)

    def prune(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep, _ = surviving(_signatures(batch.column("sig_a"), config), _signatures(batch.column("sig_b"), config), steps)
            yield batch.select(["a", "b"]).take(pa.array(keep))

    return prune


def grouped(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...]) -> Iterator[pa.Table]:
    """The runs of equal keys of a sorted stream, each as one table."""
    held: list[pa.RecordBatch] = []
    last: tuple | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        marks = np.stack([batch.column(c).to_numpy() for c in keys], 1)
        cuts = np.flatnonzero((marks[1:] != marks[:-1]).any(1)) + 1
        at = 0
        for to in [*cuts, len(marks)]:
            if held and tuple(marks[at]) != last:
                yield pa.Table.from_batches(held).combine_chunks()
                held = []
            held.append(batch.slice(at, to - at))
            last = tuple(marks[at])
            at = to
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _touching(config: NearDupConfig):
    """The rows of each block that are in a pair, of different labels, which no batch rules out.

    A pair counts in the first of the buckets that it shares, so a row comes
    back for few of its buckets, and once a block however many pairs it is in.
    """
    steps = least_matches(config)

    def touch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in grouped(batches, ("key", "i", "j")):
            labels = block.column("label").to_numpy()
            outside = block.column("outside").to_numpy(zero_copy_only=False).astype(bool)
            sigs = _signatures(block.column("sig").combine_chunks(), config)
            banded = sigs.reshape(len(sigs), config.bands, config.rows)
            band = int(block.column("key")[0].as_py()) % (1 << 64) % config.bands
            members = np.flatnonzero(~outside)
            near = np.zeros(len(labels), bool)
            for x in np.flatnonzero(outside):
                rest = members[labels[members] != labels[x]]
                kept, _ = surviving(np.broadcast_to(sigs[x], (len(rest), sigs.shape[1])), sigs[rest], steps)
                rest = rest[kept]
                rest = rest[~(banded[rest, :band] == banded[x, :band]).all(2).any(1)]
                near[rest] = True
                near[x] |= len(rest) > 0
            if near.any():
                yield block.select(["key", "rep", "label", "outside"]).filter(pa.array(near)).combine_chunks().to_batches()[0]

    return touch


def _linker(config: NearDupConfig):
    """Links between labels of each block, confirmed on full sets; no more than connect what is connected."""
    steps = least_matches(config)
    factors, masks = _permutations(config)

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in grouped(batches, ("key", "i", "j")):
            ids, labels = block.column("rep").to_numpy(), block.column("label").to_numpy()
            outside = block.column("outside").to_numpy(zero_copy_only=False).astype(bool)
            whole = block.column("text").combine_chunks()
            sets: list[np.ndarray] = []
            for texts in ts.text_blocks(whole):
                grams, ptr = ts.shingle_sets(ts.scan_words(texts, folded=True), config.width)
                sets += [grams[ptr[r] : ptr[r + 1]] for r in range(texts.rows)]
            n = np.array([len(x) for x in sets])
            full = np.flatnonzero(n)
            minima = np.zeros((len(sets), config.positions), np.uint64)
            minima[full] = _minima(np.concatenate(sets), (np.cumsum(n) - n)[full], factors, masks)
            sigs = _low_bits(minima)
            root = {int(c): int(c) for c in labels}

            def find(c: int, root: dict[int, int] = root) -> int:
                while root[c] != c:
                    root[c] = root[root[c]]
                    c = root[c]
                return c

            members = np.flatnonzero(~outside)
            found: list[tuple[int, int]] = []
            for x in np.flatnonzero(outside):
                rest = members[(labels[members] != labels[x]) & (ids[members] != ids[x])]
                kept, matches = surviving(np.broadcast_to(sigs[x], (len(rest), sigs.shape[1])), sigs[rest], steps)
                for y in rest[kept][np.argsort(-matches, kind="stable")]:
                    a, b = find(int(labels[x])), find(int(labels[y]))
                    if a != b and similar(sets[x], sets[y], config.percent) and alike(whole.take(pa.array([x, y])), config)[0]:
                        root[max(a, b)] = min(a, b)
                        found.append((int(ids[x]), int(ids[y])))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], ["a", "b"])

    return link


def similar(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sets of hashes reach the similarity; never if they share nothing."""
    if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
        return False
    both = len(np.intersect1d(x, y, True))
    return both > 0 and 100 * both >= percent * (len(x) + len(y) - both)


def alike(column: pa.Array, config: NearDupConfig) -> list[bool]:
    """Whether the first and second half of a column of texts, one by one, are similar; shingles are compared by their bytes."""
    texts = next(ts.text_blocks(column, 1 << 62))
    grams, ptr = ts.exact_shingle_sets(texts, config.width)
    n = texts.rows // 2
    return [similar(grams[ptr[r] : ptr[r + 1]], grams[ptr[n + r] : ptr[n + r + 1]], config.percent) for r in range(n)]


def _set_verifier(config: NearDupConfig):
    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            links: list[bool] = []
            a, b = batch.column("text_a"), batch.column("text_b")
            size = pc.add(pc.fill_null(pc.binary_length(a), 0), pc.fill_null(pc.binary_length(b), 0)).to_numpy()
            for low, high in ts.cuts(size):
                links += alike(pa.concat_arrays([a.slice(low, high - low), b.slice(low, high - low)]), config)
            yield batch.select(["a", "b"]).filter(pa.array(links, pa.bool_()))

    return verify


def _confirm(pairs: DataFrame, texts: DataFrame, config: NearDupConfig) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold.

    Rows of `texts` that share an id each count; a pair is a link if any of them is.
    """
    a = texts.select(F.col("id").alias("a"), F.col("text").alias("text_a"))
    b = texts.select(F.col("id").alias("b"), F.col("text").alias("text_b"))
    return pairs.join(a, "a").join(b, "b").select("a", "b", "text_a", "text_b").mapInArrow(_set_verifier(config), "a long, b long")


def _pivot_pairs(sized: DataFrame) -> DataFrame:
    """Each bucket member with the bucket's pivot, the member of most company, as (a, b), a < b."""
    company = sized.groupBy("rep").agg(F.sum("n").alias("company"))
    top = F.max(F.struct("company", (-F.col("rep")).alias("low")))
    pivots = sized.join(company, "rep").groupBy("key").agg(top.alias("top")).select("key", (-F.col("top.low")).alias("pivot"))
    # stored, so that the join below may split a bucket over many tasks
    pivots = materialise(pivots, "pivots")
    pairs = sized.join(pivots, "key").where("rep <> pivot")
    return pairs.select(F.least("rep", "pivot").alias("a"), F.greatest("rep", "pivot").alias("b")).distinct()


def _near_labels(links: DataFrame) -> DataFrame:
    """(rep, label): the least id within two links; rows with equal labels are connected."""
    both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    one = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    two = both.join(one.toDF("b", "m"), "b").groupBy("a").agg(F.min("m").alias("far"))
    return two.join(one, "a").select(F.col("a").alias("rep"), F.least("far", "m").alias("label"))


def _deal(rows: DataFrame, key: str, limit: int) -> DataFrame:
    """Rows (key, rep, label, outside, size) dealt to blocks (key, i, j) with about `limit` of each side's sizes.

    Of `ni` parts of the outsiders and `nj` of the members, each meets each.
    """
    side = lambda own: F.ceil(F.sum(F.when(own, F.col("size")).otherwise(0)) / limit).cast("int")
    parts = rows.groupBy(key).agg(side(F.col("outside")).alias("ni"), side(~F.col("outside")).alias("nj"))
    parts = materialise(parts.where("ni > 0 and nj > 0"), "parts")
    slot = F.abs(F.xxhash64("rep") % (1 << 40))
    own = F.when(F.col("outside"), slot % F.col("ni")).otherwise(slot % F.col("nj")).cast("int")
    others = F.explode(F.sequence(F.lit(0), F.when(F.col("outside"), F.col("nj")).otherwise(F.col("ni")) - 1))
    dealt = rows.join(parts, key).select(key, "rep", "label", "outside", own.alias("own"), others.alias("other"))
    return dealt.select(
        key, "rep", "label", "outside", F.when(F.col("outside"), F.col("own")).otherwise(F.col("other")).alias("i"),
        F.when(F.col("outside"), F.col("other")).otherwise(F.col("own")).alias("j"),
    )


def _in_blocks(rows: DataFrame, key: str) -> DataFrame:
    return rows.repartition(key, "i", "j").sortWithinPartitions(key, "i", "j")


def _late_links(sized: DataFrame, links: DataFrame, sigs: DataFrame, sizes: DataFrame, texts: DataFrame, config: NearDupConfig) -> DataFrame:
    """Links between members of one bucket that the pivots have left apart."""
    labels = materialise(_near_labels(links), "labels")
    named = sized.where("n > 2").join(labels, "rep", "left").select("key", "rep", F.coalesce("label", "rep").alias("label"))
    named = materialise(named, "named")
    parts = named.groupBy("key", "label").agg(F.count("*").alias("n"))
    mixed = parts.groupBy("key").agg(F.count("*").alias("k"), F.max(F.struct("n", "label")).alias("top")).where("k > 1").select("key", F.col("top.label").alias("largest"))
    rows = named.join(mixed, "key")
    outside = rows.where("label <> largest").select("key", "rep", "label", F.lit(True).alias("outside"))
    rows = outside.unionByName(rows.select("key", "rep", "label", F.lit(False).alias("outside")))
    dealt = _deal(rows.withColumn("size", F.lit(1)), "key", config.block)
    near = "key long, rep long, label long, outside boolean"
    touching = _in_blocks(dealt.join(sigs.toDF("rep", "sig"), "rep"), "key").mapInArrow(_touching(config), near).distinct()
    touching = materialise(touching, "touching")
    if touching.isEmpty():
        return links.select("a", "b").where("false")
    heavy = sizes.select(F.col("id").alias("rep"), F.greatest("n_shingles", F.lit(config.shingles_a_block // config.block)).alias("size"))
    dealt = _deal(touching.join(heavy, "rep"), "key", config.shingles_a_block)
    return _in_blocks(dealt.join(texts.toDF("rep", "text"), "rep"), "key").mapInArrow(_linker(config), "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """One row for each row of `docs`: id, n_shingles, component_id, kept.

    `kept` marks the least id of each group of linked documents.
    """
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    signed = materialise(texts.mapInArrow(_signer(config), _SIGNED), "signed")
    alive = signed.where("n_shingles > 0 and id is not null")
    # sides of joins on a key that many rows may share are stored first: then the join may split such a key
    sets = materialise(alive.groupBy("digest").agg(F.min("id").alias("rep"), F.count("*").alias("copies")), "sets")
    copies = (
        alive.select("id", "digest")
        .join(sets.where("copies > 1").select("digest", "rep"), "digest")
        .where("id <> rep")
        .select(F.col("rep").alias("a"), F.col("id").alias("b"))
    )
    reps = alive.join(sets.select(F.col("rep").alias("id")).distinct(), "id", "left_semi").select("id", "n_shingles", "keys", "sig")
    reps = materialise(reps, "reps")
    sigs = reps.select("id", "sig").dropDuplicates(["id"])
    bands = reps.select(F.col("id").alias("rep"), F.explode("keys").alias("key"))
    sizes = materialise(bands.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "bucket-sizes")
    sized = materialise(bands.join(sizes, "key"), "buckets")

    a, b = sigs.toDF("a", "sig_a"), sigs.toDF("b", "sig_b")
    compared = _pivot_pairs(sized).join(a, "a").join(b, "b").select("a", "b", "sig_a", "sig_b")
    close = compared.mapInArrow(_pair_pruner(config), "a long, b long")
    known = texts.where("id is not null")
    links = materialise(_confirm(close, known, config), "linked")
    late = _late_links(sized, links, sigs, reps.groupBy("id").agg(F.max("n_shingles").alias("n_shingles")), known, config)
    labels = connected_components(copies.unionByName(links).unionByName(late))
    component = F.coalesce("component", "id")
    return signed.select("id", "n_shingles").join(labels, "id", "left").select(
        F.col("id").alias(id_col), "n_shingles", component.alias("component_id"), F.col("id").eqNullSafe(component).alias("kept")
    )


def keep_one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", config: NearDupConfig = NearDupConfig()) -> DataFrame:
    """The rows of `docs` whose document stands for its group; of rows that share an id, one.

    Rows with a null id all stay.
    """
    verdicts = near_duplicates(docs, id_col, text_col, config).where(f"kept and {id_col} is not null").select(id_col).distinct()
    columns = docs.columns
    turn, first = Window.partitionBy(id_col).orderBy(F.col(text_col).asc_nulls_last()), free_name(docs, "turn")
    named = docs.where(F.col(id_col).isNotNull()).join(verdicts, id_col, "left_semi").withColumn(first, F.row_number().over(turn))
    return named.where(F.col(first) == 1).select(columns).unionByName(docs.where(F.col(id_col).isNull()).select(columns))
