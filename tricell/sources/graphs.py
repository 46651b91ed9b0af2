"""The graphs of FIXTURES.md: raw pairs (u, v) of each, from the given tables.

Vertices that are names, or that would clash, get ids: a name's id is its
position among the sorted names of its kind, and kinds are told apart by
id * kinds + kind, so that any engine can build the same ids.
"""

from __future__ import annotations

from collections.abc import Callable
from decimal import ROUND_HALF_UP, Decimal
from functools import reduce
from math import sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.canonical import vertex_dictionary

TEN_MINUTES = 600


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _kind(column: str | Column, kind: int, kinds: int = 3) -> Column:
    return (F.col(column) if isinstance(column, str) else column).cast("long") * kinds + kind


def _named(df: DataFrame, column: str, out: str) -> DataFrame:
    """`df` with the dictionary id of a name; dictionaries of a few names are sent by Spark's own size check."""
    ids = vertex_dictionary(df.select(F.col(column).alias("name")).where("name is not null"))
    return df.join(ids.select(F.col("name").alias(column), F.col("id").alias(out)), column)


def three_sides(rows: DataFrame, x: str, y: str, z: str) -> DataFrame:
    """Pairs of a tripartite graph of three id columns."""
    a, b, c = _kind(x, 0), _kind(y, 1), _kind(z, 2)
    pairs = F.array(F.struct(a.alias("u"), b.alias("v")), F.struct(b.alias("u"), c.alias("v")), F.struct(a.alias("u"), c.alias("v")))
    return rows.select(x, y, z).distinct().select(F.explode(pairs).alias("p")).select("p.u", "p.v").distinct()


def together(rows: DataFrame, key: list[str], member: str) -> DataFrame:
    """Pairs of members that share a key; each once, whatever the number of keys."""
    rows = rows.select(*key, F.col(member).alias("m")).where(F.col(member).isNotNull()).distinct()
    return rows.toDF(*key, "u").join(rows.toDF(*key, "v"), key).where("u < v").select("u", "v").distinct()


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(table(spark, sf_dir, "lineitem"), ["l_orderkey"], "l_partkey")


def cps_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    return line.join(orders, line.l_orderkey == orders.o_orderkey).select("o_custkey", "l_partkey", "l_suppkey").distinct()


def cps(spark: SparkSession, sf_dir: str) -> DataFrame:
    return three_sides(cps_rows(spark, sf_dir), "o_custkey", "l_partkey", "l_suppkey")


def sells_rows(spark: SparkSession, sf_dir: str, sparse: bool = False) -> DataFrame:
    line, part = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part")
    if sparse:
        line = line.where("l_returnflag = 'R' and l_quantity >= 45")
    return line.join(part, line.l_partkey == part.p_partkey).select("l_suppkey", "p_brand", "p_type").distinct()


def sells(spark: SparkSession, sf_dir: str, sparse: bool = False) -> DataFrame:
    rows = _named(_named(sells_rows(spark, sf_dir, sparse), "p_brand", "brand"), "p_type", "type")
    return three_sides(rows, "l_suppkey", "brand", "type")


def hub(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", F.ascii("l_returnflag").alias("flag"), F.ascii("l_linestatus").alias("status"))
    return three_sides(rows, "l_orderkey", "flag", "status")


def cbt(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, orders, part = (table(spark, sf_dir, n) for n in ("lineitem", "orders", "part"))
    rows = line.where("l_returnflag = 'R'").join(orders, line.l_orderkey == orders.o_orderkey).join(part, line.l_partkey == part.p_partkey)
    rows = rows.select("o_custkey", "p_brand", "p_type").distinct()
    return three_sides(_named(_named(rows, "p_brand", "brand"), "p_type", "type"), "o_custkey", "brand", "type")


def utk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "events").select("user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return three_sides(_named(rows.distinct(), "event_type", "type"), "user_id", "type", "k")


def coact(spark: SparkSession, sf_dir: str) -> DataFrame:
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    rows = table(spark, sf_dir, "events").select("event_type", F.floor(seconds / TEN_MINUTES).alias("bucket"), "user_id")
    return together(rows, ["event_type", "bucket"], "user_id")


def nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(*GROUPS["nation"](spark, sf_dir))


def cosupply(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(table(spark, sf_dir, "lineitem"), ["l_orderkey"], "l_suppkey")


def document_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.select("doc_id", F.trim("line").alias("line")).where(F.char_length("line") >= 20)


def docline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(*GROUPS["docline"](spark, sf_dir))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    return table(spark, sf_dir, "pages").select("page_id", F.explode(found).alias("href"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(*GROUPS["pages"](spark, sf_dir))


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return together(_named(page_links(spark, sf_dir).distinct(), "href", "link"), ["page_id"], "link")


#: vectors, and numbers, of one side of a block of pairs; blocks that there are at least, if each has so many vectors
VECTORS_A_BLOCK, NUMBERS_A_BLOCK = 8192, 1 << 20
LEAST_BLOCKS, LEAST_VECTORS = 8, 1024


def _score(x: np.ndarray, y: np.ndarray) -> float:
    """The cosine of two vectors rounded to 6 digits, summed in the order of their elements."""
    # plain sums: Python's own one compensates for rounding
    dot = lambda a, b: reduce(lambda s, p: s + p, (a * b).tolist(), 0.0)
    score = dot(x, y) / (sqrt(dot(x, x)) * sqrt(dot(y, y)))
    return float(Decimal(repr(score)).quantize(Decimal("1e-6"), ROUND_HALF_UP))


def _near_vectors(block: pa.Table) -> pa.Table:
    """Pairs (u, v) of a block, u < v, by a product of matrices; scores beside the threshold are computed again one by one."""
    sides = block.column("side").to_numpy()
    ids = block.column("vec_id").to_numpy()
    e = block.column("e").combine_chunks().flatten().to_numpy().reshape(len(ids), -1).astype(np.float64)
    left, right = np.flatnonzero(sides != 1), np.flatnonzero(sides != 0)
    with np.errstate(all="ignore"):
        unit = e / np.sqrt((e * e).sum(1))[:, None]
        u, v = [], []
        for at in range(0, len(left), 256):
            rows = left[at : at + 256]
            scores = unit[rows] @ unit[right].T
            # what is no number counts as the greatest one, as in SQL
            r, c = np.nonzero(~(scores < 0.2999995 - 1e-9))
            sure = ~(scores[r, c] < 0.2999995 + 1e-9)
            r, c = rows[r], right[c]
            # a block with itself has each pair both ways
            for k in np.flatnonzero(~sure & (ids[r] != ids[c])):
                sure[k] = _score(e[r[k]], e[c[k]]) >= 0.3
            sure &= (ids[r] < ids[c]) | ((sides[r] == 0) & (ids[r] > ids[c]))
            u.append(np.minimum(ids[r], ids[c])[sure])
            v.append(np.maximum(ids[r], ids[c])[sure])
    return pa.table({"u": np.concatenate(u) if u else ids[:0], "v": np.concatenate(v) if v else ids[:0]})


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors at a cosine of 0.3 or more, the score rounded to 6 digits.

    All pairs meet, as the threshold is too low for any pruning: each block of
    vectors with each other one and itself.  A vector is sent once for each
    block, so blocks are as large as a task can hold.
    """
    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long"), F.col("embedding").alias("e"))
    # floats are sent as such and become doubles where they are multiplied
    if v.schema["e"].dataType.elementType.typeName() != "float":
        v = v.withColumn("e", F.transform("e", lambda x: x.cast("double")))
    # a score with a null is null; size of a null array is -1 or null
    v = v.where("vec_id is not null and size(e) > 0").where(~F.exists("e", lambda x: x.isNull()))
    count, numbers = v.agg(F.count("*"), F.coalesce(F.sum(F.size("e")), F.lit(0))).first()
    blocks = max(1, -(-count // VECTORS_A_BLOCK), -(-numbers // NUMBERS_A_BLOCK), min(LEAST_BLOCKS, count // LEAST_VECTORS))
    own, other = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other")
    dealt = v.select("vec_id", "e", F.size("e").alias("width"), own.alias("own"), other)
    side = F.when(F.col("own") < F.col("other"), 0).when(F.col("own") > F.col("other"), 1).otherwise(2)
    dealt = dealt.select("vec_id", "e", "width", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), side.alias("side"))
    return dealt.groupBy("width", "i", "j").applyInArrow(_near_vectors, "u long, v long")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role").distinct()
    return three_sides(_named(rows, "role", "who"), "conv_id", "turn", "who")


def bipartite(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(_kind("o_custkey", 0, 2).alias("u"), _kind("o_orderkey", 1, 2).alias("v"))


def labelled_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shared-line graph on documents of good quality."""
    return together(*GROUPS["labelled_docs"](spark, sf_dir))


def good_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    good = table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return document_lines(spark, sf_dir).join(good, "doc_id", "left_semi")


def benchmark_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items that share a word of 8 characters or more."""
    words = F.split(F.lower("text"), r"\W+")
    rows = table(spark, sf_dir, "benchmark").select("item_id", F.explode(words).alias("word")).where(F.char_length("word") >= 8)
    return together(rows, ["word"], "item_id")


#: graphs of members that share a key: rows, key and member
GROUPS: dict[str, Callable[[SparkSession, str], tuple[DataFrame, list[str], str]]] = {
    "nation": lambda s, d: (table(s, d, "customer"), ["c_nationkey"], "c_custkey"),
    "docline": lambda s, d: (document_lines(s, d), ["line"], "doc_id"),
    "pages": lambda s, d: (page_links(s, d), ["href"], "page_id"),
    "labelled_docs": lambda s, d: (good_lines(s, d), ["line"], "doc_id"),
}

GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "copurchase": copurchase, "cps": cps, "sells": sells, "sells_slice": lambda s, d: sells(s, d, True), "hub": hub, "cbt": cbt, "utk": utk,
    "coact": coact, "nation": nation, "cosupply": cosupply, "docline": docline, "pages": pages, "links": links, "vec": vectors, "conv": conversations,
    "bip": bipartite, "labelled_docs": labelled_documents, "bench_docs": benchmark_words,
}
