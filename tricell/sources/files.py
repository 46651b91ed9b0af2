"""Edge files, streams of edge files, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "u long, v long"


def read_edges(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """Raw pairs (u, v) of parquet, csv, json or text ("u v" lines); schemas are given, never inferred."""
    if kind == "text":
        parts = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    return spark.read.schema(EDGE_SCHEMA).format(kind).load(path)


def stream_edges(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Raw pairs of parquet files as they arrive."""
    return spark.readStream.schema(EDGE_SCHEMA).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def write_classes(classed: DataFrame, path: str) -> None:
    """Edges laid out by colour class, so that a cell reads at most three folders."""
    classed.repartition("k_lo", "k_hi").sortWithinPartitions("lo", "hi").write.partitionBy("k_lo", "k_hi").parquet(path)


def read_cell(spark: SparkSession, path: str, cell: tuple[int, int, int]) -> DataFrame:
    """(role, lo, hi) of one cell, by partition pruning."""
    p, q, r = cell
    classes = spark.read.parquet(path)
    roles = [("tip_mid", p, q), ("tip_top", p, r), ("base", q, r)]
    parts = [classes.where((F.col("k_lo") == x) & (F.col("k_hi") == y)).select(F.lit(name).alias("role"), "lo", "hi") for name, x, y in roles]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def write_triangles(tri: DataFrame, path: str, kind: str = "parquet") -> None:
    """`noop` enumerates without storing anything."""
    writer = tri.write.format(kind)
    writer.mode("overwrite").save() if kind == "noop" else writer.save(path)


def write_bucketed(oriented: DataFrame, table: str, buckets: int = 64) -> None:
    """Oriented edges as a table bucketed and sorted by `lo`: joins on it need no shuffle."""
    oriented.write.bucketBy(buckets, "lo").sortBy("lo", "hi").mode("overwrite").saveAsTable(table)
