"""Stored intermediate tables, in the folder that the cluster shares."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

_temporary: list[str] = []


@atexit.register
def _clear() -> None:
    for path in _temporary:
        shutil.rmtree(path, ignore_errors=True)


def shared_folder(spark: SparkSession) -> str:
    """What spark.checkpoint.dir names; a local master without one gets a temporary folder."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    if not _temporary:
        _temporary.append(tempfile.mkdtemp(prefix="tricell-tables-"))
    return f"file://{_temporary[0]}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write `df` and read it back: cuts lineage, survives lost executors, and tells the planner its size."""
    path = f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def with_position(df: DataFrame, *order: str, name: str = "position") -> DataFrame:
    """`df` with its 0-based position in the order; every task numbers its own range."""
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    ranged = stored(ranged, "ranged").withColumn("_part", F.shiftright("_at", 33))
    counts = ranged.groupBy("_part").agg(F.count("*").alias("_n"))
    # one row a partition
    before = counts.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))
    inside = F.col("_at") - F.shiftleft(F.col("_part"), 33)
    return ranged.join(F.broadcast(before), "_part").withColumn(name, F.col("_before") + inside).drop("_at", "_part", "_before")
