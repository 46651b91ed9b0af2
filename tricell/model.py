"""The memory model that the methods plan with, and checks of inputs."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, isqrt, log2

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class MemoryModel:
    """`m` edges fit in memory, `b` of them in a block."""

    m: int
    b: int = 64

    @classmethod
    def for_colours(cls, edges: int, colours: int, b: int = 64) -> MemoryModel:
        """The memory with which `edges` edges need `colours` colours."""
        return cls(max(1, -(-edges // colours**2)), b)

    @classmethod
    def from_session(cls, spark: SparkSession, fraction: float = 0.3, edge_bytes: int = 64) -> MemoryModel:
        """Memory as one executor core has it; a block is a row group of edges."""
        units = {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30}
        text = spark.conf.get("spark.executor.memory", "1g").lower().rstrip("b")
        size = int(text[:-1]) * units[text[-1]] if text[-1] in units else int(text)
        cores = int(spark.conf.get("spark.executor.cores", "1"))
        return cls(max(1, int(size * fraction) // (edge_bytes * cores)), 1 << 20)

    def colours(self, edges: int, power_of_two: bool = False) -> int:
        """c = ceil(sqrt(E / M)), 1 if the edges fit in memory."""
        if edges <= self.m:
            return 1
        ratio = -(-edges // self.m)
        c = isqrt(ratio - 1) + 1
        return 1 << ceil(log2(c)) if power_of_two else c

    def validate(self, edges: int, eps: float = 0.25) -> dict[str, bool]:
        """The conditions that the cost bounds assume."""
        return {"memory_below_edges": edges >= self.m, "tall_cache": self.m >= self.b**2, "polynomial_memory": self.m >= edges**eps}


def require_columns(df: DataFrame, *names: str) -> DataFrame:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing from {df.columns}")
    return df


def co_partitioned(spark: SparkSession) -> None:
    """Let joins on (key, ...) use inputs that are partitioned by the key alone.

    Cells are the partitioning key of every cell join; without this each join would deal its inputs anew.
    """
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
