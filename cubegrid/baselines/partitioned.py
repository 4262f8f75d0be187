"""Directory partitioning, alone and with a positional index inside each partition."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.baselines.compact import CompactIndex, with_positions
from cubegrid.baselines.scan import Scan
from cubegrid.policy import SplitPolicy

#: Bytes of the file system's memory that one directory takes.
DIRECTORY_BYTES = 150


def partition_build(df: DataFrame, keys: list[str], path: str) -> None:
    """One directory per value combination; each is written by one task."""
    df.repartition(*[F.col(k) for k in keys]).write.partitionBy(*keys).parquet(path)


class Partitioned(Scan):
    """Filters on the keys prune directories; the rest is a scan."""

    def __init__(self, spark, path: str, policy: SplitPolicy):
        super().__init__(spark.read.parquet(path), policy)


class PartitionedCompact(CompactIndex):
    """Directories by some keys, a positional index on the other dimensions in each of them."""

    def __init__(self, spark, path: str, keys: list[str], dims: list[str], policy: SplitPolicy, block_rows: int):
        self.keys = keys
        super().__init__(with_positions(spark, path, block_rows), [*keys, *dims], policy)


def directory_counts(df: DataFrame, keys: list[str]) -> DataFrame:
    """Directories that partitioning by the first 1, 2, ... keys would make, and their memory."""
    one = df.agg(*[F.count_distinct(F.struct(*keys[: k + 1])).alias(f"n{k}") for k in range(len(keys))])
    each = F.array(*[F.struct(F.lit(",".join(keys[: k + 1])).alias("keys"), F.col(f"n{k}").alias("directories"), (F.col(f"n{k}") * DIRECTORY_BYTES).alias("metadata_bytes")) for k in range(len(keys))])
    return one.select(F.inline(each))
