"""Where a grid's entries are kept between queries: stores behind one small interface.

A store opens the stored entries of the committed segments as a DataFrame. Entries of a version never
change, so a store may keep what it has opened; a new version is opened anew.
"""

from __future__ import annotations

from typing import Protocol

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

from cubegrid import fs


class EntryStore(Protocol):
    """What a grid asks of the place its entries are looked up in."""

    def open(self, spark: SparkSession, paths: list[str], schema: StructType) -> DataFrame: ...


class ParquetEntries:
    """Entries read from Parquet by every query: sorted by coordinates, so statistics skip. For any size."""

    def open(self, spark: SparkSession, paths: list[str], schema: StructType) -> DataFrame:
        return spark.read.schema(schema).parquet(*paths)


class CachedEntries(ParquetEntries):
    """Entries held in the executors' memory (spilling to their disks) where their stored bytes are within
    ``most_bytes``; larger catalogs are read as they are. Lost executors lose nothing but time."""

    def __init__(self, most_bytes: int = 256 << 20):
        self.most_bytes = most_bytes
        self.held: dict[tuple[str, ...], DataFrame] = {}

    def open(self, spark: SparkSession, paths: list[str], schema: StructType) -> DataFrame:
        key = tuple(paths)
        if key not in self.held:
            found = super().open(spark, paths, schema)
            if sum(fs.size(spark, p) for p in paths) > self.most_bytes:
                return found
            for old in [k for k in self.held if k[0].rsplit("/", 2)[0] == paths[0].rsplit("/", 2)[0]]:
                self.held.pop(old).unpersist()
            self.held[key] = found.persist()
        return self.held[key]
