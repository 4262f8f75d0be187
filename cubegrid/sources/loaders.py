"""Tables of a folder, other file formats, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, path: str, kind: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON, text or Avro (where its package is present) behind one call."""
    if kind not in ("parquet", "orc", "csv", "json", "text", "avro"):
        raise ValueError(f"unknown format {kind}")
    reader = spark.read.format(kind).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif kind in ("csv", "json"):
        raise ValueError(f"{kind} needs a schema; guessing one would read the data twice")
    return reader.load(path)


def save(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", compression: str | None = None, partition_by: list[str] | None = None) -> None:
    """Result directory, e.g. of a join query."""
    writer = df.write.format(kind).mode(mode)
    if compression:
        writer = writer.option("compression", compression)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.save(path)


def save_jdbc(df: DataFrame, url: str, name: str, mode: str = "append", batch: int = 10_000, connections: int = 8, **properties: str) -> None:
    """Statistics into a serving database; few connections whatever the number of partitions."""
    df.coalesce(connections).write.option("batchsize", batch).jdbc(url, name, mode, properties)


def load_jdbc(spark: SparkSession, url: str, name: str, split: str | None = None, bounds: tuple[int, int] | None = None, connections: int = 8, **properties: str) -> DataFrame:
    """A table of a serving database or the archive; by ranges of a whole-number column where one is named."""
    if split is None:
        return spark.read.jdbc(url, name, properties=properties)
    if bounds is None:
        raise ValueError("bounds of the column to split by are needed")
    return spark.read.jdbc(url, name, column=split, lowerBound=bounds[0], upperBound=bounds[1], numPartitions=connections, properties=properties)


def load_table(spark: SparkSession, name: str, database: str | None = None) -> DataFrame:
    """A table of the session's catalog; its partitions, buckets and statistics are known to the optimizer."""
    full = f"{database}.{name}" if database else name
    if not spark.catalog.tableExists(full):
        raise ValueError(f"the catalog holds no table {full}")
    return spark.table(full)


def synchronise_archive(current: DataFrame, changes: DataFrame, key: str, version: str | None = None) -> DataFrame:
    """A snapshot of a reference table: rows with changes replaced, new ones added.

    Of several changes of a key the one with the greatest ``version`` counts, a column that only the changes
    have; a null key is a key like others. Applying the same changes again alters nothing.
    """
    if version is not None:
        others = [c for c in changes.columns if c != version]
        latest = F.max_by(F.struct(*[F.col(f"`{c}`") for c in others]), F.col(f"`{version}`")).alias("latest")
        changes = changes.groupBy(F.col(f"`{key}`").alias("changed")).agg(latest).select("latest.*")
    changed = changes.select(F.col(f"`{key}`").alias("changed_key")).distinct()
    return current.join(changed, F.col(f"`{key}`").eqNullSafe(F.col("changed_key")), "left_anti").unionByName(changes)
