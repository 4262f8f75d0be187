"""Positional indexes: per tuple of values and file, the blocks that hold it; also with counts.

A query scans the index with the conditions on its dimensions, makes the list of blocks distinct,
reads those blocks whole and filters them again. A list of few ranges of blocks is pushed to the scan, where
file names and statistics of the block column skip the rest; a longer one stays a table and is a semi-join.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid.baselines.scan import aggregate, condition
from cubegrid.headers import Agg
from cubegrid.plans.predicate import Range
from cubegrid.policy import SplitPolicy


def with_positions(spark: SparkSession, path: str, block_rows: int) -> DataFrame:
    """Rows of a Parquet folder with the file they lie in and the number of their block of rows."""
    rows = spark.read.parquet(path)
    return rows.select("*", F.col("_metadata.file_path").alias("file"), F.expr(f"_metadata.row_index div {block_rows}").alias("block"))


#: Blocks whose list the driver looks at, and ranges of neighbouring blocks that are pushed to the scan.
MOST_BLOCKS, MOST_RANGES = 10_000, 200


class CompactIndex:
    """``base`` has columns file and block; ``dims`` are the indexed columns."""

    def __init__(self, base: DataFrame, dims: list[str], policy: SplitPolicy, index: DataFrame | None = None):
        self.base, self.dims, self.policy = base, dims, policy
        self.index = index if index is not None else self.build()

    def build(self) -> DataFrame:
        """dims, file, sorted array of blocks."""
        return self.base.groupBy(*self.dims, "file").agg(F.sort_array(F.collect_set("block")).alias("blocks"))

    def blocks(self, ranges) -> DataFrame:
        usable = [r for r in ranges if r.name in self.dims]
        hits = self.index.where(condition(self.policy, usable))
        return hits.select("file", F.explode("blocks").alias("block")).distinct()

    def block_rows(self, ranges) -> DataFrame:
        """All rows of the blocks that the query touches."""
        hits = self.blocks(ranges)
        found = sorted((r.file, r.block) for r in hits.limit(MOST_BLOCKS + 1).collect())
        runs: list[list] = []
        for file, block in found:
            if runs and runs[-1][0] == file and block == runs[-1][2] + 1:
                runs[-1][2] = block
            else:
                runs.append([file, block, block])
        if len(found) > MOST_BLOCKS or len(runs) > MOST_RANGES:
            return self.base.join(hits, ["file", "block"], "left_semi")
        quoted = lambda f: "'" + f.replace("\\", "\\\\").replace("'", "\\'") + "'"
        return self.base.where(" OR ".join(f"(file = {quoted(f)} AND block BETWEEN {a} AND {b})" for f, a, b in runs) or "false")

    def rows(self, ranges, residual: str | None = None) -> DataFrame:
        return self.block_rows(ranges).where(condition(self.policy, ranges, residual))

    def query(self, ranges, aggs, group=()) -> DataFrame:
        return aggregate(self.rows(ranges), aggs, group)

    def records_read(self, ranges) -> DataFrame:
        return self.block_rows(ranges).agg(F.count("*").alias("records_read"))

    def records_read_by(self, queries: dict[str, tuple[Range, ...]]) -> DataFrame:
        """One row with a column for each of several queries: their records read, by one pass over index and base."""
        hit = {name: condition(self.policy, [r for r in ranges if r.name in self.dims]) for name, ranges in queries.items()}
        blocks = self.index.select("file", F.explode("blocks").alias("block"), *[c.alias(name) for name, c in hit.items()])
        blocks = blocks.groupBy("file", "block").agg(*[F.bool_or(name).alias(name) for name in hit])
        rows = self.base.groupBy("file", "block").agg(F.count("*").alias("__n")).join(blocks, ["file", "block"])
        return rows.agg(*[F.coalesce(F.sum(F.when(F.col(name), F.col("__n"))), F.lit(0)).alias(name) for name in hit])

    def stats(self) -> DataFrame:
        """Distinct tuples, index rows and (tuple, block) pairs: how near the index is to the table."""
        return self.index.agg(F.count_distinct(F.struct(*self.dims)).alias("tuples"), F.count("*").alias("index_rows"), F.coalesce(F.sum(F.size("blocks")), F.lit(0)).alias("tuple_blocks"))


class AggregateIndex(CompactIndex):
    """A positional index that also counts the rows of each tuple and answers counts by itself."""

    def build(self) -> DataFrame:
        return self.base.groupBy(*self.dims, "file").agg(F.sort_array(F.collect_set("block")).alias("blocks"), F.count("*").alias("cnt"))

    def applicable(self, ranges: tuple[Range, ...], aggs: tuple[Agg, ...], group: tuple[str, ...] = (), residual: str | None = None) -> tuple[bool, str]:
        outside = ({r.name for r in ranges} | set(group)) - set(self.dims)
        if outside:
            return False, f"{sorted(outside)} are not indexed"
        if residual:
            return False, "a condition outside the index"
        for a in aggs:
            if a.kind != "count" or (a.expr != "*" and a.expr not in self.dims):
                return False, f"only counts are kept, not {a.kind}({a.expr})"
        return True, ""

    def query(self, ranges, aggs, group=()) -> DataFrame:
        """Counts from the index alone; anything else by the blocks, as the positional index does."""
        if not self.applicable(ranges, aggs, group)[0]:
            return super().query(ranges, aggs, group)
        hits = self.index.where(condition(self.policy, ranges))
        outs = []
        for a in aggs:
            n = F.col("cnt") if a.expr == "*" else F.when(F.col(a.expr).isNotNull(), F.col("cnt")).otherwise(0)
            outs.append(F.coalesce(F.sum(n), F.lit(0)).alias(a.alias))
        return hits.groupBy(*group).agg(*outs) if group else hits.agg(*outs)
