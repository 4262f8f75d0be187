"""Sharded row store: rows hashed by one key over nodes, again over chunks of a node, each chunk with a
compound index.

A node is a bucket of the table and a chunk a directory, so a value of the key is one file of one node;
within a file the rows are sorted by the index columns and lie in small pages whose statistics serve
ranges on the leading ones. Users are dealt over the same nodes, whole, and join without a shuffle.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid import fs
from cubegrid.baselines.scan import Scan, aggregate
from cubegrid.build import PAGE_ROWS
from cubegrid.policy import SplitPolicy


def _node(key: str, nodes: int) -> Column:
    """The bucket that Spark's own bucketing gives a key."""
    return F.pmod(F.hash(key), F.lit(nodes))


def _chunk(value: Column, chunks: int) -> Column:
    """A hash that does not follow the first, or every node would fill a few chunks only."""
    return F.pmod(F.xxhash64(value), F.lit(chunks)).cast("int")


def _bucketed(df: DataFrame, key: str, sort: list[str], nodes: int, path: str, by: list[str] = ()) -> str:
    name = f"shards_{uuid.uuid4().hex[:12]}"
    writer = df.write.bucketBy(nodes, key).sortBy(*sort).option("path", path).option("parquet.page.row.count.limit", PAGE_ROWS)
    (writer.partitionBy(*by) if by else writer).saveAsTable(name)
    return name


class ShardedStore(Scan):
    def __init__(self, facts: DataFrame, users: DataFrame | None, key: str, index: list[str], policy: SplitPolicy, nodes: int = 4, chunks: int = 2, user_key: str | None = None):
        self.spark: SparkSession = facts.sparkSession
        self.key, self.nodes, self.chunks = key, nodes, chunks
        self.chunk = next(c for c in ("chunk", *(f"chunk_{k}" for k in range(len(facts.columns) + 1))) if c not in facts.columns)
        dealt = facts.withColumn(self.chunk, _chunk(F.col(key), chunks))
        # one task a chunk: each writes one sorted file
        dealt = dealt.repartitionById(nodes * chunks, (_node(key, nodes) * chunks + F.col(self.chunk)).cast("int"))
        self.path = fs.scratch(self.spark, "shards")
        self.stored = self.spark.table(_bucketed(dealt, key, index, nodes, self.path, [self.chunk]))
        super().__init__(self.stored.drop(self.chunk), policy)
        self.users = None
        if users is not None:
            own = user_key or key
            self.users = self.spark.table(_bucketed(users.repartitionById(nodes, _node(own, nodes).cast("int")), own, [own], nodes, fs.scratch(self.spark, "shard-users")))

    def _pinned(self, ranges) -> int | None:
        """The one whole number that the ranges leave the key, if they do."""
        lo = [r.lo + (not r.lo_closed) for r in ranges if r.name == self.key and isinstance(r.lo, int)]
        hi = [r.hi - (not r.hi_closed) for r in ranges if r.name == self.key and isinstance(r.hi, int)]
        return max(lo) if lo and hi and max(lo) == min(hi) else None

    def rows(self, ranges, residual: str | None = None) -> DataFrame:
        """Rows of a box; a condition that leaves one key opens one chunk of one node."""
        rows, value = self.stored, self._pinned(ranges)
        if value is not None:
            same = F.lit(value).cast(rows.schema[self.key].dataType)
            rows = rows.where((F.col(self.key) == same) & (F.col(self.chunk) == _chunk(same, self.chunks)))
        return Scan(rows, self.policy).rows(ranges, residual).drop(self.chunk)

    def query(self, ranges, aggs, group=()) -> DataFrame:
        """The filter and a partial aggregate run in every shard; partials are merged once."""
        return aggregate(self.rows(ranges), aggs, group)

    def join_users(self, ranges, on: str | None = None) -> DataFrame:
        """Facts with their users, node by node."""
        return self.rows(ranges).hint("merge").join(self.users, on or self.key)

    def shard_sizes(self) -> DataFrame:
        """Rows of every chunk of every node."""
        return self.stored.groupBy(_node(self.key, self.nodes).alias("node"), F.col(self.chunk).alias("chunk")).agg(F.count("*").alias("n"))
