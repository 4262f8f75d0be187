"""Arrivals into a grid: land, verify, reorganise, publish, batch by batch.

Each micro-batch is appended under its batch id; the grid's committed list makes a repeated batch
a no-op, so a restarted stream neither loses nor doubles rows. Headers need no streaming state:
entries of batches are additive and merged when read.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from cubegrid.api import GridTable
from cubegrid.plans.planner import GridQuery
from cubegrid.plans.predicate import Range


def verify(df: DataFrame, valid: Column, keys: list[str]) -> tuple[DataFrame, DataFrame]:
    """(rows that are valid, one per key; rows set aside)."""
    ok = F.coalesce(valid, F.lit(False))
    return df.where(ok).dropDuplicates(keys), df.where(~ok)


def unseen(rows: DataFrame, grid: GridTable, keys: list[str]) -> DataFrame:
    """Rows whose keys no earlier batch brought, however long ago.

    The grid itself is the memory. Keys hold the time, so only cells between the first and the last time of
    the batch can hold a repeat: the anti-join reads these and there is no state to keep. Rows without
    a time are compared with the rows of the grid without one.
    """
    time = grid.policy.time_dim
    if time is None or time not in keys:
        raise ValueError("keys must hold the time dimension of the grid")
    stamped = rows.where(F.col(time).isNotNull())
    lo, hi = stamped.agg(F.min(time), F.max(time)).first()
    old = grid.data().where(F.col(time).isNull()).select(*keys)
    if lo is not None:
        old = old.unionByName(grid.query(GridQuery((Range.between(time, lo, hi),), select=tuple(f"`{k}`" for k in keys))))
    theirs = old.select(*[F.col(f"`{k}`").alias(f"old_{n}") for n, k in enumerate(keys)])
    same = [F.col(f"`{k}`").eqNullSafe(F.col(f"old_{n}")) for n, k in enumerate(keys)]
    return rows.join(theirs, same, "left_anti")


def stream_into_grid(arrivals: DataFrame, grid: GridTable, checkpoint: str, valid: Column, keys: list[str], quarantine: str | None = None, prepare: Callable[[DataFrame], DataFrame] | None = None, first_batch: int = 1, available_now: bool = True, files: int = 2, across_batches: bool = False) -> StreamingQuery:
    """Start appending a stream to a grid; rows that fail ``valid`` go to the quarantine folder.

    Repeats are dropped within a batch, and with ``across_batches`` against all that the grid holds. Rows that come late
    are appended like others, to their old cells, as new entries.
    """

    def publish(batch: DataFrame, batch_id: int) -> None:
        rows = prepare(batch) if prepare else batch
        good, bad = verify(rows, valid, keys)
        if quarantine:
            bad.write.mode("overwrite").parquet(f"{quarantine}/batch={batch_id}")
        if across_batches:
            good = unseen(good, grid.refresh(), keys)
        grid.append(good, first_batch + batch_id, files=files)

    writer = arrivals.writeStream.foreachBatch(publish).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def deduplicated(arrivals: DataFrame, time: str, keys: list[str], delay: str = "1 hour") -> DataFrame:
    """Drop repeats within the watermark; the time is cast, as watermarks need a zoned timestamp."""
    zoned = arrivals.withColumn(time, F.col(time).cast("timestamp"))
    return zoned.withWatermark(time, delay).dropDuplicatesWithinWatermark(keys)
