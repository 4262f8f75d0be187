"""Windowed statistics of a stream of readings, and a detector of missing readings."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from cubegrid import fs
from cubegrid.registry import Registry
from cubegrid.sources.loaders import table

query = Registry()


def tumbling(rows: DataFrame, time: str = "ts", length: str = "15 minutes", delay: str = "1 hour") -> DataFrame:
    """Readings per collection period and type; late rows beyond the watermark are left out."""
    zoned = rows.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, delay)
    w = F.window(time, length)
    return zoned.groupBy(w, "event_type").agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(rows: DataFrame, time: str = "ts", length: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return rows.groupBy(F.window(time, length, slide)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(rows: DataFrame, by: str = "user_id", time: str = "ts", gap: str = "6 hours") -> DataFrame:
    return rows.groupBy(by, F.session_window(time, gap)).agg(F.count("*").alias("n")).select(by, F.col("session_window.start").alias("start"), "n")


def gaps(rows: DataFrame, by: str = "user_id", time: str = "ts", longest_seconds: int = 86400, delay: str = "1 hour") -> DataFrame:
    """Streaming detector: (by, last_seen, seconds) whenever a reading comes later than allowed.

    State is one time per key; batches may bring rows of a key in any order.
    """
    zoned = rows.select(F.col(by).cast("long").alias("k"), F.col(time).cast("timestamp").alias("t")).withWatermark("t", delay)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        times = pd.concat([b["t"] for b in batches]).sort_values()
        seen = [state.get[0]] if state.exists else []
        micros = seen + [int(x.value // 1000) for x in times]
        micros.sort()
        late = [(a, (b - a) // 10**6) for a, b in zip(micros, micros[1:], strict=False) if b - a > longest_seconds * 10**6]
        state.update((micros[-1],))
        if late:
            yield pd.DataFrame({by: [key[0]] * len(late), "last_seen": [pd.Timestamp(a, unit="us") for a, _ in late], "seconds": [x for _, x in late]})

    return zoned.groupBy("k").applyInPandasWithState(step, f"{by} long, last_seen timestamp, seconds long", "last long", "append", GroupStateTimeout.NoTimeout)


def silent(rows: DataFrame, by: str = "user_id", time: str = "ts", longest_seconds: int = 86400, delay: str = "1 hour") -> DataFrame:
    """Streaming detector: (by, last_seen) once no reading has come for too long, by the watermark.

    ``gaps`` needs a next reading to see that one was missing; this reports a key that may never send again.
    A key that falls silent again is reported again; one whose next reading comes in the very batch that would
    report it is left to ``gaps``. State is one time per key and goes with the report.
    """
    zoned = rows.select(F.col(by).cast("long").alias("k"), F.col(time).cast("timestamp").alias("t")).where("t IS NOT NULL").withWatermark("t", delay)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            (last,) = state.get
            state.remove()
            yield pd.DataFrame({by: [key[0]], "last_seen": [pd.Timestamp(last, unit="us")]})
            return
        last = max([int(b["t"].max().value // 1000) for b in batches] + ([state.get[0]] if state.exists else []))
        state.update((last,))
        # a time that the watermark has passed already is reported by the next batch
        state.setTimeoutTimestamp(max(last // 1000 + longest_seconds * 1000, state.getCurrentWatermarkMs() + 1))

    return zoned.groupBy("k").applyInPandasWithState(step, f"{by} long, last_seen timestamp", "last long", "append", GroupStateTimeout.EventTimeTimeout)


def replay(spark, path: str, name: str, make, mode: str = "complete") -> DataFrame:
    """Run a streaming plan over the files of a folder to its end and return what it wrote."""
    schema = spark.read.parquet(path).schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)
    if mode == "complete":
        out = fs.scratch(spark, name)

        def keep(batch: DataFrame, batch_id: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/result")

        q = make(source).writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.parquet(f"{out}/result")
    out = fs.scratch(spark, name)
    q = make(source).writeStream.outputMode(mode).format("parquet").option("path", f"{out}/result").option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{out}/result")


def _landing(spark, sf_dir: str) -> str:
    """Events as a folder of files in time order, as they would land."""
    path = fs.scratch(spark, "landing")
    events = table(spark, sf_dir, "events")
    lo, hi = events.agg(F.min("event_id"), F.max("event_id")).first()
    step = (hi - lo) // 3 + 1
    for k in range(3):  # one after the other: a file source takes files by their age
        part = events.where(F.col("event_id").between(lo + k * step, lo + (k + 1) * step - 1))
        part.coalesce(1).sortWithinPartitions("event_id").write.mode("append").parquet(path)
    return path


_TUMBLING = "SELECT time_bucket(INTERVAL 15 MINUTE, ts) AS start, event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events GROUP BY ALL"


@query("stream_tumbling", _TUMBLING)
def stream_tumbling(s, d):
    """Streamed windows, run to the end of the input."""
    got = replay(s, _landing(s, d), "tumbling", tumbling)
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.col("total").cast("double").alias("total"))


@query("batch_tumbling", _TUMBLING)
def batch_tumbling(s, d):
    """The same windows over the stored table."""
    got = tumbling(table(s, d, "events"))
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.col("total").cast("double").alias("total"))


@query("win_sliding", "SELECT b + INTERVAL (6 * k) HOUR AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 18 HOUR AS b FROM events), (SELECT unnest([0, 1, 2, 3]) AS k) GROUP BY ALL")
def win_sliding(s, d):
    return sliding(table(s, d, "events")).select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("win_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def win_session(s, d):
    return sessions(table(s, d, "events")).select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_gaps", "SELECT user_id, last_seen, CAST(epoch_us(ts) - epoch_us(last_seen) AS BIGINT) // 1000000 AS seconds FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS last_seen FROM events) WHERE epoch_us(ts) - epoch_us(last_seen) > 86400000000")
def stream_gaps(s, d):
    """Missing readings found by per-key state over a stream."""
    got = replay(s, _landing(s, d), "gaps", gaps, mode="append")
    return got.select("user_id", F.col("last_seen").cast("timestamp_ntz").alias("last_seen"), "seconds")


@query("stream_silent", "SELECT user_id, max(ts) AS last_seen FROM events GROUP BY user_id HAVING max(ts) + INTERVAL 1 DAY < (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def stream_silent(s, d):
    """Keys that are silent when the stream ends; earlier silences are those that ``stream_gaps`` reports."""
    found = replay(s, _landing(s, d), "silent", silent, mode="append")
    last = found.groupBy("user_id").agg(F.max("last_seen").cast("timestamp_ntz").alias("last_seen"))
    seen = table(s, d, "events").groupBy("user_id").agg(F.max("ts").cast("timestamp_ntz").alias("last_seen"))
    return last.join(seen, ["user_id", "last_seen"], "left_semi").select("user_id", "last_seen")


@query("stream_grid_ingest", "SELECT user_id // 10 AS g_user_id, CAST(CAST(ts AS DATE) - DATE '2024-01-01' AS BIGINT) AS g_day, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events GROUP BY ALL")
def stream_grid_ingest(s, d):
    """A grid fed by a stream of files has the cells of one built at once."""
    from datetime import date

    from cubegrid.api import GridTable
    from cubegrid.headers import Header
    from cubegrid.policy import Dim, SplitPolicy
    from cubegrid.streaming.ingest import stream_into_grid

    rows = table(s, d, "events").select("event_id", "user_id", F.to_date("ts").alias("day"), F.col("value").cast("decimal(18,2)").alias("power"))
    policy = SplitPolicy([Dim("user_id", 0, 10), Dim("day", date(2024, 1, 1), 1, "d")], "day")
    grid = GridTable.create(rows.limit(0), fs.scratch(s, "stream-grid"), policy, [Header.sum("power", "total")], files=1)
    path = _landing(s, d)
    source = s.readStream.schema(s.read.parquet(path).schema).option("maxFilesPerTrigger", 1).parquet(path)
    shape = lambda b: b.select("event_id", "user_id", F.to_date("ts").alias("day"), F.col("value").cast("decimal(18,2)").alias("power"))
    q = stream_into_grid(source, grid, fs.scratch(s, "stream-checkpoint"), F.col("power").isNotNull(), ["event_id"], prepare=shape)
    q.awaitTermination()
    cells = GridTable.open(s, grid.path).cells()
    return cells.select("g_user_id", "g_day", "n", F.col("h_total").cast("double").alias("total"))
