"""Cost measures: sizes, entries, times, records read, amplification, speed-up, cost model."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid import fs
from cubegrid.baselines.partitioned import DIRECTORY_BYTES


def index_bytes(spark: SparkSession, path: str) -> int:
    """Stored bytes of a catalog or index table."""
    return fs.size(spark, path)


def index_entries(entries: DataFrame, policy) -> DataFrame:
    """Cells and segments of a catalog."""
    return entries.agg(F.count_distinct(F.struct(*policy.columns)).alias("cells"), F.count("*").alias("segments"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows"))


def timed(run: Callable[[], Any], repeats: int = 3) -> tuple[float, Any]:
    """Mean seconds over repeats, and the last result."""
    spent, out = 0.0, None
    for _ in range(repeats):
        began = time.perf_counter()
        out = run()
        spent += time.perf_counter() - began
    return spent / repeats, out


def timed_query(grid, query) -> tuple[float, float]:
    """Seconds of the catalog phase (forced alone) and of the data phase."""
    plan = grid.plan(query)
    began = time.perf_counter()
    plan.stats().collect()
    index = time.perf_counter() - began
    began = time.perf_counter()
    plan.run().collect()
    return index, time.perf_counter() - began


def accurate_records(base: DataFrame, cond: Column) -> DataFrame:
    return base.where(cond).agg(F.count("*").alias("accurate"))


def selectivity(base: DataFrame, cond: Column) -> DataFrame:
    return base.agg((F.count_if(cond) / F.count("*")).alias("selectivity"))


def amplification(read: int, accurate: int) -> float | None:
    return read / accurate if accurate else None


def speedup(baseline_seconds: float, seconds: float) -> float:
    return baseline_seconds / seconds


def partition_metadata_bytes(counts: list[int]) -> int:
    """Memory for directories of every value combination: product of counts times bytes each."""
    out = DIRECTORY_BYTES
    for n in counts:
        out *= n
    return out


def flatness(seconds: dict[str, float]) -> float:
    """Slowest over fastest time across selectivities: 1 means insensitive."""
    return max(seconds.values()) / min(seconds.values())


def estimate(plan, lookup_cost: float = 1.0, row_cost: float = 0.02) -> DataFrame:
    """Modelled cost: cells looked up, plus rows read; what it reads depends on the plan's path."""
    s = plan.stats()
    rows = F.col("rows_boundary") if plan.headers else F.col("rows_related")
    return s.select((F.col("related") * lookup_cost + rows * row_cost).alias("cost"), "related", rows.alias("rows"))


def scan_footprint(df: DataFrame, folder: str = "") -> dict[str, int]:
    """Files and rows that the executed Parquet scans of a query hand out, from Spark's own plan metrics;
    only scans of files under ``folder`` where one is given."""
    df.collect()
    out = {"files": 0, "rows": 0}
    todo = [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        name = node.nodeName()
        if name.startswith("AdaptiveSparkPlan"):
            todo.append(node.executedPlan())
            continue
        if "QueryStage" in name:
            todo.append(node.plan())
            continue
        if name.startswith("Scan parquet") and folder.split(":", 1)[-1].lstrip("/") in node.relation().location().rootPaths().mkString(" "):
            for key, metric in (("files", "numFiles"), ("rows", "numOutputRows")):
                m = node.metrics().get(metric)
                if m.isDefined():
                    out[key] += m.get().value()
        kids = node.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    return out


def scan_metrics(spark: SparkSession, path: str, files: list[str] | None) -> dict[str, int]:
    """Files chosen of all files under a folder, and their bytes."""
    known = fs.list_files(spark, path)
    chosen = set(files) if files is not None else {f for f, _ in known}
    tail = {f.split(":", 1)[-1].lstrip("/") for f in chosen}
    hit = [(f, n) for f, n in known if f.split(":", 1)[-1].lstrip("/") in tail]
    return {"files": len(hit), "files_total": len(known), "bytes": sum(n for _, n in hit), "bytes_total": sum(n for _, n in known)}
