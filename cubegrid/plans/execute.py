"""Pruned reading: files from the catalog, row ranges within files, and exact re-filtering."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Up to so many file names are handed to the reader by the driver; beyond, statistics in the files prune.
MAX_DRIVER_FILES = 10_000
#: A grid of so few files is opened whole: their footers cost less than a job that lists the catalog.
FEW_FILES = 16


def choose_files(cells: DataFrame, most: int = MAX_DRIVER_FILES) -> list[str] | None:
    """Distinct files of the entries, or None where they are more than the driver should list."""
    found = [r[0] for r in cells.select("file").distinct().limit(most + 1).collect()]
    return None if len(found) > most else sorted(found)


def ranges_by_file(cells: DataFrame) -> DataFrame:
    """Per file the row ranges to read, in order, adjacent ones joined: file, ranges, rows."""
    order = Window.partitionBy("file").orderBy("row_start")
    begins = F.coalesce(F.col("row_start") > F.lag("row_end").over(order), F.lit(True)).cast("int")
    runs = cells.select("file", "row_start", "row_end", begins.alias("b")).withColumn("run", F.sum("b").over(order))
    joined = runs.groupBy("file", "run").agg(F.min("row_start").alias("row_start"), F.max("row_end").alias("row_end"))
    return joined.groupBy("file").agg(F.sort_array(F.collect_list(F.struct("row_start", "row_end"))).alias("ranges"), F.sum(F.col("row_end") - F.col("row_start")).alias("rows"))


def scan_cells(plan) -> DataFrame:
    """Rows of the cells that the plan reads and that satisfy its box and residual.

    Files come from the catalog; within them plain ranges on the sorted coordinate columns reach the
    Parquet reader, which skips row groups and pages, so that little more than the row ranges of these
    cells is read. With headers in use only the rim of the box is asked for, as a union of boxes, so no
    row is counted twice; in observed mode the inner cells are no box and the rim is a semi-join.
    """
    grid, box = plan.grid, plan.box
    if box.is_empty:
        return grid.data().where("false")
    observed = plan.headers and plan.mode == "observed"
    files = None if grid.file_count <= FEW_FILES else choose_files(plan.read_cells())
    if files is not None and not files:
        return grid.data().where("false")
    terms = [box.rim_sql() if plan.headers and not observed else "true", box.rows_sql(), plan.query.residual or "true"]
    # related first: its plain ranges are pushed down whatever the rest is
    rows = grid.data(files).where(" AND ".join(f"({t})" for t in [box.related_sql(), *terms] if t != "true") or "true")
    if observed:
        keys = grid.policy.columns
        rim = plan.read_cells().select(*[F.col(c).alias(f"__{c}") for c in keys], F.col("file").alias("__file")).distinct()
        rows = rows.select("*", F.col("_metadata.file_path").alias("__path"))
        same = F.col("__path") == F.col("__file")
        for c in keys:
            same = same & F.col(c).eqNullSafe(F.col(f"__{c}"))
        rows = rows.join(rim, same, "left_semi").drop("__path")
    return rows
