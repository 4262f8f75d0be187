"""Construction of a grid: assign coordinates, bring each cell's rows together, write, describe."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubegrid.headers import Header
from cubegrid.policy import SplitPolicy

#: Bits of each coordinate that take part in the interleaved order.
_Z_BITS = 16
#: Rows of a Parquet page. Pages are what a read can skip, so they are kept well below a cell's rows.
PAGE_ROWS = 512


def assign_cells(df: DataFrame, policy: SplitPolicy) -> DataFrame:
    """Add the coordinate columns; a projection, no shuffle."""
    return df.withColumns({d.column: d.coord() for d in policy.dims})


def interleaved(columns: list[str], bits: int = _Z_BITS) -> Column:
    """Coordinates with their bits interleaved, lowest bit of the last column lowest."""
    bits = min(bits, 62 // len(columns))
    out = F.lit(0).cast("long")
    for b in range(bits):
        for k, c in enumerate(columns):
            bit = F.shiftright(F.coalesce(F.col(c), F.lit(0)), b).bitwiseAND(F.lit(1).cast("long"))
            out = out.bitwiseOR(F.shiftleft(bit, b * len(columns) + len(columns) - 1 - k))
    return out


def cell_order(policy: SplitPolicy, layout: str) -> list[Column]:
    """Sort keys of a layout; equal cells always stay together."""
    columns = policy.columns
    if layout == "zorder":
        return [interleaved(columns), *[F.col(c) for c in columns]]
    if layout == "time_first" and policy.time_dim:
        first = policy.dim(policy.time_dim).column
        columns = [first, *[c for c in columns if c != first]]
    elif layout not in ("lex", "time_first"):
        raise ValueError(f"unknown layout {layout}")
    return [F.col(c) for c in columns]


def reorganise(df: DataFrame, policy: SplitPolicy, path: str, files: int | None = None, layout: str = "lex", salt: int = 1, compression: str = "zstd", row_group_bytes: int | None = None, page_rows: int = PAGE_ROWS, copies: int = 1) -> None:
    """Write rows sorted by cell: a range shuffle, so a cell lies in one file unless salted.

    Of every row ``copies`` are written, made behind the shuffle and the sort: copies of a row stand side by side.

    ``salt`` above 1 lets a cell with very many rows spread over several files; its entry then has
    several segments, which readers merge.
    """
    keys = cell_order(policy, layout)
    spread = [F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in df.columns]), F.lit(salt))] if salt > 1 else []
    cells = assign_cells(df, policy)
    dealt = cells.repartitionByRange(files, *keys, *spread) if files else cells.repartitionByRange(*keys, *spread)
    rows = dealt.sortWithinPartitions(*keys)
    if copies > 1:  # a generator keeps the order of its rows
        names = rows.columns
        rows = rows.select("*", F.explode(F.array_repeat(F.lit(0), copies))).select(*[f"`{c}`" for c in names])
    writer = rows.write.option("compression", compression).option("parquet.page.row.count.limit", page_rows)
    if row_group_bytes:
        writer = writer.option("parquet.block.size", row_group_bytes)
    writer.parquet(path)


def _wide(policy: SplitPolicy) -> list:
    """Dimensions whose cells hold several ticks; of the others the coordinate says the tick."""
    return [d for d in policy.dims if not d.cut_points and (d.width_ticks > 1 or d.continuous)]


def describe_cells(data: DataFrame, policy: SplitPolicy, headers: list[Header], batch_id: int) -> DataFrame:
    """One entry per (cell, file) in stored form: header values, observed ticks, first row.

    A second narrow pass over written files, because row positions exist only then and a retried
    task must not count twice. Partial aggregation leaves about one row per file and cell. What
    follows from the rest (corner, end of the row range, ticks of unit cells) is not stored.
    """
    seen = [(f(d.ticks()) - F.any_value(F.col(d.column)) * d.width_ticks - d.origin_ticks).alias(f"off_{n}_{d.name}") for d in _wide(policy) for n, f in (("min", F.min), ("max", F.max))]
    per_cell = (
        data.select("*", F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("__row"), F.col("_metadata.file_size").alias("__size"))
        .groupBy("file", *policy.columns)
        .agg(F.count("*").alias("n"), *[h.partial().alias(h.column) for h in headers], *seen, F.min("__row").alias("row_start"), F.max("__size").alias("file_bytes"))
    )
    return per_cell.withColumn("file_rows", F.sum("n").over(Window.partitionBy("file"))).withColumn("batch_id", F.lit(batch_id).cast("long"))


def full_entries(stored: DataFrame, policy: SplitPolicy, headers: list[Header]) -> DataFrame:
    """Entries with all that follows from what is stored."""
    wide = {d.name for d in _wide(policy)}
    ticks = []
    for d in policy.dims:
        if d.cut_points:
            continue
        low = f"g_{d.name} * {d.width_ticks} + {d.origin_ticks}"
        ticks += [f"{low}{f' + off_{n}_{d.name}' if d.name in wide else ''} AS dim_{n}_{d.name}" for n in ("min", "max")]
    return stored.select(
        *policy.columns,
        policy.corner().alias("corner"),
        "n",
        *[h.column for h in headers],
        *[F.expr(t) for t in ticks],
        "file",
        "row_start",
        F.expr("row_start + n AS row_end"),
        F.expr("CAST(round(file_bytes * (n / file_rows)) AS BIGINT) AS bytes"),
        "batch_id",
    )


def locate_segments(data: DataFrame, policy: SplitPolicy) -> DataFrame:
    """file, cell and row range only."""
    return full_entries(describe_cells(data, policy, [], 0), policy, []).select("file", *policy.columns, "row_start", "row_end", "n", "bytes")


def dimension_bounds(entries: DataFrame, policy: SplitPolicy) -> DataFrame:
    """Lowest and highest coordinate of each dimension, from entries and not from rows."""
    flat = entries.agg(*[f(d.column).alias(f"{n}_{d.name}") for d in policy.dims for n, f in (("lo", F.min), ("hi", F.max))])
    each = F.array(*[F.struct(F.lit(d.name).alias("dim"), F.col(f"lo_{d.name}").alias("g_min"), F.col(f"hi_{d.name}").alias("g_max")) for d in policy.dims])
    return flat.select(F.inline(each))
