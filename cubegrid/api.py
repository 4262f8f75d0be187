"""A grid table: data sorted by cell, its catalog, and queries over both.

Layout under the grid's path:
    data/seg=<name>/              rows with coordinate columns, sorted by cell
    catalog/gen=<g>/seg=<name>/   entries of the cells of one segment
    meta/v<version>.json          policy, headers, layout, committed segments and ingested batches
Every attempt writes a segment under a name of its own, so no writer touches what another has
written; it counts once a version names it. A version file is created only if its number is free, and
a writer that finds it taken reads the new version and tries again on top of it.

Segments are storage and batches are what was ingested: compaction replaces segments, but a batch id
stays known for ever, so a batch that is sent again is never added twice.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from cubegrid import fs
from cubegrid.build import PAGE_ROWS, assign_cells, describe_cells, dimension_bounds, full_entries, reorganise
from cubegrid.headers import Header
from cubegrid.plans.planner import GridQuery, Plan, make_plan
from cubegrid.policy import SplitPolicy
from cubegrid.stores import EntryStore, ParquetEntries


class ConflictError(RuntimeError):
    """Another writer changed what this change was based on."""


def _holds(ranges: list[list[int]], k: int) -> bool:
    return any(a <= k <= b for a, b in ranges)


def _with(ranges: list[list[int]], k: int) -> list[list[int]]:
    """Closed ranges of whole numbers with one number more, neighbours joined."""
    out: list[list[int]] = []
    for a, b in sorted([*ranges, [k, k]]):
        if out and a <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


class GridTable:
    def __init__(self, spark: SparkSession, path: str, meta: dict, store: EntryStore | None = None):
        self.spark, self.path = spark, path.rstrip("/")
        self.store = store or ParquetEntries()
        self._use(meta)

    def _use(self, meta: dict) -> None:
        self.meta = meta
        self.policy = SplitPolicy.from_json(meta["policy"])
        self.headers = [Header.from_json(h) for h in meta["headers"]]
        self.base_schema = StructType.fromJson(meta["schema"])
        self.base_columns = self.base_schema.fieldNames()
        self._opened: dict[str, DataFrame] = {}

    # ---- life cycle ----

    @classmethod
    def create(cls, df: DataFrame, path: str, policy: SplitPolicy, headers: list[Header] = (), files: int | None = None, layout: str = "lex", salt: int = 1, row_group_bytes: int | None = None, compression: str = "zstd", batch_id: int = 0, page_rows: int = PAGE_ROWS, store: EntryStore | None = None, copies: int = 1) -> GridTable:
        """Reorganise ``df``, every row ``copies`` times, into a new grid. Data has one order, so a path holds one grid only."""
        spark = df.sparkSession
        path = path.rstrip("/")
        if _versions(spark, path):
            raise FileExistsError(f"{path} already holds a grid")
        if clash := set(policy.columns) & set(df.columns):
            raise ValueError(f"columns {sorted(clash)} are taken by coordinates")
        meta = {"policy": policy.to_json(), "headers": [h.to_json() for h in headers], "schema": df.schema.jsonValue(), "layout": layout, "salt": salt, "row_group_bytes": row_group_bytes, "page_rows": page_rows, "compression": compression, "version": 0, "generation": "0", "segments": {}, "ingested": []}
        grid = cls(spark, path, meta, store)
        if not grid._add(df, batch_id, files, copies=copies):
            raise FileExistsError(f"{path} was made by another writer in the meantime")
        return grid

    @classmethod
    def open(cls, spark: SparkSession, path: str, store: EntryStore | None = None) -> GridTable:
        grid = cls.__new__(cls)
        grid.spark, grid.path, grid.store = spark, path.rstrip("/"), store or ParquetEntries()
        grid.refresh()
        return grid

    def refresh(self) -> GridTable:
        """Take the latest committed version."""
        found = _versions(self.spark, self.path)
        if not found:
            raise FileNotFoundError(f"{self.path} holds no grid")
        self._use(json.loads(fs.read_text(self.spark, f"{self.path}/meta/{found[-1]}")))
        return self

    def _commit(self, change: Callable[[dict], dict | None]) -> bool:
        """Publish ``change`` of the latest version as the next one; False if it turns out needless.

        ``change`` is called again on top of whatever another writer has published first.
        """
        while True:
            if _versions(self.spark, self.path):
                self.refresh()
            new = change(self.meta)
            if new is None:
                return False
            new = {**new, "version": self.meta["version"] + 1}
            if fs.publish_text(self.spark, f"{self.path}/meta/v{new['version']:012d}.json", json.dumps(new, indent=1)):
                self._use(new)
                return True

    def _data_path(self, segment: str) -> str:
        return f"{self.path}/data/seg={segment}"

    def _catalog_path(self, segment: str, generation: str | None = None) -> str:
        return f"{self.path}/catalog/gen={self.meta['generation'] if generation is None else generation}/seg={segment}"

    def _write_entries(self, segment: str, batch_id: int, headers: list[Header], generation: str) -> dict:
        """Describe a segment; returns the schema of its entries."""
        entries = describe_cells(self._read_data([self._data_path(segment)]), self.policy, headers, batch_id)
        entries.sort(*self.policy.columns).write.mode("overwrite").option("compression", "zstd").parquet(self._catalog_path(segment, generation))
        return entries.schema.jsonValue()

    def _add(self, df: DataFrame, batch_id: int, files: int | None, instead_of: tuple[str, ...] = (), ingest: bool = True, copies: int = 1) -> bool:
        """Write a segment and publish it; what a writer finds published in between is kept."""
        segment = f"{batch_id}-{uuid.uuid4().hex[:12]}"
        reorganise(df, self.policy, self._data_path(segment), files, self.meta["layout"], self.meta["salt"], self.meta["compression"], self.meta["row_group_bytes"], self.meta["page_rows"], copies)
        about = {"batch": batch_id, "files": len(fs.list_files(self.spark, self._data_path(segment)))}
        described: dict[str, dict] = {}

        def change(meta: dict) -> dict | None:
            if ingest and _holds(meta["ingested"], batch_id):
                return None
            if missing := [s for s in instead_of if s not in meta["segments"]]:
                raise ConflictError(f"segments {missing} were replaced by another writer")
            g = meta["generation"]
            if g not in described:  # a header may have been added since
                described[g] = self._write_entries(segment, batch_id, [Header.from_json(h) for h in meta["headers"]], g)
            kept = {k: v for k, v in meta["segments"].items() if k not in instead_of}
            return {**meta, "segments": {**kept, segment: about}, "entries_schema": described[g], "ingested": _with(meta["ingested"], batch_id) if ingest else meta["ingested"]}

        return self._commit(change)

    def append(self, df: DataFrame, batch_id: int, files: int | None = None, verify: bool = True) -> bool:
        """Add a batch; nothing stored is touched. False if the batch was ever added (a retry)."""
        self.refresh()
        if _holds(self.meta["ingested"], batch_id):
            return False
        if verify:
            self.check_schema(df)
        return self._add(df.select(*[f"`{c}`" for c in self.base_columns]), batch_id, files)

    def check_schema(self, df: DataFrame) -> None:
        have = {f.name: f.dataType for f in df.schema}
        wrong = [f.name for f in self.base_schema if have.get(f.name) != f.dataType]
        if wrong:
            raise ValueError(f"columns {wrong} are missing or of another type")

    def add_header(self, header: Header) -> None:
        """Precompute one more function over all segments: a new catalog generation, no data moved."""

        def change(meta: dict) -> dict | None:
            headers = [Header.from_json(h) for h in meta["headers"]]
            if header.key in {h.key for h in headers}:
                return None
            generation = f"{int(meta['generation'].split('-')[0]) + 1}-{uuid.uuid4().hex[:8]}"  # no other writer's
            for segment, about in meta["segments"].items():
                schema = self._write_entries(segment, about["batch"], [*headers, header], generation)
            return {**meta, "headers": [*meta["headers"], header.to_json()], "generation": generation, "entries_schema": schema}

        self._commit(change)

    def compact(self, batches: list[int] | None = None, files: int | None = None) -> None:
        """Rewrite the segments of some batches (default: all) as one, so that each cell has one
        segment again. Which batches were ingested does not change."""
        self.refresh()
        old = tuple(s for s, about in self.meta["segments"].items() if batches is None or about["batch"] in batches)
        if old:
            rows = self._read_data([self._data_path(s) for s in old]).select(*[f"`{c}`" for c in self.base_columns])
            self._add(rows, min(self.meta["segments"][s]["batch"] for s in old), files, old, ingest=False)

    def vacuum(self) -> None:
        """Delete what the latest version does not name: for when no writer or older reader is at work."""
        self.refresh()
        for kind, keep in (("data", self.meta["segments"]), (f"catalog/gen={self.meta['generation']}", self.meta["segments"])):
            for name in fs.names(self.spark, f"{self.path}/{kind}"):
                if name.startswith("seg=") and name[4:] not in keep:
                    fs.delete(self.spark, f"{self.path}/{kind}/{name}")
        for name in fs.names(self.spark, f"{self.path}/catalog"):
            if name != f"gen={self.meta['generation']}":
                fs.delete(self.spark, f"{self.path}/catalog/{name}")
        for name in _versions(self.spark, self.path)[:-1]:
            fs.delete(self.spark, f"{self.path}/meta/{name}")

    # ---- reading ----

    @property
    def data_schema(self) -> StructType:
        schema = StructType(list(self.base_schema.fields))
        for c in self.policy.columns:
            schema = schema.add(c, "long")
        return schema

    def _read_data(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(self.data_schema).parquet(*paths)

    def data(self, files: list[str] | None = None) -> DataFrame:
        """Rows with coordinates: of the given files, or of all committed segments.

        The latter is opened once per version: its files never change.
        """
        if files:
            return self._read_data(files)
        if "data" not in self._opened:
            self._opened["data"] = self._read_data([self._data_path(s) for s in self.meta["segments"]])
        return self._opened["data"]

    def entries(self) -> DataFrame:
        """The catalog: one row per cell and segment, from the store of this handle."""
        if "entries" not in self._opened:
            paths = [self._catalog_path(s) for s in self.meta["segments"]]
            stored = self.store.open(self.spark, paths, StructType.fromJson(self.meta["entries_schema"]))
            self._opened["entries"] = full_entries(stored, self.policy, self.headers)
        return self._opened["entries"]

    @property
    def file_count(self) -> int:
        return sum(s["files"] for s in self.meta["segments"].values())

    def cells(self) -> DataFrame:
        """Entries merged to one row per cell: coordinates, n and finished headers."""
        outs = [h.finish(h.merge(F.col(h.column))).alias(h.column) for h in self.headers]
        return self.entries().groupBy(*self.policy.columns).agg(F.sum("n").alias("n"), *outs)

    def bounds(self) -> DataFrame:
        return dimension_bounds(self.entries(), self.policy)

    def bounds_map(self) -> dict[str, tuple[int | None, int | None]]:
        return {r["dim"]: (r["g_min"], r["g_max"]) for r in self.bounds().collect()}

    def plan(self, query: GridQuery, mode: str = "geometric", headers: bool = True) -> Plan:
        return make_plan(self, query, mode, headers)

    def query(self, query: GridQuery, mode: str = "geometric", headers: bool = True) -> DataFrame:
        return self.plan(query, mode, headers).run()

    def sql(self, text: str) -> DataFrame:
        """Run a SELECT over this grid: ranges on dimensions are planned, the rest is left to Spark."""
        from cubegrid.sql_front import parse_select

        return self.query(parse_select(text, self.policy, self.spark))

    def register(self, name: str) -> None:
        """A temporary view of the base columns, and the name by which ``sql_front.sql`` finds this grid."""
        from cubegrid.sql_front import REGISTERED

        self.data().select(*[f"`{c}`" for c in self.base_columns]).createOrReplaceTempView(name)
        REGISTERED[(self.spark.sparkContext.applicationId, name.lower())] = self


def _versions(spark: SparkSession, path: str) -> list[str]:
    return [n for n in fs.names(spark, f"{path}/meta") if n.startswith("v") and n.endswith(".json")]


__all__ = ["ConflictError", "GridQuery", "GridTable", "assign_cells"]
