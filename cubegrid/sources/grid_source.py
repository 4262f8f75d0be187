"""A grid behind ``spark.read.format("cubegrid")``: range filters pushed to it choose row ranges of files.

The catalog is filtered by the pushed ranges; each file becomes one partition with the joined row
ranges of its related cells, and only row groups that meet a range are opened. Rows pass through Python, so this serves tools and moderate tables; the planner in ``plans`` is the
way for large ones. Needs spark.sql.python.filterPushdown.enabled (off by default in Spark).
"""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from cubegrid.plans.predicate import Range, make_box
from cubegrid.policy import SplitPolicy

_OPS = {GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<=", EqualTo: "="}


class _File(InputPartition):
    def __init__(self, path: str, ranges: list[tuple[int, int]]):
        super().__init__(path)
        self.path, self.ranges = path, ranges


def _open(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("/") else path.replace(":/", ":///", 1))


class CubeGridReader(DataSourceReader):
    def __init__(self, path: str, meta: dict):
        self.path, self.meta = path, meta
        self.policy = SplitPolicy.from_json(meta["policy"])
        self.ranges: list[Range] = []

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Ranges on dimensions are used to prune; all filters stay with Spark for exactness."""
        for f in filters:
            op = _OPS.get(type(f))
            if op and len(f.attribute) == 1 and f.attribute[0] in self.policy and self.policy.dim(f.attribute[0]).kind in ("int", "date"):
                self.ranges.append(Range.compare(f.attribute[0], op, f.value))
            yield f

    def _limits(self) -> dict[str, tuple[int | None, int | None]]:
        box = make_box(self.policy, self.ranges)
        return {f"g_{n}": (i.g_lo, i.g_hi) for n, i in box.intervals.items()}

    def partitions(self) -> list[_File]:
        import pyarrow.dataset as ds

        system, root = _open(self.path)
        base = f"{root}/catalog/gen={self.meta['generation']}"
        found: dict[str, list[tuple[int, int]]] = {}
        for segment in self.meta["segments"]:
            entries = ds.dataset(f"{base}/seg={segment}", filesystem=system, format="parquet")
            for batch in entries.to_batches(columns=["file", "row_start", "n"], filter=_expression(self._limits())):
                for file, start, n in zip(*(batch.column(c).to_pylist() for c in ("file", "row_start", "n")), strict=True):
                    found.setdefault(file, []).append((start, start + n))
        return [_File(f, _joined(found[f])) for f in sorted(found)]

    def read(self, partition: _File):
        import pyarrow.parquet as pq

        system, own = _open(partition.path)
        columns = StructType.fromJson(self.meta["schema"]).fieldNames()
        with system.open_input_file(own) as stream:
            file = pq.ParquetFile(stream)
            first = 0
            for g in range(file.num_row_groups):
                last = first + file.metadata.row_group(g).num_rows
                inside = [(max(a, first), min(b, last)) for a, b in partition.ranges if a < last and first < b]
                at = first
                if inside:
                    for batch in file.iter_batches(row_groups=[g], columns=columns):
                        for a, b in inside:
                            lo, hi = max(a - at, 0), min(b - at, batch.num_rows)
                            if lo < hi:
                                yield batch.slice(lo, hi - lo)
                        at += batch.num_rows
                first = last


def _joined(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(ranges):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _expression(limits: dict[str, tuple[int | None, int | None]]):
    import pyarrow.compute as pc

    out = None
    for name, (lo, hi) in limits.items():
        for term in ([pc.field(name) >= lo] if lo is not None else []) + ([pc.field(name) <= hi] if hi is not None else []):
            out = term if out is None else out & term
    return out


class CubeGridSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cubegrid"

    def _meta(self) -> dict:
        from pyarrow import fs

        system, root = _open(self.options["path"])
        versions = [f.path for f in system.get_file_info(fs.FileSelector(f"{root}/meta")) if f.base_name.startswith("v") and f.base_name.endswith(".json")]
        with system.open_input_stream(max(versions)) as f:
            return json.loads(f.read())

    def schema(self) -> StructType:
        return StructType.fromJson(self._meta()["schema"])

    def reader(self, schema: StructType) -> CubeGridReader:
        return CubeGridReader(self.options["path"], self._meta())
