"""The methods a grid is compared with. Each follows ``IndexMethod``, and so does a grid behind ``GridMethod``."""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import DataFrame

from cubegrid.plans.planner import GridQuery


class IndexMethod(Protocol):
    """A pluggable access method over one fact table."""

    def query(self, ranges, aggs, group=()) -> DataFrame: ...

    def records_read(self, ranges) -> DataFrame: ...


@dataclass
class GridMethod:
    """A grid as one of the methods, with or without its headers."""

    grid: object
    headers: bool = True

    def query(self, ranges, aggs, group=()) -> DataFrame:
        return self.grid.query(GridQuery(tuple(ranges), tuple(aggs), tuple(group)), headers=self.headers)

    def records_read(self, ranges, aggs=()) -> DataFrame:
        """Rows of the cells that a query reads; without aggregates these are all related cells."""
        return self.grid.plan(GridQuery(tuple(ranges), tuple(aggs)), headers=self.headers).records_read()
