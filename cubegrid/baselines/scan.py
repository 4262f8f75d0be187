"""Full scan: read everything, filter, aggregate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubegrid.headers import Agg
from cubegrid.plans.predicate import make_box
from cubegrid.policy import SplitPolicy


def condition(policy: SplitPolicy, ranges, residual: str | None = None) -> Column:
    box = make_box(policy, ranges, residual)
    return box.rows() & F.expr(box.residual) if box.residual else box.rows()


def aggregate(rows: DataFrame, aggs: tuple[Agg, ...], group: tuple[str, ...] = ()) -> DataFrame:
    outs = [a.over_rows() for a in aggs]
    return rows.groupBy(*group).agg(*outs) if group else rows.agg(*outs)


class Scan:
    def __init__(self, base: DataFrame, policy: SplitPolicy):
        self.base, self.policy = base, policy

    def rows(self, ranges, residual: str | None = None) -> DataFrame:
        return self.base.where(condition(self.policy, ranges, residual))

    def query(self, ranges, aggs, group=()) -> DataFrame:
        return aggregate(self.rows(ranges), aggs, group)

    def records_read(self, ranges) -> DataFrame:
        return self.base.agg(F.count("*").alias("records_read"))
