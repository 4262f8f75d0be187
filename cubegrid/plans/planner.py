"""Plans: which cells a query touches, which part headers answer, and how the parts are merged."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubegrid.headers import Agg, Header
from cubegrid.plans.execute import scan_cells
from cubegrid.plans.predicate import PredicateBox, make_box


@dataclass(frozen=True)
class GridQuery:
    """Ranges on columns, a residual condition, outputs, and group keys or a projection."""

    ranges: tuple = ()
    aggs: tuple[Agg, ...] = ()
    group: tuple[str, ...] = ()
    select: tuple[str, ...] = ()
    residual: str | None = None


@dataclass
class Plan:
    grid: object
    query: GridQuery
    box: PredicateBox
    mode: str  # geometric or observed
    headers: bool  # whether inner cells are answered from headers
    reason: str = ""

    @cached_property
    def cells(self) -> DataFrame:
        """Entries that the box touches, with the boolean ``inner``. A filter on the catalog, never an
        enumeration of the box."""
        if self.box.is_empty:
            return self.grid.entries().select("*", F.lit(False).alias("inner")).where("false")
        return self.grid.entries().where(self._touched()).select("*", F.expr(self._inside()).alias("inner"))

    def _touched(self) -> str:
        touched = self.box.related_sql()
        return f"{touched} AND {self.box.overlap_observed_sql()}" if self.mode == "observed" else touched

    def _inside(self) -> str:
        return self.box.inner_observed_sql() if self.mode == "observed" else self.box.inner_sql()

    def inner_entries(self) -> DataFrame:
        """Entries that headers answer."""
        if self.box.is_empty or (self.mode == "geometric" and not self.box.has_inner):
            return self.grid.entries().where("false")
        return self.grid.entries().where(f"{self._touched()} AND {self._inside()}")

    def read_cells(self) -> DataFrame:
        """Entries whose rows the plan reads."""
        return self.cells.where(~F.col("inner")) if self.headers else self.cells

    def records_read(self) -> DataFrame:
        """One row: rows of the cells whose row ranges this plan asks for, from the catalog. What the scan
        hands out is ``measures.scan_footprint``: these, but for the ends of pages."""
        return self.read_cells().agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("records_read"))

    def read_sql(self) -> str:
        """The condition on entries that ``read_cells`` applies."""
        if self.box.is_empty:
            return "false"
        return f"({self._touched()}) AND NOT ({self._inside()})" if self.headers else self._touched()

    def stats(self) -> DataFrame:
        """Related, inner and boundary cells with their rows."""
        keys = self.grid.policy.columns
        merged = self.cells.groupBy(*keys).agg(F.sum("n").alias("n"), F.min("inner").alias("inner"))
        n = F.coalesce(F.sum("n"), F.lit(0))
        return merged.agg(
            F.count("*").alias("related"),
            F.count_if("inner").alias("inner"),
            F.count_if(~F.col("inner")).alias("boundary"),
            n.alias("rows_related"),
            F.coalesce(F.sum(F.when(~F.col("inner"), F.col("n"))), F.lit(0)).alias("rows_boundary"),
        )

    def run(self) -> DataFrame:
        q = self.query
        if not q.aggs and not q.group:
            rows = scan_cells(self)
            return rows.select(*[F.expr(s) for s in q.select]) if q.select else rows.select(*self.grid.base_columns)
        if self.headers and q.group:
            return _group_from_headers(self)
        if self.headers:
            return _merge(self.grid, q, [self])
        rows = scan_cells(self)
        outs = [a.over_rows() for a in q.aggs]
        return rows.groupBy(*q.group).agg(*outs) if q.group else rows.agg(*outs)

    def explain(self) -> str:
        return self.run()._jdf.queryExecution().explainString(self.grid.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def records_read_by(plans: dict[str, Plan]) -> DataFrame:
    """One row with a column for each of several plans of one grid: their records read, by one pass over the catalog."""
    asked = {name: f"({p.read_sql()})" for name, p in plans.items()}
    entries = next(iter(plans.values())).grid.entries().where(" OR ".join(asked.values()))
    return entries.agg(*[F.coalesce(F.sum(F.when(F.expr(c), F.col("n"))), F.lit(0)).cast("long").alias(name) for name, c in asked.items()])


def header_answerable(query: GridQuery, headers: list[Header], policy) -> tuple[bool, str]:
    """Whether inner cells can be answered from headers, and why not."""
    if not query.aggs:
        return False, "not an aggregate query"
    if query.residual:
        return False, "a condition outside the index dimensions"
    known = {h.key for h in headers}
    for a in query.aggs:
        for kind, e in a.parts():
            if (kind, e) not in known:
                return False, f"no header {kind}({e})"
    for g in query.group:
        if g not in policy:
            return False, f"group key {g} is no dimension"
        d = policy.dim(g)
        if d.cut_points or d.continuous or d.width_ticks != 1 or d.kind == "timestamp":
            return False, f"an interval of {g} holds several values"
    return True, ""


def make_plan(grid, query: GridQuery, mode: str = "geometric", use_headers: bool = True) -> Plan:
    box = make_box(grid.policy, query.ranges, query.residual)
    if box.residual != query.residual:
        query = GridQuery(query.ranges, query.aggs, query.group, query.select, box.residual)
    ok, reason = header_answerable(query, grid.headers, grid.policy) if use_headers else (False, "headers not wanted")
    if ok and query.group and not box.has_inner:
        ok, reason = False, "no inner cell"
    return Plan(grid, query, box, mode, ok, reason)


# ---- header part and boundary part ----------------------------------------------------------------


def _needed(grid, query: GridQuery) -> list[Header]:
    wanted = {p for a in query.aggs for p in a.parts()}
    return [h for h in grid.headers if h.key in wanted]


def _finished(grid, query: GridQuery, needed: list[Header], merged: dict[str, Column]) -> list[Column]:
    by_key = {h.key: h for h in needed}
    out = []
    for a in query.aggs:
        parts = a.parts()
        if not parts:
            out.append(F.coalesce(merged["n"], F.lit(0)).cast("long").alias(a.alias))
        elif a.kind == "avg":
            s, c = (merged[by_key[p].column] for p in parts)
            # of the type that avg over rows has; an empty answer is NULL, as SQL has it
            kind = grid.data().agg(F.avg(F.expr(a.expr))).schema[0].dataType
            out.append(F.try_divide(s, c).cast(kind).alias(a.alias))
        else:
            h = by_key[parts[0]]
            out.append(h.finish(merged[h.column]).alias(a.alias))
    return out


def _merge(grid, query: GridQuery, plans: list[Plan], group: tuple[str, ...] = ()) -> DataFrame:
    """Headers of inner cells and partials over boundary rows, united and merged in one job."""
    needed = _needed(grid, query)
    names = ["n", *[h.column for h in needed]]
    merges = {"n": lambda c: F.sum(c), **{h.column: h.merge for h in needed}}
    pieces = []
    for plan in plans:
        rows = scan_cells(plan)
        partial = [F.count("*").alias("n"), *[h.partial().alias(h.column) for h in needed]]
        # entries join the final merge as they are: its map side already combines them
        if group:
            pieces.append(plan.inner_entries().select(*[_group_value(grid, g) for g in group], *names))
            pieces.append(rows.groupBy(*[_row_value(grid, g) for g in group]).agg(*partial))
        else:
            pieces.append(plan.inner_entries().select(*names))
            pieces.append(rows.agg(*partial))
    union = reduce(DataFrame.union, pieces)  # all of the same columns in the same order
    merged = {n: merges[n](F.col(n)) for n in names}
    outs = _finished(grid, query, needed, merged)
    if group:
        return union.groupBy(*group).agg(F.sum("n").alias("__rows"), *outs).where("__rows > 0").drop("__rows")
    return union.agg(*outs)


def _group_value(grid, name: str) -> Column:
    """The value of a dimension of unit width, from its coordinate."""
    d = grid.policy.dim(name)
    ticks = F.col(d.column) + d.origin_ticks
    if d.kind == "date":
        return F.date_from_unix_date(ticks.cast("int")).alias(name)
    if d.kind == "decimal":
        return (ticks.cast("decimal(28,0)") / F.lit(10**d.scale)).cast(f"decimal(28,{d.scale})").alias(name)
    return ticks.cast(grid.data_schema[name].dataType).alias(name)


def _row_value(grid, name: str) -> Column:
    d = grid.policy.dim(name)
    if d.kind == "date":
        return F.col(name).cast("date").alias(name)
    if d.kind == "decimal":
        return F.col(name).cast(f"decimal(28,{d.scale})").alias(name)
    return F.col(name)


def _group_from_headers(plan: Plan) -> DataFrame:
    return _merge(plan.grid, plan.query, [plan], plan.query.group)


def plan_union(grid, boxes: list[tuple], aggs: tuple[Agg, ...]) -> DataFrame:
    """Aggregate over several disjoint boxes (lists of ranges): parts of all of them, merged once."""
    made = [make_box(grid.policy, ranges) for ranges in boxes]
    for i, a in enumerate(made):
        if a.residual:
            raise ValueError("boxes constrain index dimensions only")
        for b in made[i + 1 :]:
            if not a.disjoint_from(b):
                raise ValueError("boxes overlap; cut them apart first")
    query = GridQuery(aggs=aggs)
    ok, reason = header_answerable(query, grid.headers, grid.policy)
    if not ok:
        raise ValueError(reason)
    return _merge(grid, query, [Plan(grid, query, b, "geometric", True) for b in made])
