"""Query boxes: conjunctions of ranges normalised per dimension, and what they mean for cells."""

from __future__ import annotations

import bisect
from collections.abc import Sequence
from dataclasses import dataclass, field
from datetime import date, datetime
from decimal import Decimal
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F

from cubegrid.policy import Dim, SplitPolicy


@dataclass(frozen=True)
class Range:
    """lo and hi with open or closed ends; None leaves a side open-ended."""

    name: str
    lo: Any = None
    hi: Any = None
    lo_closed: bool = True
    hi_closed: bool = False

    @classmethod
    def open(cls, name: str, lo: Any, hi: Any) -> Range:
        return cls(name, lo, hi, False, False)

    @classmethod
    def between(cls, name: str, lo: Any, hi: Any) -> Range:
        return cls(name, lo, hi, True, True)

    @classmethod
    def eq(cls, name: str, value: Any) -> Range:
        return cls(name, value, value, True, True)

    @classmethod
    def compare(cls, name: str, op: str, value: Any) -> Range:
        if op == "=":
            return cls.eq(name, value)
        if op in (">", ">="):
            return cls(name, lo=value, lo_closed=op == ">=")
        if op in ("<", "<="):
            return cls(name, hi=value, hi_closed=op == "<=")
        raise ValueError(f"no range for operator {op}")

    def on_column(self, dim: Dim) -> str:
        """The exact condition on the base column, as SQL text."""
        # exact decimals on both sides, so that 0.07 as a double meets 0.07 as a bound
        col = f"CAST(`{self.name}` AS DECIMAL(28,{max(dim.scale, 6) if dim.continuous else dim.scale}))" if dim.kind == "decimal" else f"`{self.name}`"
        out = []
        for value, op in ((self.lo, ">=" if self.lo_closed else ">"), (self.hi, "<=" if self.hi_closed else "<")):
            if value is None:
                continue
            if dim.kind == "decimal":
                bound = f"CAST('{value}' AS DECIMAL(28,9))"
            elif dim.kind == "date" and not isinstance(value, date):
                bound = _sql(date.fromisoformat(value))
            else:
                bound = _sql(value)
            out.append(f"{col} {op} {bound}")
        return " AND ".join(out) or "true"


@dataclass(frozen=True)
class Interval:
    """Coordinates of a dimension: related [g_lo, g_hi], inner [in_lo, in_hi]; None is unbounded."""

    g_lo: int | None
    g_hi: int | None
    in_lo: int | None
    in_hi: int | None
    t_lo: int | None = None  # ticks, half-open: rows outside cannot match
    t_hi: int | None = None


def normalise(r: Range, dim: Dim) -> Interval:
    """A range as coordinates. Values that fall on ticks are discrete: > v is >= the next tick."""
    if dim.cut_points:
        points = dim.cut_points
        g_lo = None if r.lo is None else bisect.bisect_right(points, r.lo)
        if r.hi is None:
            g_hi = None
        else:
            g_hi = bisect.bisect_right(points, r.hi)
            if not r.hi_closed and g_hi > 0 and points[g_hi - 1] == r.hi:
                g_hi -= 1
        starts = r.lo is not None and r.lo_closed and r.lo in points
        ends = r.hi is not None and not r.hi_closed and r.hi in points
        return Interval(g_lo, g_hi, None if g_lo is None else g_lo if starts else g_lo + 1, None if g_hi is None else g_hi if ends else g_hi - 1)
    w, o = dim.width_ticks, dim.origin_ticks
    t_lo = t_hi = sure_lo = sure_hi = None
    if r.lo is not None:
        t = dim.ticks_of(r.lo)
        between = dim.between_ticks(r.lo)
        if dim.continuous:
            t_lo, sure_lo = t, t + 1 if between or not r.lo_closed else t
        else:
            t_lo = sure_lo = t + 1 if between or not r.lo_closed else t
    if r.hi is not None:
        t = dim.ticks_of(r.hi)
        between = dim.between_ticks(r.hi)
        if dim.continuous:
            t_hi, sure_hi = t + 1 if between or r.hi_closed else t, t
        else:
            t_hi = sure_hi = t + 1 if between or r.hi_closed else t
    return Interval(
        None if t_lo is None else (t_lo - o) // w,
        None if t_hi is None else (t_hi - 1 - o) // w,
        None if sure_lo is None else -((o - sure_lo) // w),
        None if sure_hi is None else (sure_hi - o) // w - 1,
        t_lo,
        t_hi,
    )


@dataclass(frozen=True)
class PredicateBox:
    """One interval per constrained dimension, the ranges they came from, and what is left over."""

    policy: SplitPolicy
    ranges: tuple[Range, ...] = ()
    residual: str | None = None
    intervals: dict[str, Interval] = field(default_factory=dict, compare=False)

    @property
    def is_empty(self) -> bool:
        return any((i.t_lo is not None and i.t_hi is not None and i.t_lo >= i.t_hi) or (i.g_lo is not None and i.g_hi is not None and i.g_lo > i.g_hi) for i in self.intervals.values())

    def related_sql(self) -> str:
        """Cells that may hold matching rows. A NULL coordinate fails on constrained dimensions only."""
        return _all([_within(n, i.g_lo, i.g_hi) for n, i in self.intervals.items()])

    def inner_sql(self) -> str:
        """Cells all of whose rows match; dimensions left free constrain nothing."""
        return _all([_within(n, i.in_lo, i.in_hi) for n, i in self.intervals.items()])

    def rim_sql(self) -> str:
        """Related cells that are not inner, as a union of disjoint boxes.

        Each box takes one side of one dimension beyond the inner range, the dimensions before it within
        their inner ranges and those after it within their related ones. Boxes of plain comparisons are
        what the Parquet reader tests against the statistics of row groups and pages; a negation is not.
        """
        if not self.has_inner:
            return self.related_sql()
        names, boxes = list(self.intervals), []
        for k, n in enumerate(names):
            i = self.intervals[n]
            before = [_within(m, self.intervals[m].in_lo, self.intervals[m].in_hi) for m in names[:k]]
            after = [_within(m, self.intervals[m].g_lo, self.intervals[m].g_hi) for m in names[k + 1 :]]
            if i.in_lo is not None and i.g_lo < i.in_lo:
                boxes.append(_all([*before, _within(n, i.g_lo, i.in_lo - 1), *after]))
            if i.in_hi is not None and i.in_hi < i.g_hi:
                boxes.append(_all([*before, _within(n, i.in_hi + 1, i.g_hi), *after]))
        return " OR ".join(f"({b})" for b in boxes) or "false"

    @property
    def has_inner(self) -> bool:
        return all(i.in_lo is None or i.in_hi is None or i.in_lo <= i.in_hi for i in self.intervals.values())

    def rows_sql(self) -> str:
        """The exact condition on rows, without the residual."""
        return _all([f"({r.on_column(self.policy.dim(r.name))})" for r in self.ranges])

    def inner_observed_sql(self) -> str:
        """Inner by each entry's observed lowest and highest ticks; exact whatever the rounding."""
        out = []
        for n, i in self.intervals.items():
            if self.policy.dim(n).cut_points or self.policy.dim(n).continuous:
                out.append(_within(n, i.in_lo, i.in_hi))
                continue
            if i.t_lo is not None:
                out.append(f"dim_min_{n} >= {i.t_lo}")
            if i.t_hi is not None:
                out.append(f"dim_max_{n} < {i.t_hi}")
        return _all(out)

    def overlap_observed_sql(self) -> str:
        out = []
        for n, i in self.intervals.items():
            if self.policy.dim(n).cut_points:
                continue
            if i.t_lo is not None:
                out.append(f"dim_max_{n} >= {i.t_lo}")
            if i.t_hi is not None:
                out.append(f"dim_min_{n} < {i.t_hi}")
        return _all(out)

    def related(self) -> Column:
        return F.expr(self.related_sql())

    def inner(self) -> Column:
        return F.expr(self.inner_sql())

    def rows(self) -> Column:
        return F.expr(self.rows_sql())

    def disjoint_from(self, other: PredicateBox) -> bool:
        for n, a in self.intervals.items():
            b = other.intervals.get(n)
            if b is None:
                continue
            if a.t_hi is not None and b.t_lo is not None and a.t_hi <= b.t_lo and not self.policy.dim(n).continuous:
                return True
            if b.t_hi is not None and a.t_lo is not None and b.t_hi <= a.t_lo and not self.policy.dim(n).continuous:
                return True
        return False


def _within(name: str, lo: int | None, hi: int | None) -> str:
    out = [f"g_{name} IS NOT NULL"]
    if lo is not None:
        out.append(f"g_{name} >= {lo}")
    if hi is not None:
        out.append(f"g_{name} <= {hi}")
    return " AND ".join(out)


def _all(terms: list[str]) -> str:
    return " AND ".join(terms) or "true"


def make_box(policy: SplitPolicy, terms: Sequence[Range], residual: str | None = None) -> PredicateBox:
    """Intersect the ranges of each dimension; ranges on other columns become residual text."""
    merged: dict[str, Interval] = {}
    kept, rest = [], [residual] if residual else []
    for r in terms:
        if r.name not in policy:
            rest += [f"`{r.name}` {op} {_sql(v)}" for v, op in ((r.lo, ">=" if r.lo_closed else ">"), (r.hi, "<=" if r.hi_closed else "<")) if v is not None]
            continue
        kept.append(r)
        new = normalise(r, policy.dim(r.name))
        old = merged.get(r.name)
        if old is not None:
            new = Interval(*[_meet(getattr(old, k), getattr(new, k), k.endswith("lo")) for k in ("g_lo", "g_hi", "in_lo", "in_hi", "t_lo", "t_hi")])
        merged[r.name] = new
    return PredicateBox(policy, tuple(kept), " AND ".join(f"({x})" for x in rest) or None, merged)


def _meet(a: int | None, b: int | None, low: bool) -> int | None:
    if a is None or b is None:
        return b if a is None else a
    return max(a, b) if low else min(a, b)


def _sql(v: Any) -> str:
    if isinstance(v, datetime):
        return f"TIMESTAMP_NTZ'{v}'"
    if isinstance(v, date):
        return f"DATE'{v}'"
    if isinstance(v, str):
        return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(v, float):
        return f"CAST('{v}' AS DOUBLE)"
    if isinstance(v, Decimal):
        return f"CAST('{v}' AS DECIMAL(38,{max(0, -v.as_tuple().exponent)}))"
    return str(v)


def complete_box(box: PredicateBox, bounds: dict[str, tuple[int | None, int | None]]) -> dict[str, tuple[Any, Any]]:
    """Missing dimensions filled from the stored bounds, the upper end one interval beyond the last.

    For display, estimates and tests; the plan itself leaves such dimensions free, which also keeps
    rows whose value is NULL.
    """
    out = {}
    for d in box.policy.dims:
        i = box.intervals.get(d.name)
        lo, hi = bounds.get(d.name, (None, None))
        g_lo = i.g_lo if i and i.g_lo is not None else lo
        g_hi = i.g_hi if i and i.g_hi is not None else hi
        out[d.name] = (None, None) if g_lo is None or g_hi is None else (d.bounds_of(g_lo)[0], d.bounds_of(g_hi)[1])
    return out
