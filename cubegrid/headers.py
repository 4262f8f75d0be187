"""Precomputed additive aggregates of cells: partial over rows, merge over partials, finish at the end."""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


#: Quoted text of any kind, words, and single characters of everything else.
_TOKEN = re.compile(r"""'(?:[^'\\]|\\.|'')*'|"(?:[^"\\]|\\.|"")*"|`[^`]*`|\w+|[^\w\s]""")


def canonical(expr: str) -> str:
    """An expression for comparing: white space and case count inside quotes only.

    Two spellings that differ otherwise are taken as different, which costs a header but never an answer.
    """
    out: list[str] = []
    for t in _TOKEN.findall(expr):
        if out and (out[-1][-1].isalnum() or out[-1][-1] == "_") and (t[0].isalnum() or t[0] == "_"):
            out.append(" ")
        out.append(t if t[0] in "'\"`" else t.lower())
    return "".join(out)


@dataclass(frozen=True)
class Header:
    """``partial`` makes an aggregate over rows; ``merge`` combines a column of partials."""

    kind: str
    expr: str
    name: str
    partial: Callable[[], Column]
    merge: Callable[[Column], Column]
    finish: Callable[[Column], Column] = lambda c: c

    @property
    def column(self) -> str:
        return f"h_{self.name}"

    @property
    def key(self) -> tuple[str, str]:
        return self.kind, canonical(self.expr)

    @classmethod
    def sum(cls, expr: str, name: str | None = None) -> Header:
        return cls("sum", expr, name or f"sum_{_slug(expr)}", lambda: F.sum(F.expr(expr)), F.sum)

    @classmethod
    def min(cls, expr: str, name: str | None = None) -> Header:
        return cls("min", expr, name or f"min_{_slug(expr)}", lambda: F.min(F.expr(expr)), F.min)

    @classmethod
    def max(cls, expr: str, name: str | None = None) -> Header:
        return cls("max", expr, name or f"max_{_slug(expr)}", lambda: F.max(F.expr(expr)), F.max)

    @classmethod
    def count(cls, expr: str, name: str | None = None) -> Header:
        """Non-null values of an expression; the row count is always kept as ``n``."""
        return cls("count", expr, name or f"count_{_slug(expr)}", lambda: F.count(F.expr(expr)), F.sum, lambda c: F.coalesce(c, F.lit(0)))

    @classmethod
    def distinct_sketch(cls, expr: str, name: str | None = None) -> Header:
        """A mergeable sketch of distinct values; its estimate is approximate and asked for by its own kind."""
        return cls("approx_distinct", expr, name or f"hll_{_slug(expr)}", lambda: F.hll_sketch_agg(F.expr(expr)), lambda c: F.hll_union_agg(c), lambda c: F.coalesce(F.hll_sketch_estimate(c), F.lit(0)))

    @classmethod
    def custom(cls, kind: str, expr: str, name: str, partial: Callable[[], Column], merge: Callable[[Column], Column], finish: Callable[[Column], Column] = lambda c: c) -> Header:
        """Any additive function: merge(partial(a), partial(b)) must equal partial(a and b)."""
        return cls(kind, expr, name, partial, merge, finish)

    def to_json(self) -> dict:
        if self.kind not in ("sum", "min", "max", "count", "approx_distinct"):
            return {"kind": "custom", "custom": self.kind, "expr": self.expr, "name": self.name}
        return {"kind": self.kind, "expr": self.expr, "name": self.name}

    @classmethod
    def from_json(cls, d: dict) -> Header:
        make = {"sum": cls.sum, "min": cls.min, "max": cls.max, "count": cls.count, "approx_distinct": cls.distinct_sketch}
        if d["kind"] == "custom":
            if d["custom"] not in CUSTOM:
                raise ValueError(f"register the header kind {d['custom']} in CUSTOM before opening this grid")
            return CUSTOM[d["custom"]](d["expr"], d["name"])
        return make[d["kind"]](d["expr"], d["name"])


#: Factories (expr, name) -> Header of custom kinds, needed to open grids that hold them.
CUSTOM: dict[str, Callable[[str, str], Header]] = {}


def _slug(expr: str) -> str:
    return re.sub(r"\W+", "_", expr).strip("_").lower()


@dataclass(frozen=True)
class Agg:
    """An output of an aggregate query: kind (sum, count, min, max, avg, ...), expression, alias."""

    kind: str
    expr: str
    alias: str

    def parts(self) -> list[tuple[str, str]]:
        """Header keys from which the output can be derived."""
        e = canonical(self.expr)
        if self.kind == "count" and e == "*":
            return []
        if self.kind == "avg":
            return [("sum", e), ("count", e)]
        return [(self.kind, e)]

    def over_rows(self) -> Column:
        if self.kind == "count":
            return (F.count("*") if self.expr == "*" else F.count(F.expr(self.expr))).alias(self.alias)
        if self.kind == "count_distinct":
            return F.count_distinct(F.expr(self.expr)).alias(self.alias)
        if self.kind == "approx_distinct":
            return F.coalesce(F.hll_sketch_estimate(F.hll_sketch_agg(F.expr(self.expr))), F.lit(0)).alias(self.alias)
        if self.kind in CUSTOM:
            h = CUSTOM[self.kind](self.expr, self.alias)
            return h.finish(h.partial()).alias(self.alias)
        return getattr(F, self.kind)(F.expr(self.expr)).alias(self.alias)
