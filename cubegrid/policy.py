"""Split policies: how the index dimensions are cut into half-open intervals, and cell arithmetic.

Every dimension is measured in whole *ticks* (ids, days, microseconds, or units of a declared
decimal scale), so a coordinate is an exact integer floor division and never binary floating point.
"""

from __future__ import annotations

import bisect
import math
from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from datetime import date, datetime, timedelta
from decimal import ROUND_FLOOR, Decimal
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_EPOCH = date(1970, 1, 1)
_UNIT_DAYS = {"d": 1, "w": 7}
_UNIT_MICROS = {"s": 10**6, "m": 60 * 10**6, "h": 3600 * 10**6, "d": 86400 * 10**6}


@dataclass(frozen=True)
class Dim:
    """One index dimension: cuts at origin + k * width, or at explicit sorted cut points.

    ``scale`` declares decimals: the value is exact at that many digits. ``continuous`` marks
    values finer than a tick; range ends then keep their open or closed side.
    """

    name: str
    origin: Any = 0
    width: Any = 1
    unit: str | None = None
    scale: int | None = None
    continuous: bool = False
    cut_points: tuple = field(default=())

    def __post_init__(self) -> None:
        if not self.cut_points and self.width_ticks <= 0:
            raise ValueError(f"{self.name}: the width must be positive")
        if list(self.cut_points) != sorted(set(self.cut_points)):
            raise ValueError(f"{self.name}: cut points must rise")

    @classmethod
    def cuts(cls, name: str, points: Sequence) -> Dim:
        return cls(name, cut_points=tuple(points))

    @classmethod
    def equal(cls, name: str, lo: int, hi: int, k: int) -> Dim:
        """k equal intervals over whole numbers lo..hi."""
        return cls(name, lo, max(1, math.ceil((hi - lo + 1) / k)))

    @property
    def kind(self) -> str:
        if self.cut_points:
            return "cuts"
        if isinstance(self.origin, datetime):
            return "timestamp"
        if isinstance(self.origin, date):
            return "date"
        return "decimal" if self.scale is not None else "int"

    @property
    def column(self) -> str:
        return f"g_{self.name}"

    @property
    def width_ticks(self) -> int:
        if self.kind == "date":
            return int(self.width) * _UNIT_DAYS[self.unit or "d"]
        if self.kind == "timestamp":
            return int(self.width) * _UNIT_MICROS[self.unit or "d"]
        return int(Decimal(str(self.width)).scaleb(self.scale or 0))

    @property
    def origin_ticks(self) -> int:
        return self.ticks_of(self.origin)

    def ticks_of(self, value: Any) -> int:
        """Ticks of a Python value, rounded down where it lies between two."""
        if self.kind == "date":
            d = date.fromisoformat(value) if isinstance(value, str) else value
            return ((d.date() if isinstance(d, datetime) else d) - _EPOCH).days
        if self.kind == "timestamp":
            t = datetime.fromisoformat(value) if isinstance(value, str) else value
            return (t - datetime(1970, 1, 1)) // timedelta(microseconds=1)
        return int(Decimal(str(value)).scaleb(self.scale or 0).to_integral_value(ROUND_FLOOR))

    def between_ticks(self, value: Any) -> bool:
        """Whether the value lies strictly between two ticks."""
        if self.kind in ("date", "timestamp"):
            return self.kind == "date" and isinstance(value, datetime) and value.time() != datetime.min.time()
        return Decimal(str(value)).scaleb(self.scale or 0) % 1 != 0

    def value_of(self, ticks: int) -> Any:
        if self.kind == "date":
            return _EPOCH + timedelta(days=ticks)
        if self.kind == "timestamp":
            return datetime(1970, 1, 1) + timedelta(microseconds=ticks)
        return Decimal(ticks).scaleb(-self.scale) if self.scale else ticks

    def ticks(self, col: Column | None = None) -> Column:
        """The value's ticks as a long column."""
        c = F.col(self.name) if col is None else col
        if self.kind == "date":
            return F.unix_date(c.cast("date")).cast("long")
        if self.kind == "timestamp":
            return F.timestamp_diff("MICROSECOND", F.lit(datetime(1970, 1, 1)).cast("timestamp_ntz"), c.cast("timestamp_ntz"))
        if self.kind == "decimal":
            exact = c.cast(f"decimal(28,{max(self.scale, 6) if self.continuous else self.scale})")
            scaled = exact * F.lit(10**self.scale).cast("decimal(10,0)")
            return F.floor(scaled).cast("long")
        return c.cast("long") if not self.continuous else F.floor(c.cast("decimal(28,6)")).cast("long")

    def coord(self, col: Column | None = None) -> Column:
        """The coordinate: floor to the previous cut, exact for negatives too."""
        if self.cut_points:
            c = F.col(self.name) if col is None else col
            points = F.array(*[F.lit(p) for p in self.cut_points])
            return F.when(c.isNotNull(), F.size(F.filter(points, lambda p: p <= c)).cast("long"))
        off = self.ticks(col) - F.lit(self.origin_ticks)
        w = F.lit(self.width_ticks)
        return F.call_function("div", off - F.pmod(off, w), w)

    def coord_of(self, value: Any) -> int:
        if self.cut_points:
            return bisect.bisect_right(self.cut_points, value)
        return (self.ticks_of(value) - self.origin_ticks) // self.width_ticks

    def bounds_of(self, g: int) -> tuple[Any, Any]:
        """The closed-open interval of a coordinate, as values."""
        if self.cut_points:
            lo = self.cut_points[g - 1] if g > 0 else None
            return lo, self.cut_points[g] if g < len(self.cut_points) else None
        lo = self.origin_ticks + g * self.width_ticks
        return self.value_of(lo), self.value_of(lo + self.width_ticks)

    def corner(self) -> Column:
        """Printable lower cut of the coordinate column."""
        g = F.col(self.column)
        if self.cut_points:
            return F.coalesce(g.cast("string"), F.lit("null"))
        ticks = g * self.width_ticks + self.origin_ticks
        if self.kind == "date":
            shown = F.date_from_unix_date(ticks.cast("int")).cast("string")
        elif self.kind == "decimal":
            shown = (ticks.cast("decimal(28,0)") / F.lit(10**self.scale)).cast(f"decimal(28,{self.scale})").cast("string")
        else:
            shown = ticks.cast("string")
        return F.coalesce(shown, F.lit("null"))

    def to_json(self) -> dict:
        enc = lambda v: v.isoformat() if isinstance(v, date | datetime) else str(v) if isinstance(v, Decimal) else v
        return {"name": self.name, "kind": self.kind, "origin": enc(self.origin), "width": enc(self.width), "unit": self.unit, "scale": self.scale, "continuous": self.continuous, "cuts": [enc(p) for p in self.cut_points]}

    @classmethod
    def from_json(cls, d: dict) -> Dim:
        origin = d["origin"]
        if d["kind"] == "date":
            origin = date.fromisoformat(origin)
        elif d["kind"] == "timestamp":
            origin = datetime.fromisoformat(origin)
        return cls(d["name"], origin, d["width"], d["unit"], d["scale"], d["continuous"], tuple(d["cuts"]))


@dataclass(frozen=True)
class SplitPolicy:
    """The dimensions of a grid; time is added as a default dimension where it is not listed."""

    dims: tuple[Dim, ...]
    time_dim: str | None = None

    def __init__(self, dims: Sequence[Dim], time_dim: str | Dim | None = None):
        dims = tuple(dims)
        name = time_dim.name if isinstance(time_dim, Dim) else time_dim
        if name is not None and name not in [d.name for d in dims]:
            dims += (time_dim if isinstance(time_dim, Dim) else Dim(name, date(1970, 1, 1), 1, "d"),)
        if len({d.name for d in dims}) < len(dims):
            raise ValueError("a dimension is listed twice")
        object.__setattr__(self, "dims", dims)
        object.__setattr__(self, "time_dim", name)

    @property
    def columns(self) -> list[str]:
        return [d.column for d in self.dims]

    def dim(self, name: str) -> Dim:
        return next(d for d in self.dims if d.name == name)

    def __contains__(self, name: str) -> bool:
        return any(d.name == name for d in self.dims)

    def corner(self) -> Column:
        return F.concat_ws("_", *[d.corner() for d in self.dims])

    def cell_key(self) -> Column:
        return F.struct(*[F.col(c) for c in self.columns])

    def cell_bounds(self) -> list[Column]:
        """lo_ and hi_ ticks of each dimension's interval."""
        out = []
        for d in self.dims:
            if not d.cut_points:
                lo = F.col(d.column) * d.width_ticks + d.origin_ticks
                out += [lo.alias(f"lo_{d.name}"), (lo + d.width_ticks).alias(f"hi_{d.name}")]
        return out

    def to_json(self) -> dict:
        return {"dims": [d.to_json() for d in self.dims], "time_dim": self.time_dim}

    @classmethod
    def from_json(cls, d: dict) -> SplitPolicy:
        return cls([Dim.from_json(x) for x in d["dims"]], d["time_dim"])


def policy_family(base: SplitPolicy, name: str, widths: dict[str, Any]) -> dict[str, SplitPolicy]:
    """Variants of a policy that differ in the width of one dimension (coarse, medium, fine)."""
    return {k: SplitPolicy([replace(d, width=w) if d.name == name else d for d in base.dims], base.time_dim) for k, w in widths.items()}


def quantile_cuts(df: DataFrame, name: str, k: int, accuracy: int = 10000) -> Dim:
    """Cuts at k quantiles, for skewed dimensions."""
    points = df.agg(F.percentile_approx(name, [i / k for i in range(1, k)], accuracy)).first()[0] or []
    return Dim.cuts(name, sorted(set(points)))
