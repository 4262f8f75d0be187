"""Cell arithmetic, ranges and their meaning for cells; no Spark where none is needed."""

from __future__ import annotations

from datetime import date, datetime
from decimal import Decimal

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cubegrid.measures import partition_metadata_bytes
from cubegrid.plans.predicate import Range, make_box, normalise
from cubegrid.policy import Dim, SplitPolicy, policy_family
from cubegrid.sql_front import extract_ranges, parse_create, parse_select


def test_worked_geometry():
    policy = SplitPolicy([Dim("a", 1, 3), Dim("b", 11, 2)])
    box = make_box(policy, [Range("a", 5, 12), Range("b", 12, 16)])
    a, b = box.intervals["a"], box.intervals["b"]
    assert (a.g_lo, a.g_hi, a.in_lo, a.in_hi) == (1, 3, 2, 2)
    assert (b.g_lo, b.g_hi, b.in_lo, b.in_hi) == (0, 2, 1, 1)
    assert policy.dim("a").bounds_of(2) == (7, 10) and policy.dim("b").bounds_of(1) == (13, 15)


def test_decimals_are_exact():
    d = Dim("x", 0, Decimal("0.01"), scale=2)
    assert [d.coord_of(v) for v in (0.07, 0.29, Decimal("0.28"), -0.01)] == [7, 29, 28, -1]


def test_dates_and_times():
    d = Dim("day", date(2024, 1, 1), 1, "d")
    assert d.coord_of("2024-01-31") == 30 and d.bounds_of(-1) == (date(2023, 12, 31), date(2024, 1, 1))
    t = Dim("ts", datetime(2024, 1, 1), 15, "m")
    assert t.coord_of(datetime(2024, 1, 1, 1)) == 4 and t.width_ticks == 900 * 10**6


def test_policy_rules():
    p = SplitPolicy([Dim("u", 0, 10)], time_dim="day")
    assert [d.name for d in p.dims] == ["u", "day"] and p.dim("day").width_ticks == 1
    assert SplitPolicy.from_json(p.to_json()) == p
    fam = policy_family(p, "u", {"l": 100, "s": 5})
    assert fam["l"].dim("u").width == 100 and fam["s"].dim("day") == p.dim("day")
    with pytest.raises(ValueError):
        SplitPolicy([Dim("u"), Dim("u")])
    with pytest.raises(ValueError):
        Dim("u", 0, 0)
    assert Dim.equal("u", 0, 999, 100).width == 10


def test_directory_memory():
    assert partition_metadata_bytes([100, 100, 100]) == 150_000_000  # about 143 MB of 2^20 bytes


@settings(max_examples=300, deadline=None)
@given(
    origin=st.integers(-20, 20),
    width=st.integers(1, 9),
    lo=st.one_of(st.none(), st.integers(-40, 40)),
    hi=st.one_of(st.none(), st.integers(-40, 40)),
    lc=st.booleans(),
    hc=st.booleans(),
)
def test_intervals_against_brute_force(origin, width, lo, hi, lc, hc):
    d = Dim("x", origin, width)
    i = normalise(Range("x", lo, hi, lc, hc), d)
    match = lambda v: (lo is None or v > lo or (lc and v == lo)) and (hi is None or v < hi or (hc and v == hi))
    for g in range(-12, 13):
        a, b = d.bounds_of(g)
        rows = [match(v) for v in range(a, b)]
        related = (i.g_lo is None or g >= i.g_lo) and (i.g_hi is None or g <= i.g_hi)
        inner = (i.in_lo is None or g >= i.in_lo) and (i.in_hi is None or g <= i.in_hi)
        if any(rows):
            assert related
        if all(rows):
            assert inner
        if inner and related:
            assert all(rows)


@settings(max_examples=200, deadline=None)
@given(points=st.lists(st.integers(-20, 20), min_size=1, max_size=6, unique=True), lo=st.one_of(st.none(), st.integers(-25, 25)), hi=st.one_of(st.none(), st.integers(-25, 25)), lc=st.booleans(), hc=st.booleans())
def test_cut_dimensions_against_brute_force(points, lo, hi, lc, hc):
    d = Dim.cuts("x", sorted(points))
    i = normalise(Range("x", lo, hi, lc, hc), d)
    match = lambda v: (lo is None or v > lo or (lc and v == lo)) and (hi is None or v < hi or (hc and v == hi))
    cells: dict[int, list[bool]] = {}
    for v in range(-60, 61):
        cells.setdefault(d.coord_of(v), []).append(match(v))
    for g, rows in cells.items():
        related = (i.g_lo is None or g >= i.g_lo) and (i.g_hi is None or g <= i.g_hi)
        inner = (i.in_lo is None or g >= i.in_lo) and (i.in_hi is None or g <= i.in_hi)
        assert related or not any(rows)
        assert all(rows) or not (inner and related)


def test_statements(spark):
    c = parse_create("CREATE GRID g ON TABLE t DIMENSIONS (a, x, day) PROPERTIES ('a'='1_3', 'x'='0_0.01', 'day'='1995-01-01_100d', 'precompute'='sum(p*q), count(p), max(p)')")
    assert [d.kind for d in c.policy.dims] == ["int", "decimal", "date"] and [h.kind for h in c.headers] == ["sum", "count", "max"]
    q = parse_select("SELECT sum(p * q) AS r, count(*) FROM t WHERE a BETWEEN 3 AND 7 AND x >= 0.05 AND day < '1998-01-01' AND name = 'a and b' GROUP BY day", c.policy)
    assert len(q.ranges) == 3 and q.residual == "((name = 'a and b'))" and q.group == ("day",) and q.aggs[0].alias == "r"
    ranges, rest = extract_ranges("a > 1 and (b = 2 or b = 3)", c.policy)
    assert len(ranges) == 1 and rest == "(((b = 2) OR (b = 3)))"
    for bad in ("CREATE GRID x", "CREATE GRID g ON TABLE t DIMENSIONS (a) PROPERTIES ('b'='0_1')"):
        with pytest.raises(ValueError):
            parse_create(bad)
