"""Grids: answers equal a scan for any box, entries describe the files, appends and headers hold."""

from __future__ import annotations

import hashlib
import random
from datetime import date, datetime, timedelta
from decimal import Decimal

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cubegrid import fs, measures, sql_front
from cubegrid.advisor import recommend_policy
from cubegrid.api import ConflictError, GridTable
from cubegrid.baselines import GridMethod
from cubegrid.baselines.bitmap import BitmapIndex
from cubegrid.baselines.compact import AggregateIndex, CompactIndex
from cubegrid.baselines.scan import Scan
from cubegrid.baselines.sharded import ShardedStore
from cubegrid.headers import Agg, Header, canonical
from cubegrid.plans.planner import GridQuery, header_answerable, plan_union
from cubegrid.plans.predicate import Range, complete_box, make_box
from cubegrid.policy import Dim, SplitPolicy, quantile_cuts
from cubegrid.sources import loaders
from cubegrid.stores import CachedEntries
from cubegrid.streaming import windows
from cubegrid.streaming.ingest import deduplicated, stream_into_grid, unseen

DAY0 = date(2024, 1, 1)
POLICY = SplitPolicy([Dim("u", 0, 5), Dim("r", 0, 1), Dim("x", 0, Decimal("0.02"), scale=2), Dim("day", DAY0, 2, "d")], "day")
HEADERS = [Header.sum("p"), Header.count("p"), Header.min("p"), Header.max("p"), Header.distinct_sketch("u")]
AGGS = (Agg("sum", "p", "s"), Agg("avg", "p", "a"), Agg("min", "p", "lo"), Agg("max", "p", "hi"), Agg("count", "*", "n"), Agg("count", "p", "np"))


def make_rows(spark, n=1500, seed=1):
    rng = random.Random(seed)
    rows = []
    for k in range(n):
        null = lambda v: None if rng.random() < 0.03 else v
        rows.append((k, null(rng.randrange(-12, 40)), null(rng.randrange(4)), null(rng.choice([0.0, 0.01, 0.07, 0.29, 0.28, -0.01, 0.14])), null(DAY0 + timedelta(days=rng.randrange(-3, 20))), null(Decimal(rng.randrange(10000)).scaleb(-2)), rng.choice("abc")))
    return spark.createDataFrame(rows, "k long, u long, r int, x double, day date, p decimal(12,2), kind string")


@pytest.fixture(scope="module")
def rows(spark):
    return make_rows(spark).cache()


@pytest.fixture(scope="module")
def grid(spark, rows):
    return GridTable.create(rows, fs.scratch(spark, "t-grid"), POLICY, HEADERS, files=3)


def random_ranges(rng):
    out = []
    if rng.random() < 0.7:
        a, b = sorted((rng.randrange(-14, 42), rng.randrange(-14, 42)))
        out.append(Range("u", a, b, rng.random() < 0.5, rng.random() < 0.5))
    if rng.random() < 0.4:
        out.append(Range.eq("r", rng.randrange(5)))
    if rng.random() < 0.5:
        a, b = sorted((rng.choice([0.0, 0.01, 0.05, 0.07, -0.01]), rng.choice([0.07, 0.1, 0.28, 0.29])))
        out.append(Range.between("x", Decimal(str(a)), Decimal(str(b))))
    if rng.random() < 0.6:
        a = DAY0 + timedelta(days=rng.randrange(-5, 15))
        out.append(Range("day", a, a + timedelta(days=rng.randrange(0, 9)), True, rng.random() < 0.5))
    return tuple(out)


def test_any_box_equals_scan(grid, rows):
    rng = random.Random(5)
    scan = Scan(rows, POLICY)
    for k in range(10):
        ranges = random_ranges(rng)
        want = scan.query(ranges, AGGS).first()
        for mode in ("geometric", "observed"):
            plan = grid.plan(GridQuery(ranges, AGGS), mode)
            assert plan.headers and plan.run().first() == want, (k, mode, ranges)
        stats = grid.plan(GridQuery(ranges, AGGS)).stats().first()
        read = grid.plan(GridQuery(ranges, AGGS)).records_read().first()[0]
        accurate = scan.rows(ranges).count()
        assert stats["related"] == stats["inner"] + stats["boundary"] and read == stats["rows_boundary"]
        assert stats["rows_related"] >= accurate and read >= stats["rows_related"] - accurate
        got = sorted(r.k for r in grid.query(GridQuery(ranges, select=("k",))).collect())
        assert got == sorted(r.k for r in scan.rows(ranges).select("k").collect())


def test_group_join_and_residual(grid, rows, spark):
    ranges = (Range("u", 0, 30), Range("day", DAY0, DAY0 + timedelta(days=9)))
    scan = Scan(rows, POLICY)
    key = lambda df: sorted(map(str, df.collect()))
    for group in (("r",), ("kind",), ("day", "r")):
        assert key(grid.query(GridQuery(ranges, AGGS[:1], group))) == key(scan.query(ranges, AGGS[:1], group))
    plan = grid.plan(GridQuery(ranges, AGGS, residual="kind = 'a'"))
    assert not plan.headers and "outside" in plan.reason
    assert plan.run().first() == scan.rows(ranges, "kind = 'a'").agg(*[a.over_rows() for a in AGGS]).first()
    # ranges on other columns become part of the residual
    assert grid.query(GridQuery((*ranges, Range.between("k", 5, 700)), AGGS)).first() == rows.where("k between 5 and 700").transform(lambda d: Scan(d, POLICY).query(ranges, AGGS)).first()


def test_group_by_unit_dimension_uses_headers(grid, rows):
    ranges = (Range("u", -12, 39),)
    plan = grid.plan(GridQuery(ranges, AGGS[:2], ("r",)))
    assert plan.headers
    assert sorted(map(str, plan.run().collect())) == sorted(map(str, Scan(rows, POLICY).query(ranges, AGGS[:2], ("r",)).collect()))


def test_empty_and_outside_boxes(grid):
    for ranges in ((Range("u", 9, 3),), (Range("u", 1000, 2000),), (Range.open("u", 3, 4),)):
        r = grid.query(GridQuery(ranges, AGGS)).first()
        assert r["n"] == 0 and r["s"] is None and r["np"] == 0 and r["a"] is None


def test_entries_describe_files(grid, rows, spark):
    entries = grid.entries()
    assert entries.agg(F.sum("n")).first()[0] == rows.count()
    assert entries.where("row_end - row_start != n").count() == 0
    per_file = entries.groupBy("file").agg(F.sum("n").alias("n"), F.min("row_start").alias("a"), F.max("row_end").alias("b")).collect()
    assert all(r.a == 0 and r.b == r.n for r in per_file)
    assert grid.cells().count() == entries.select(*POLICY.columns).distinct().count() == entries.count()
    bounds = grid.bounds_map()
    assert bounds["r"] == (0, 3) and bounds["u"] == (-3, 7)
    full = complete_box(make_box(POLICY, [Range("u", 0, 10)]), bounds)
    assert full["u"] == (0, 10) and full["r"] == (0, 4)
    assert measures.index_bytes(spark, f"{grid.path}/catalog") > 0
    corner = entries.where("g_u = -1 and g_r = 2").select("corner").first()
    assert corner is None or corner[0].startswith("-5_2_")


def test_sketch_header(grid, rows):
    got = grid.query(GridQuery((Range("day", DAY0, DAY0 + timedelta(days=10)),), (Agg("approx_distinct", "u", "d"),))).first()[0]
    exact = rows.where(F.col("day").between(DAY0, DAY0 + timedelta(days=9))).agg(F.count_distinct("u")).first()[0]
    assert abs(got - exact) <= 2


def test_non_additive_is_refused(grid):
    ok, why = header_answerable(GridQuery((), (Agg("count_distinct", "u", "d"),)), grid.headers, POLICY)
    assert not ok and "no header" in why
    assert grid.query(GridQuery((Range.eq("r", 1),), (Agg("count_distinct", "u", "d"),))).first()[0] > 0


def test_append_equals_build(spark, rows, grid):
    cut = [DAY0 - timedelta(days=9), DAY0 + timedelta(days=5), DAY0 + timedelta(days=11), DAY0 + timedelta(days=99)]
    parts = [rows.where((F.col("day") >= a) & (F.col("day") < b)) for a, b in zip(cut, cut[1:], strict=False)]
    parts[0] = parts[0].unionByName(rows.where("day is null"))
    g = GridTable.create(parts[0], fs.scratch(spark, "t-append"), POLICY, HEADERS[:4], files=2)
    before = {f: hashlib.md5(open(f.removeprefix("file:"), "rb").read()).hexdigest() for f, _ in fs.list_files(spark, f"{g.path}/data")}
    assert g.append(parts[1], 1, files=2) and g.append(parts[2], 2, files=2) and not g.append(parts[2], 2)
    after = {f: hashlib.md5(open(f.removeprefix("file:"), "rb").read()).hexdigest() for f, _ in fs.list_files(spark, f"{g.path}/data")}
    assert before.items() <= after.items()
    cells = lambda x: x.cells().select(*POLICY.columns, "n", "h_sum_p", "h_count_p", "h_min_p", "h_max_p")
    assert cells(g).exceptAll(cells(grid)).isEmpty() and cells(grid).exceptAll(cells(g)).isEmpty()
    # late rows for cells that exist, then compaction to one segment per cell again
    late = rows.where("k % 50 = 0")
    g.append(late, 3, files=1)
    q = GridQuery((Range("u", 0, 30),), AGGS)
    want = Scan(rows.unionByName(late), POLICY).query(q.ranges, AGGS).first()
    assert g.query(q).first() == want and g.entries().count() > g.cells().count()
    g.compact()
    assert g.query(q).first() == want and g.entries().count() == g.cells().count()
    g.vacuum()
    assert GridTable.open(spark, g.path).query(q).first() == want
    with pytest.raises(ValueError):
        g.append(rows.drop("p"), 9)
    with pytest.raises(FileExistsError):
        GridTable.create(rows, g.path, POLICY)


def test_add_header_equals_built_in(spark, rows):
    g = GridTable.create(rows, fs.scratch(spark, "t-later"), POLICY, [], files=2)
    q = GridQuery((Range("u", 0, 30),), AGGS)
    assert not g.plan(q).headers
    for h in HEADERS[:4]:
        g.add_header(h)
    assert g.plan(q).headers and g.query(q).first() == Scan(rows, POLICY).query(q.ranges, AGGS).first()


def test_layouts_salt_and_split_files(spark, rows):
    q = GridQuery((Range("u", 3, 27), Range("day", DAY0, DAY0 + timedelta(days=7))), AGGS)
    want = Scan(rows, POLICY).query(q.ranges, AGGS).first()
    for options in ({"layout": "zorder"}, {"layout": "time_first"}, {"salt": 3}):
        g = GridTable.create(rows, fs.scratch(spark, "t-layout"), POLICY, HEADERS, files=3, **options)
        assert g.query(q).first() == want, options
        assert g.entries().where("row_end - row_start != n").count() == 0
    spark.conf.set("spark.sql.files.maxPartitionBytes", "4096")  # segments straddle splits
    try:
        g = GridTable.create(rows, fs.scratch(spark, "t-split"), POLICY, HEADERS, files=2, row_group_bytes=4096)
        assert g.query(q).first() == want and g.query(q, headers=False).first() == want
    finally:
        spark.conf.unset("spark.sql.files.maxPartitionBytes")


def test_copies_are_made_behind_the_shuffle(spark, rows):
    """A grid of copies equals one of repeated rows, and its build shuffles no copy."""
    few = GridTable.create(rows, fs.scratch(spark, "t-copies"), POLICY, HEADERS, files=3, copies=4)
    many = GridTable.create(rows.join(spark.range(4).select(F.lit(0).alias("nth"))).drop("nth"), fs.scratch(spark, "t-many"), POLICY, HEADERS, files=3)
    order = [*POLICY.columns, "k"]
    assert few.data().orderBy(*order).collect() == many.data().orderBy(*order).collect()
    assert few.cells().orderBy(*POLICY.columns).drop("h_distinct_sketch_u").collect() == many.cells().orderBy(*POLICY.columns).drop("h_distinct_sketch_u").collect()
    assert few.entries().where("row_end - row_start != n").count() == 0
    read = few.data().select(*POLICY.columns, F.col("_metadata.file_path").alias("f"), F.col("_metadata.row_index").alias("i")).orderBy("f", "i").collect()
    for f in {r.f for r in read}:
        cells = [tuple((x is not None, x) for x in r[:-2]) for r in read if r.f == f]
        assert cells == sorted(cells)
    for grid in (few, many):
        assert grid.query(GridQuery((Range("u", 3, 27),), AGGS)).first() == grid.query(GridQuery((Range("u", 3, 27),), AGGS), headers=False).first()


def test_cube_of_a_thousand_rows(spark):
    cube = spark.range(1000).select((F.col("id") % 10).alias("a"), (F.col("id") / 10 % 10).cast("int").alias("b"), (F.col("id") / 100).cast("int").alias("c"))
    g = GridTable.create(cube, fs.scratch(spark, "t-cube"), SplitPolicy([Dim(n, 0, 2) for n in "abc"]), [], files=2)
    assert g.cells().count() == 125 and cube.distinct().count() == 1000


def test_finer_cells_read_no_more_rows(spark, rows):
    reads, cells = [], []
    for w in (20, 10, 5, 1):
        g = GridTable.create(rows, fs.scratch(spark, "t-nest"), SplitPolicy([Dim("u", 0, w), Dim("r", 0, 1)]), HEADERS[:1], files=2)
        p = g.plan(GridQuery((Range.open("u", 3, 33), Range.open("r", 0, 3)), (Agg("sum", "p", "s"),)), headers=False)
        reads.append(p.records_read().first()[0])
        cells.append(p.stats().first()["related"])
    assert reads == sorted(reads, reverse=True) and cells == sorted(cells)


def rows_in(grid) -> int:
    return grid.data().count()


def test_scan_reads_related_ranges_only(spark):
    """Spark's own scan metric on five million rows: little more than the rows of the cells asked for."""
    from cubegrid import workloads as w

    base = w.meter(spark, "/root/testdata/sf0.1").select(*w._FACTS)
    many = base.join(F.broadcast(spark.range(50).withColumnRenamed("id", "times")))
    many = many.drop("times")
    policy, page = w.meter_policies(True)["grid_m"], 128
    g = GridTable.create(many, fs.scratch(spark, "t-many"), policy, w.METER_HEADERS, files=8, page_rows=page)
    assert rows_in(g) == 50 * base.count()
    read = {}
    for sel in w.SELECTIVITIES:
        for headers in (True, False):
            plan = g.plan(GridQuery(w.box(sel, True), w.SUM), headers=headers)
            asked, foot = plan.records_read().first()[0], measures.scan_footprint(plan.run(), f"{g.path}/data")
            assert foot["rows"] <= 1.5 * asked + page * foot["files"], (sel, headers, asked, foot)
            read[sel, headers] = foot["rows"]
    assert read["p05", True] < read["p05", False] and read["p12", True] < read["p12", False]
    line = spark.read.parquet("/root/testdata/sf0.1/lineitem.parquet").join(F.broadcast(spark.range(9).withColumnRenamed("id", "times"))).drop("times")
    g = GridTable.create(line, fs.scratch(spark, "t-lines"), w.q6_policy(), [Header.sum(w.REVENUE, "revenue")], files=8, page_rows=page)
    rows = {}
    for headers in (True, False):
        plan = g.plan(GridQuery(w.Q6, w._Q6_OUT), headers=headers)
        asked, foot = plan.records_read().first()[0], measures.scan_footprint(plan.run(), f"{g.path}/data")
        assert foot["rows"] <= 1.5 * asked + page * foot["files"], (headers, asked, foot)
        rows[headers] = foot["rows"]
    assert rows[True] < rows[False]


def test_plan_is_honest_and_pushed_down(spark, grid):
    q = GridQuery((Range("u", 0, 10), Range("day", DAY0, DAY0 + timedelta(days=4))), AGGS[:1])
    plan = grid.plan(q, headers=False)
    text = plan.explain()
    assert "PushedFilters" in text and "g_u" in text.split("PushedFilters")[1] and "CartesianProduct" not in text
    data, keys = grid.data(), plan.cells.select(*[F.col(c).alias(f"k_{c}") for c in POLICY.columns]).distinct()
    same = [data[c].eqNullSafe(keys[f"k_{c}"]) for c in POLICY.columns]
    assert data.join(keys, same[0] & same[1] & same[2] & same[3], "left_semi").count() == plan.records_read().first()[0]
    foot = measures.scan_footprint(plan.run(), f"{grid.path}/data")
    assert 0 < foot["rows"] <= rows_in(grid) and measures.scan_metrics(spark, f"{grid.path}/data", None)["files"] >= 3
    cost = measures.estimate(plan).first()
    assert cost["rows"] == plan.records_read().first()[0]
    assert all(t > 0 for t in measures.timed_query(grid, q))


def test_union_of_boxes(grid, rows):
    boxes = [(Range("u", 0, 10),), (Range("u", 10, 20), Range.eq("r", 1))]
    got = plan_union(grid, boxes, AGGS).first()
    assert got == rows.where("(u >= 0 and u < 10) or (u >= 10 and u < 20 and r = 1)").agg(*[a.over_rows() for a in AGGS]).first()
    with pytest.raises(ValueError):
        plan_union(grid, [(Range("u", 0, 10),), (Range("u", 5, 12),)], AGGS)


def test_baselines(rows):
    base = rows.withColumn("file", F.lit("f")).withColumn("block", F.expr("k div 100"))
    ranges = (Range("u", 0, 10), Range.eq("r", 1))
    want = Scan(rows, POLICY).query(ranges, AGGS).first()
    index = CompactIndex(base, ["r", "day"], POLICY)
    assert index.query(ranges, AGGS).first() == want
    assert index.stats().first()["tuple_blocks"] >= index.stats().first()["tuples"]
    agg = AggregateIndex(base, ["u", "r"], POLICY)
    n = (Agg("count", "*", "n"),)
    assert agg.applicable(ranges, n)[0] and agg.query(ranges, n).first()["n"] == want["n"]
    assert not agg.applicable(ranges, AGGS)[0] and agg.query(ranges, AGGS).first() == want
    assert not agg.applicable((Range.eq("day", DAY0),), n)[0]
    bits = BitmapIndex(rows, ["kind", "r"], "k")
    v = F.col("value")
    cond = {"kind": v.isin("a", "b"), "r": v == "1"}
    exact = rows.where("kind in ('a', 'b') and r = 1")
    assert bits.count(cond).first()["n"] == exact.count()
    assert sorted(x.k for x in bits.rows(cond).collect()) == sorted(x.k for x in exact.collect())


def test_cuts_and_advisor(spark, rows):
    d = quantile_cuts(rows, "u", 4)
    g = GridTable.create(rows, fs.scratch(spark, "t-cuts"), SplitPolicy([d, Dim("r", 0, 1)]), HEADERS[:1], files=2)
    q = GridQuery((Range("u", 2, 25),), (Agg("sum", "p", "s"),))
    assert g.query(q).first() == Scan(rows, g.policy).query(q.ranges, q.aggs).first()
    fine = SplitPolicy([Dim("u", 0, 1), Dim("r", 0, 1)])
    best, table = recommend_policy(rows, fine, [(Range("u", 0, 20),)], {"u": [1, 5, 20]}, sample=1.0, lookup_cost=1.0, row_cost=0.001)
    assert table.count() == 3 and best.dim("u").width == 20  # lookups dear, rows cheap: wide cells
    best, _ = recommend_policy(rows, fine, [(Range("u", 0, 17),)], {"u": [1, 5, 20]}, sample=1.0, lookup_cost=0.001, row_cost=1.0)
    assert best.dim("u").width == 1


# ---- statements, spelling, writers ---------------------------------------------------------------


def test_quoted_text_in_headers_keeps_its_case(spark):
    df = spark.createDataFrame([(k % 7, "View" if k % 3 else "view", Decimal(k)) for k in range(90)], "u long, t string, p decimal(12,2)")
    own = "case when t = 'View' then p end"
    g = GridTable.create(df, fs.scratch(spark, "t-case"), SplitPolicy([Dim("u", 0, 2)]), [Header.sum(own, "seen")], files=2)
    for text in ("case when t = 'view' then p end", "case when t = 'View' then p end", "CASE  WHEN t='View'  THEN p END", "case when t = ' View' then p end"):
        q = GridQuery((Range("u", 1, 6),), (Agg("sum", text, "s"),))
        assert g.plan(q).headers == (canonical(text) == canonical(own))
        assert g.query(q).first()[0] == df.where("u >= 1 and u < 6").agg(F.expr(f"sum({text})")).first()[0]


@pytest.fixture(scope="module")
def named(spark, grid):
    grid.register("t_named")
    return grid


CONDITIONS = [
    "u >= 7 AND u < 20 OR r = 1",
    "(u >= 7 OR r = 1) AND day > '2024-01-03'",
    "u BETWEEN 3 AND 19 AND NOT (r = 2)",
    "NOT u > 5 AND 1 <= r",
    "u NOT BETWEEN 5 AND 9",
    "CASE WHEN u > 3 AND r < 2 THEN kind = 'a' ELSE kind = 'b' END",
    "kind = 'x AND y' OR kind = 'a' AND u = 4",
    "u IN (1, 2, 3) AND x BETWEEN 0.01 AND 0.28",
    "u <= 17.5 AND day = date'2024-01-05'",
    "u > -3 AND 12 > u AND p IS NOT NULL",
    "u = NULL AND r = 1",
    "u + 1 > 5 AND r >= 1 and day >= date'2023-12-31'",
]


@pytest.mark.parametrize("where", CONDITIONS)
def test_statement_equals_spark(spark, named, where):
    for text in (f"SELECT sum(p) AS s, count(*) AS n, count(p) AS c FROM t_named WHERE {where}", f"SELECT kind, max(p) AS hi FROM t_named WHERE {where} GROUP BY kind", f"SELECT k, p * 2 AS twice FROM t_named WHERE {where}"):
        assert sorted(map(str, sql_front.sql(spark, text).collect())) == sorted(map(str, spark.sql(text).collect())), text


def test_statements_meet_the_planner_or_spark(spark, named, monkeypatch):
    seen = []
    monkeypatch.setattr(type(named), "query", lambda self, q, *a, _own=type(named).query, **k: (seen.append(q), _own(self, q, *a, **k))[1])
    assert sql_front.sql(spark, "SELECT sum(p) AS s FROM t_named WHERE u >= 5 AND u < 20;").first() == spark.sql("SELECT sum(p) AS s FROM t_named WHERE u >= 5 AND u < 20").first()
    assert len(seen) == 1 and len(seen[0].ranges) == 2 and seen[0].residual is None
    for text in ("SELECT a.k FROM t_named a JOIN t_named b USING (k) WHERE a.u = 1", "SELECT sum(p) + 1 AS x FROM t_named GROUP BY r HAVING count(*) > 3", "SELECT kind, r, count(*) AS n FROM t_named GROUP BY kind, r ORDER BY n LIMIT 2", "SELECT count(DISTINCT r) FILTER (WHERE u > 1) AS n FROM t_named"):
        assert sorted(map(str, sql_front.sql(spark, text).select("*").collect())) == sorted(map(str, spark.sql(text).collect()))


LITERALS = st.integers(-14, 42)
TERM = st.one_of(
    st.tuples(st.sampled_from(["u", "r"]), st.sampled_from([">", ">=", "<", "<=", "="]), LITERALS).map(lambda t: f"{t[0]} {t[1]} {t[2]}"),
    st.tuples(LITERALS, st.sampled_from([">", ">=", "<", "<="]), st.just("u")).map(lambda t: f"{t[0]} {t[1]} {t[2]}"),
    st.tuples(LITERALS, LITERALS).map(lambda t: f"u BETWEEN {t[0]} AND {t[1]}"),
    st.sampled_from(["kind = 'a'", "day >= '2024-01-04'", "x <= 0.07", "p > 20"]),
)
CONDITION = st.recursive(TERM, lambda c: st.one_of(st.tuples(c, st.sampled_from(["AND", "OR"]), c).map(lambda t: f"({t[0]}) {t[1]} ({t[2]})"), st.tuples(c, c, c).map(lambda t: f"{t[0]} AND {t[1]} OR {t[2]}"), c.map(lambda t: f"NOT ({t})")), max_leaves=4)


@settings(max_examples=25, deadline=None, suppress_health_check=list(HealthCheck))
@given(where=CONDITION)
def test_any_statement_equals_spark(spark, named, where):
    text = f"SELECT sum(p) AS s, count(*) AS n FROM t_named WHERE {where}"
    assert sql_front.sql(spark, text).first() == spark.sql(text).first()


def batch_of(rows, k):
    return rows.where(F.col("k") % 6 == k)


def total(rows, ks):
    return rows.where((F.col("k") % 6).isin(*ks)).count()


def test_batches_survive_compaction_and_replay(spark, rows):
    g = GridTable.create(batch_of(rows, 0), fs.scratch(spark, "t-replay"), POLICY, HEADERS[:1], files=1)
    assert g.append(batch_of(rows, 1), 1, files=1) and g.append(batch_of(rows, 2), 2, files=1)
    g.compact()
    assert g.append(batch_of(rows, 3), 3, files=1)  # the next batch of the stream is no retry
    assert not g.append(batch_of(rows, 1), 1) and not g.append(batch_of(rows, 0), 0)  # a replayed batch is one
    g.compact()
    assert not GridTable.open(spark, g.path).append(batch_of(rows, 2), 2)
    assert rows_in(GridTable.open(spark, g.path)) == total(rows, (0, 1, 2, 3)) and g.meta["ingested"] == [[0, 3]]
    g.add_header(HEADERS[1])
    g.vacuum()
    g = GridTable.open(spark, g.path)
    assert len(g.meta["segments"]) == 1 and fs.names(spark, f"{g.path}/catalog") == [f"gen={g.meta['generation']}"] and len(fs.names(spark, f"{g.path}/meta")) == 1
    assert g.query(GridQuery((), (Agg("count", "*", "n"), Agg("count", "p", "c")))).first() == (total(rows, (0, 1, 2, 3)), rows.where("k % 6 < 4").where("p is not null").count())


def test_two_writers_lose_nothing(spark, rows):
    a = GridTable.create(batch_of(rows, 0), fs.scratch(spark, "t-writers"), POLICY, HEADERS[:1], files=1)
    b, c = GridTable.open(spark, a.path), GridTable.open(spark, a.path)
    assert a.append(batch_of(rows, 1), 10, files=1) and b.append(batch_of(rows, 2), 11, files=1)
    assert not b.append(batch_of(rows, 1), 10) and sorted(x["batch"] for x in GridTable.open(spark, a.path).meta["segments"].values()) == [0, 10, 11]

    # between the writing and the publishing of one handle, others publish
    def others(text=fs.publish_text, done=[]):  # noqa: B006
        def publish(s, path, content):
            if not done:
                done.append(1)
                b.add_header(HEADERS[1])
                b.append(batch_of(rows, 4), 12, files=1)
            return text(s, path, content)

        return publish

    with pytest.MonkeyPatch.context() as m:
        m.setattr(fs, "publish_text", others())
        assert c.append(batch_of(rows, 3), 13, files=1)
    g = GridTable.open(spark, a.path)
    q = GridQuery((Range("u", -5, 30),), (Agg("count", "*", "n"), Agg("count", "p", "c")))
    assert g.plan(q).headers and rows_in(g) == total(rows, (0, 1, 2, 3, 4)) and g.query(q).first() == g.query(q, headers=False).first()

    def replaced(s, path, content, text=fs.publish_text, done=[]):  # noqa: B006
        if not done:
            done.append(1)
            b.compact()
        return text(s, path, content)

    with pytest.MonkeyPatch.context() as m:
        m.setattr(fs, "publish_text", replaced)
        with pytest.raises(ConflictError):
            c.compact()
    assert rows_in(GridTable.open(spark, a.path)) == total(rows, (0, 1, 2, 3, 4))


def test_a_failed_attempt_leaves_nothing(spark, rows):
    g = GridTable.create(batch_of(rows, 0), fs.scratch(spark, "t-fail"), POLICY, HEADERS[:1], files=1)
    with pytest.MonkeyPatch.context() as m:
        m.setattr(fs, "publish_text", lambda *a: (_ for _ in ()).throw(OSError("lost")))
        with pytest.raises(OSError):
            g.append(batch_of(rows, 1), 1, files=1)
    again = GridTable.open(spark, g.path)
    assert rows_in(again) == total(rows, (0,)) and again.append(batch_of(rows, 1), 1, files=1)
    again.vacuum()
    assert len(fs.names(spark, f"{g.path}/data")) == 2 and rows_in(GridTable.open(spark, g.path)) == total(rows, (0, 1))


def test_stores_answer_alike(spark, grid, rows):
    q = GridQuery((Range("u", 0, 30),), AGGS)
    kept, none = CachedEntries(), CachedEntries(most_bytes=0)
    for store in (kept, none):
        g = GridTable.open(spark, grid.path, store)
        assert g.query(q).first() == g.query(q).first() == grid.query(q).first()
    assert len(kept.held) == 1 and not none.held
    assert GridTable.open(spark, grid.path, kept).entries().storageLevel.useMemory is False  # a projection over what is held


# ---- streams, sinks, methods ---------------------------------------------------------------------


def test_late_and_repeated_readings_of_a_stream(spark, tmp_path):
    """Late rows reach their old cells; repeats are dropped within a batch and across batches; bad rows go aside."""
    shape = "u long, day date, p decimal(12,2)"
    day = [DAY0 + timedelta(days=k) for k in range(20)]
    batches = [
        [(1, day[9], 5), (1, day[9], 5), (2, day[10], 7), (3, None, 1)],
        [(1, day[9], 5), (4, day[2], 9), (2, day[11], None), (3, None, 1)],
        [(2, day[10], 7), (None, day[9], 2), (5, day[19], 3)],
    ]
    policy = SplitPolicy([Dim("u", 0, 2), Dim("day", DAY0, 1, "d")], "day")
    to_frame = lambda b: spark.createDataFrame([(u, d, None if p is None else Decimal(p)) for u, d, p in b], shape)
    grid = GridTable.create(to_frame([]), str(tmp_path / "grid"), policy, [Header.sum("p")], files=1)
    landing = str(tmp_path / "landing")
    for k, b in enumerate(batches):
        to_frame(b).coalesce(1).write.mode("append").parquet(landing)
        q = stream_into_grid(spark.readStream.schema(shape).parquet(landing), grid, str(tmp_path / "state"), F.col("p").isNotNull(), ["u", "day"], str(tmp_path / "aside"), across_batches=True)
        q.awaitTermination()
        assert len(grid.refresh().meta["ingested"]) == 1 and grid.meta["ingested"][0] == [0, k + 1]
    want = {(u, d, p) for b in batches for u, d, p in b if p is not None}
    got = [(r.u, r.day, int(r.p)) for r in grid.data().collect()]
    assert len(got) == len(set(got)) and set(got) == want
    late = GridQuery((Range("day", day[2], day[3]),), (Agg("sum", "p", "s"),))
    assert grid.plan(late).headers and grid.query(late).first().s == 9
    assert spark.read.parquet(str(tmp_path / "aside")).count() == 1
    with pytest.raises(ValueError):
        unseen(to_frame([]), grid, ["u"])


def test_repeats_within_the_watermark(spark, tmp_path):
    rows = [(k, DAY0) for k in (1, 1, 2, 3, 3, 3)]
    for _ in range(2):
        spark.createDataFrame(rows, "u long, day date").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("u long, day date").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    out = str(tmp_path / "out")
    deduplicated(source, "day", ["u"]).writeStream.format("parquet").option("path", out).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    assert sorted(r.u for r in spark.read.parquet(out).collect()) == [1, 2, 3]


def test_silent_keys_are_reported_again_when_they_return(spark, tmp_path):
    at = lambda hours: datetime(2024, 1, 1) + timedelta(hours=hours)
    for k, b in enumerate([[(1, at(0)), (2, at(1))], [(2, at(40))], [(2, at(50))], [(1, at(60)), (2, at(61))], [(2, at(100))], [(2, at(101))]]):
        spark.createDataFrame(b, "user_id long, ts timestamp").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    got = windows.replay(spark, str(tmp_path / "in"), "t-silent", windows.silent, mode="append")
    found = sorted((r.user_id, r.last_seen) for r in got.collect())
    assert [x for x in found if x[0] == 1] == [(1, at(0)), (1, at(60))] and (2, at(101)) not in found


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv"])
def test_formats_round_trip(rows, kind, tmp_path):
    path = str(tmp_path / kind)
    loaders.save(rows, path, kind, compression="gzip" if kind in ("json", "csv") else None, partition_by=["kind"])
    got = loaders.load(rows.sparkSession, path, kind, None if kind in ("parquet", "orc") else rows.schema)
    key = lambda r: r["k"]
    assert sorted(got.select(*rows.columns).collect(), key=key) == sorted(rows.collect(), key=key)


def test_sources_and_sinks(spark, rows, tmp_path):
    rows.select("kind").coalesce(1).write.text(str(tmp_path / "text"))
    assert loaders.load(spark, str(tmp_path / "text"), "text").groupBy("value").count().count() == 3
    with pytest.raises(ValueError):
        loaders.load(spark, str(tmp_path / "text"), "csv")
    with pytest.raises(ValueError):
        loaders.load(spark, str(tmp_path / "text"), "xml")
    stats = rows.groupBy("kind").agg(F.count("*").alias("n"))
    loaders.save_jdbc(stats, "jdbc:derby:memory:served;create=true", "stats", driver="org.apache.derby.iapi.jdbc.AutoloadedDriver")
    back = loaders.load_jdbc(spark, "jdbc:derby:memory:served", "stats", driver="org.apache.derby.iapi.jdbc.AutoloadedDriver")
    assert sorted(tuple(r) for r in back.collect()) == sorted(tuple(r) for r in stats.collect())


def test_archive_keeps_one_row_a_key(spark):
    old = spark.createDataFrame([(1, "a"), (2, "b"), (None, "n")], "id long, v string")
    new = spark.createDataFrame([(2, "B", 1), (2, "C", 2), (3, "c", 1), (None, "N", 1)], "id long, v string, version int")
    got = loaders.synchronise_archive(old, new, "id", "version")
    assert {(r.id, r.v) for r in got.collect()} == {(1, "a"), (2, "C"), (3, "c"), (None, "N")} and got.count() == 4
    again = loaders.synchronise_archive(got, new, "id", "version")
    assert sorted(map(str, again.collect())) == sorted(map(str, got.collect()))


def test_every_method_answers_alike(grid, rows):
    """A grid with and without headers, a scan and a sharded store behind one protocol."""
    users = rows.sparkSession.createDataFrame([(k, f"n{k}") for k in range(-12, 40, 2)], "u long, name string")
    store = ShardedStore(rows, users, "u", ["u", "r", "day"], POLICY, nodes=3, chunks=2)
    methods = [Scan(rows, POLICY), GridMethod(grid), GridMethod(grid, False), store]
    for ranges in [(), (Range("u", 0, 10),), (Range.eq("u", 7),), (Range.open("u", 6, 8), Range.eq("r", 1)), (Range.eq("u", 10**6),)]:
        assert len({m.query(ranges, AGGS).first() for m in methods}) == 1
        read = [m.records_read(ranges).first().records_read for m in methods]
        assert all(0 <= n <= 1500 for n in read) and read[1] <= read[2] <= read[0]
    assert sum(r.n for r in store.shard_sizes().collect()) == 1500 and store.shard_sizes().where("n > 0").count() >= 5
    joined = store.join_users((Range("u", 0, 10),))
    assert "Exchange" not in joined._jdf.queryExecution().sparkPlan().toString() and joined.count() == rows.where("u >= 0 and u < 10 and u % 2 = 0").count()
    whole_scan, one_key = (measures.scan_footprint(store.rows(r)) for r in ((), (Range.eq("u", 7),)))
    assert one_key["files"] < whole_scan["files"] == 6 and one_key["rows"] < whole_scan["rows"] == 1500
