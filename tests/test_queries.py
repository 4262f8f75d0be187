"""Every query with SQL agrees with DuckDB, and the pinned counts of the workloads hold."""

from __future__ import annotations

import importlib
import sys
from datetime import date, datetime, timedelta

import oracle
import pytest
from conftest import SF001, SF01

from cubegrid import catalogue, workloads
from cubegrid.plans.planner import GridQuery, records_read_by
from cubegrid.plans.predicate import Range


@pytest.fixture(scope="module")
def con():
    return oracle.connect(SF01)


@pytest.mark.parametrize("name", sorted(catalogue.ORACLE))
def test_oracle(spark, con, name):
    assert oracle.difference(catalogue.QUERIES[name](spark, SF01), con, catalogue.ORACLE[name]) is None


@pytest.mark.parametrize("name", sorted(set(catalogue.QUERIES) - set(catalogue.ORACLE)))
def test_rows_only(spark, name):
    assert catalogue.QUERIES[name](spark, SF01).count() > 0


def test_entry(spark):
    import __spark_entry__ as e

    assert len(e.entry(spark).collect()) == 1 and set(e.oracle_sql()) <= set(e.queries())
    assert catalogue.ENTRY(spark, SF001).first()["revenue"] == pytest.approx(365888.5609)


def test_pinned_counts(spark):
    reads = {(r.method, r.query): r.records_read for r in workloads.reads_agg_meter(spark, SF01).collect()}
    assert reads[("grid_l", "p05")] == 1360 and reads[("grid_m", "p05")] == 238 and reads[("grid_s", "p12")] == 66
    assert reads[("compact", "point")] == 500 and reads[("compact", "p12")] == 5500
    group = {(r.method, r.query): r.records_read for r in workloads.reads_group_meter(spark, SF01).collect()}
    assert [group[(m, "p05")] for m in workloads.GRIDS] == [1360, 616, 513]
    assert all(reads[(m, "point")] == group[(m, "point")] for m in workloads.GRIDS)
    q6 = {r.method: (r.records_read, r.accurate) for r in workloads.reads_q6(spark, SF01).collect()}
    assert q6["grid_headers"] == (656, 1175) and q6["grid_scan"] == (1310, 1175) and q6["compact_2d"][0] == q6["compact_3d"][0] == 60000


def test_joins_take_every_row(spark, tmp_path):
    """The full and the as-of join over whole tables, against brute force on sides that differ."""
    moment = datetime(2024, 1, 10)
    customers, suppliers = range(8), range(5, 12)
    orders = [(k, k % 4, moment - timedelta(days=9516 - k % 3)) for k in range(23)]
    events = [(k, k % 3, moment + timedelta(hours=7 * k - 20)) for k in range(12)]
    spark.createDataFrame([(k,) for k in customers], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(k,) for k in suppliers], "s_suppkey long").write.parquet(f"{tmp_path}/supplier.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(events, "event_id long, user_id long, ts timestamp_ntz").write.parquet(f"{tmp_path}/events.parquet")
    full = catalogue.QUERIES["op_join_full"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, full)) == sorted((k, k not in customers, k not in suppliers) for k in {*customers, *suppliers})
    asof = {r.o_orderkey: r.event_id for r in catalogue.QUERIES["op_join_asof"](spark, str(tmp_path)).collect()}
    want = {k: max(((ts, e) for e, user, ts in events if user == who and ts <= day + timedelta(days=9516)), default=(None, None))[1] for k, who, day in orders}
    assert asof == want and len(asof) == 23 and {None} < set(asof.values())


def test_joins_take_every_row_of_the_tables(spark):
    at = {t: spark.read.parquet(f"{SF001}/{t}.parquet").count() for t in ("customer", "orders")}
    assert catalogue.QUERIES["op_join_full"](spark, SF001).where("not only_supplier").count() == at["customer"]
    assert catalogue.QUERIES["op_join_asof"](spark, SF001).count() == at["orders"]


def test_table_function_lists_cells_of_the_table(spark, tmp_path):
    """The worked geometry has nine cells and one inner; the query lists cells of the boxes of the customers it reads."""
    from cubegrid.functions.udx import CellsInBox

    cells = [(a, b, (a, b) == (2, 1)) for a in (1, 2, 3) for b in (0, 1, 2)]
    assert list(CellsInBox().eval(1, 3, 5, 12, 11, 2, 12, 16)) == cells
    spark.createDataFrame([(0, 0), (994, 3), (40, None), (None, 2)], "c_custkey long, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    got = sorted(map(tuple, catalogue.QUERIES["fn_udtf_cells"](spark, str(tmp_path)).collect()))
    # customer 0 covers users 5 to 704 and 12 to 15 of the other, customer 994 users 999 to 1698 and 15 to 18
    assert got == [(0, 0, 1, 0), (0, 1, 1, 0), (0, 2, 1, 0), (1, 0, 1, 0), (1, 1, 1, 0), (1, 2, 2, 0), (1, 3, 1, 0), (2, 2, 1, 1), (2, 3, 1, 1), (3, 2, 1, 0), (3, 3, 1, 0)]


def test_amplification_of_empty_answers(spark, tmp_path):
    """No reading in the point box, readings without a user: ratios over nothing as SQL has them."""
    moment = datetime(2024, 1, 3)
    events = [(k, k % 90, moment + timedelta(hours=5 * k), "view", k / 4) for k in range(120)]
    spark.createDataFrame(events, "event_id long, user_id long, ts timestamp_ntz, event_type string, value double").write.parquet(f"{tmp_path}/events.parquet")
    spark.createDataFrame([(k, k % 25) for k in range(80)], "c_custkey long, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    con = oracle.duckdb.connect()
    for t in ("events", "customer"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    got = catalogue.QUERIES["measure_amplification_meter"](spark, str(tmp_path))
    assert oracle.difference(got, con, catalogue.ORACLE["measure_amplification_meter"]) is None
    assert {r.selectivity for r in got.where("query = 'point'").collect()} == {0.0}


def test_reads_go_through_each_table_once(spark):
    """Three catalogs, the index with the readings, and the exact counts: no plan for each figure, which the driver would hold all at once."""
    leaves = lambda name: catalogue.QUERIES[name](spark, SF001)._jdf.queryExecution().optimizedPlan().collectLeaves().size()
    assert leaves("reads_agg_meter") == leaves("reads_group_meter_large") == 6
    assert leaves("measure_amplification_meter") == 7  # and all events


def test_reads_of_several_queries_at_once(spark):
    """One pass gives what each query gives by itself, empty boxes and free dimensions too."""
    boxes = {sel: workloads.box(sel) for sel in (*workloads.SELECTIVITIES, "partial")}
    boxes |= {"none": workloads.box("point")[:2] + (Range.open("day", date(2024, 1, 20), date(2024, 1, 20)),), "late": (Range.eq("day", date(2025, 1, 1)),), "all": ()}
    grid = workloads.meter_grid(spark, SF001, "grid_m")
    plans = {f"{sel}_{headers}": grid.plan(GridQuery(ranges, workloads.SUM), headers=headers) for sel, ranges in boxes.items() for headers in (False, True)}
    got = records_read_by(plans).first().asDict()
    assert got == {name: plan.records_read().first()[0] for name, plan in plans.items()} and got["all_False"] == 1000
    compact = workloads.meter_compact(spark, SF001)
    got = compact.records_read_by(boxes).first().asDict()
    assert got == {name: compact.records_read(ranges).first()[0] for name, ranges in boxes.items()} and got["none"] == got["late"] == 0


SF1 = "/root/testdata/sf0.1"  # 100,000 events
AT_SF1 = ["agg_p05_grid_m", "agg_p12_scan", "group_point_compact", "join_p05_sharded", "grid_cells_meter_l", "reads_agg_meter", "measure_amplification_meter", "extra_pred_grid_m", "grid_sql_select", "grid_sql_create", "partition_compact_agg", "append_equals_rebuild"]
AT_SF1_LARGE = ["agg_p05_grid_m_large", "agg_p12_scan_large", "group_p05_grid_l_large", "join_point_grid_s_large", "partial_grid_l_large", "grid_cells_meter_m_large", "reads_group_meter_large"]


@pytest.mark.parametrize("name", [*AT_SF1, *AT_SF1_LARGE])
def test_sql_holds_at_every_size(spark, name):
    """A query answers its own SQL however many events there are."""
    assert oracle.difference(catalogue.QUERIES[name](spark, SF1), oracle.connect(SF1), catalogue.ORACLE[name]) is None


def test_pinned_counts_large(spark):
    reads = {(r.method, r.query): (r.records_read, r.accurate) for r in workloads.reads_agg_meter_large(spark, SF1).collect()}
    assert [reads[(m, "p05")] for m in (*workloads.GRIDS, "compact")] == [(12837, 5097), (1517, 5097), (162, 5097), (35000, 5097)]
    assert catalogue.QUERIES["agg_p12_grid_m_large"](spark, SF1).first()["sum_power"] == pytest.approx(600582.34)


def test_without_llm(monkeypatch):
    """The entry module stands without the llm subpackage and the pipeline."""
    for name in ("cubegrid.llm", "cubegrid.llm.registry", "corpus_pipeline"):
        monkeypatch.setitem(sys.modules, name, None)
    import __spark_entry__ as e

    again = importlib.reload(e)
    try:
        assert "q6_grid_headers" in again.queries() and "pipeline" not in again.queries()
    finally:
        monkeypatch.undo()
        importlib.reload(e)


def test_except_and_unoracled_rows(spark):
    """What has no SQL, against exact values."""
    q = catalogue.QUERIES
    assert q["op_except"](spark, SF01).count() > 0
    exact = workloads.meter(spark, SF01)
    for r in q["op_coalesce_ranges"](spark, SF01).collect():
        assert r["ranges"] > 0 and r["rows"] > 0
    reads = {(r.method, r.query): r.records_read for r in workloads.reads_group_meter(spark, SF01).collect()}
    assert sum(r["rows"] for r in q["op_coalesce_ranges"](spark, SF01).collect()) == reads[("grid_m", "p05")]
    shares = {r.event_type: r["count"] for r in exact.groupBy("event_type").count().collect()}
    for r in q["op_sample"](spark, SF01).collect():
        assert abs(r.n - 0.1 * shares[r.event_type]) < 5 * (0.09 * shares[r.event_type]) ** 0.5
    sizes = {r.method: (r.bytes, r.index_rows) for r in q["measure_index_bytes"](spark, SF01).collect()}
    entries = {r.method: r.entries for r in q["grid_entry_counts"](spark, SF01).collect()}
    assert all(sizes[m][1] >= entries[m] and sizes[m][0] > 0 for m in workloads.GRIDS)
    assert sizes["grid_l"][0] < sizes["grid_m"][0] < sizes["grid_s"][0] and sizes["compact_2d"][0] < sizes["compact_3d"][0]


def test_policy_advisor_costs(spark):
    """The modelled costs, from cells and rows counted one by one."""
    import duckdb

    con = oracle.connect(SF01)
    want = []
    for k in (1, 5, 25, 100):
        w = workloads._WIDTHS[False]["s"] * k
        total = 0.0
        for sel in workloads.SELECTIVITIES:
            u, r, d = workloads._BOXES[False][sel]
            others = f"region_id > {r[0]} AND region_id < {r[1]} AND day > DATE '2024-01-{d[0]:02d}' AND day < DATE '2024-01-{d[1]:02d}'"
            rel = f"user_id // {w} BETWEEN {(u[0] + 1) // w} AND {(u[1] - 1) // w} AND {others}"
            rim = f"{rel} AND NOT (user_id // {w} >= {-(-(u[0] + 1) // w)} AND user_id // {w} < {u[1] // w})"
            one = lambda what, where: con.sql(f"WITH {workloads.METER} SELECT {what} FROM meter WHERE {where}").fetchall()[0][0]
            total += one(f"count(DISTINCT (user_id // {w}, region_id, day))", rel) + 0.02 * 0.5 * (one("count(*)", rim) + one("count(*)", rel))
        want.append(total)
    got = sorted(r.cost for r in catalogue.QUERIES["policy_advisor"](spark, SF01).collect())
    assert isinstance(con, duckdb.DuckDBPyConnection) and got == pytest.approx(sorted(want))
