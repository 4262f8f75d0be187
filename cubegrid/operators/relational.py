"""The relational operators around range queries, one query each, beside their SQL."""

from __future__ import annotations

from datetime import date

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubegrid.operators.joins import asof_join, range_join, salted_join
from cubegrid.registry import Registry
from cubegrid.sources.loaders import table
from cubegrid.workloads import METER, meter, meter_compact, meter_grid, meter_shards

query = Registry()


def _m(spark, sf_dir) -> DataFrame:
    return meter(spark, sf_dir).drop("file", "block")


# ---- filters and projections ----------------------------------------------------------------------


@query("op_filter_range", f"WITH {METER} SELECT rid, user_id, CAST(power AS DOUBLE) AS power FROM meter WHERE power BETWEEN 20 AND 40 AND day >= DATE '2024-01-10' AND region_id IS NOT NULL")
def op_filter_range(s, d):
    rows = _m(s, d).where(F.col("power").between(20, 40) & (F.col("day") >= date(2024, 1, 10)) & F.col("region_id").isNotNull())
    return rows.select("rid", "user_id", F.col("power").cast("double").alias("power"))


@query("op_filter_in", f"WITH {METER} SELECT rid, event_type FROM meter WHERE region_id IN (1, 5, 9) AND (event_type LIKE 'p%' OR event_type = 'view')")
def op_filter_in(s, d):
    return _m(s, d).where(F.col("region_id").isin(1, 5, 9) & (F.col("event_type").like("p%") | (F.col("event_type") == "view"))).select("rid", "event_type")


@query("op_project_expr", "SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DOUBLE) AS net, upper(l_returnflag) AS flag FROM lineitem WHERE l_quantity > 45")
def op_project_expr(s, d):
    price, disc = F.col("l_extendedprice").cast("decimal(18,2)"), F.col("l_discount").cast("decimal(4,2)")
    return table(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_linenumber", (price * (1 - disc)).cast("double").alias("net"), F.upper("l_returnflag").alias("flag"))


# ---- joins ------------------------------------------------------------------------------------------


@query("op_join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def op_join_broadcast(s, d):
    """``nation`` has 25 rows by definition, so it may be broadcast."""
    nations = table(s, d, "nation").select("n_nationkey", "n_name")
    return table(s, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("op_join_smj", "SELECT o_orderpriority, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def op_join_smj(s, d):
    lines = table(s, d, "lineitem").select("l_orderkey", F.col("l_extendedprice").cast("decimal(18,2)").alias("price"))
    joined = table(s, d, "orders").select("o_orderkey", "o_orderpriority").hint("merge").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("price").cast("double").alias("total"))


@query("op_join_bucketed", f"WITH {METER} SELECT c_name AS user_name, count(*) AS n FROM meter JOIN customer ON user_id = c_custkey WHERE day < DATE '2024-01-04' GROUP BY c_name")
def op_join_bucketed(s, d):
    """Both sides hold the same buckets: no exchange before the join."""
    from cubegrid.plans.predicate import Range

    return meter_shards(s, d).join_users((Range("day", hi=date(2024, 1, 4)),)).groupBy("user_name").agg(F.count("*").alias("n"))


@query("op_join_salted", f"WITH {METER} SELECT event_type, weight, count(*) AS n FROM meter JOIN (SELECT event_type AS t, count(*) AS weight FROM meter GROUP BY event_type) ON event_type = t GROUP BY ALL")
def op_join_salted(s, d):
    """A few hot keys, dealt over copies of the small side."""
    facts = _m(s, d).select("rid", "event_type")
    weights = facts.groupBy("event_type").agg(F.count("*").alias("weight"))
    return salted_join(facts, weights, "event_type", 4).groupBy("event_type", "weight").agg(F.count("*").alias("n"))


@query("op_join_left", f"WITH {METER}, m AS (SELECT user_id, count(*) AS n FROM meter GROUP BY user_id) SELECT c_custkey, coalesce(n, 0) AS n FROM customer LEFT JOIN m ON c_custkey = user_id")
def op_join_left(s, d):
    per_user = _m(s, d).groupBy("user_id").agg(F.count("*").alias("n"))
    return table(s, d, "customer").join(per_user, F.col("c_custkey") == F.col("user_id"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n"))


@query("op_join_full", "SELECT coalesce(c_custkey, s_suppkey) AS id, c_custkey IS NULL AS only_supplier, s_suppkey IS NULL AS only_customer FROM customer FULL JOIN supplier ON c_custkey = s_suppkey")
def op_join_full(s, d):
    """All customers and all suppliers; what only one side has depends on the tables alone."""
    a = table(s, d, "customer").select(F.col("c_custkey").alias("c"))
    b = table(s, d, "supplier").select(F.col("s_suppkey").alias("u"))
    return a.join(b, F.col("c") == F.col("u"), "full").select(F.coalesce("c", "u").alias("id"), F.col("c").isNull().alias("only_supplier"), F.col("u").isNull().alias("only_customer"))


@query("op_semi_blocks", f"WITH {METER}, b AS (SELECT *, rid // ((SELECT count(*) FROM events) // 20) AS block FROM meter) SELECT CAST(block AS BIGINT) AS block, count(*) AS n FROM b WHERE block IN (SELECT block FROM b WHERE region_id = 3 AND day = DATE '2024-01-08') GROUP BY block")
def op_semi_blocks(s, d):
    """Whole blocks that hold a matching tuple."""
    from cubegrid.plans.predicate import Range

    hits = meter_compact(s, d).blocks((Range.eq("region_id", 3), Range.eq("day", date(2024, 1, 8))))
    return meter(s, d).join(hits, ["file", "block"], "left_semi").groupBy("block").agg(F.count("*").alias("n"))


@query("op_anti_missing", f"WITH {METER}, days AS (SELECT DISTINCT day FROM meter), us AS (SELECT DISTINCT user_id FROM meter) SELECT user_id, day FROM us, days WHERE NOT EXISTS (SELECT 1 FROM meter m WHERE m.user_id = us.user_id AND m.day = days.day)")
def op_anti_missing(s, d):
    """Users without a reading on a day. The calendar has one row per day, so it is broadcast."""
    m = _m(s, d)
    days = m.agg(F.min("day").alias("a"), F.max("day").alias("b")).select(F.explode(F.sequence("a", "b")).alias("day")).join(m.select("day").distinct(), "day", "left_semi")
    users = m.select("user_id").distinct()
    return users.join(F.broadcast(days)).join(m.select("user_id", "day").distinct(), ["user_id", "day"], "left_anti")


@query("op_cross_calendar", f"WITH {METER} SELECT region_id, day, (SELECT count(*) FROM meter m WHERE m.region_id = r.region_id AND m.day = c.day) AS n FROM (SELECT DISTINCT region_id FROM meter) r, (SELECT unnest(generate_series(DATE '2024-01-01', DATE '2024-01-30', INTERVAL 1 DAY))::DATE AS day) c")
def op_cross_calendar(s, d):
    """Regions by days, both short by definition, with their readings."""
    m = _m(s, d)
    days = s.range(30).select(F.date_add(F.lit(date(2024, 1, 1)), F.col("id").cast("int")).alias("day"))
    counts = m.groupBy("region_id", "day").agg(F.count("*").alias("n"))
    return m.select("region_id").distinct().join(F.broadcast(days)).join(counts, ["region_id", "day"], "left").select("region_id", "day", F.coalesce("n", F.lit(0)).alias("n"))


@query("op_join_range_boxes", "WITH r AS (SELECT p_partkey AS box, p_partkey * 25 AS lo, p_partkey * 25 + 60 AS hi FROM part WHERE p_size <= 10) SELECT box, count(*) AS n FROM orders JOIN r ON o_orderkey >= lo AND o_orderkey < hi GROUP BY box")
def op_join_range_boxes(s, d):
    """Many boxes over points by shared buckets."""
    boxes = table(s, d, "part").where("p_size <= 10").select(F.col("p_partkey").alias("box"), (F.col("p_partkey") * 25).alias("lo"), (F.col("p_partkey") * 25 + 60).alias("hi"))
    return range_join(table(s, d, "orders").select("o_orderkey"), "o_orderkey", boxes, "lo", "hi", 64).groupBy("box").agg(F.count("*").alias("n"))


@query("op_join_asof", "SELECT o_orderkey, max_by(event_id, (ts, event_id)) AS event_id FROM (SELECT o_orderkey, o_custkey, CAST(o_orderdate AS TIMESTAMP) + INTERVAL 9516 DAY AS t FROM orders) LEFT JOIN events ON user_id = o_custkey AND ts <= t GROUP BY o_orderkey")
def op_join_asof(s, d):
    """The last reading of the customer at or before a moment, for every order."""
    at = F.expr("o_orderdate + INTERVAL '9516' DAY")
    orders = table(s, d, "orders").select("o_orderkey", F.col("o_custkey").alias("user_id"), at.alias("t"))
    events = table(s, d, "events").select("user_id", "ts", "event_id")
    return asof_join(orders, events, ["user_id"], F.col("t"), F.col("ts"), ["event_id"]).select("o_orderkey", "event_id")


# ---- aggregation --------------------------------------------------------------------------------------


@query("op_agg_hash", f"WITH {METER} SELECT region_id, count(*) AS n, CAST(sum(power) AS DOUBLE) AS total, CAST(min(power) AS DOUBLE) AS lo, CAST(max(power) AS DOUBLE) AS hi, count(*) FILTER (WHERE power > 50) AS high FROM meter GROUP BY region_id")
def op_agg_hash(s, d):
    p = F.col("power")
    return _m(s, d).groupBy("region_id").agg(F.count("*").alias("n"), F.sum(p).cast("double").alias("total"), F.min(p).cast("double").alias("lo"), F.max(p).cast("double").alias("hi"), F.count_if(p > 50).alias("high"))


@query("op_agg_distinct", f"WITH {METER} SELECT day, count(DISTINCT user_id) AS users, count(DISTINCT region_id) AS regions FROM meter GROUP BY day")
def op_agg_distinct(s, d):
    return _m(s, d).groupBy("day").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("region_id").alias("regions"))


@query("op_agg_approx_distinct")
def op_agg_approx_distinct(s, d):
    """Distinct users from mergeable sketches per day."""
    per_day = _m(s, d).groupBy("day").agg(F.hll_sketch_agg("user_id").alias("sketch"))
    return per_day.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("users"))


@query("op_agg_percentile", f"WITH {METER} SELECT event_type, quantile_cont(CAST(power AS DOUBLE), 0.5) AS median, quantile_cont(CAST(power AS DOUBLE), 0.9) AS p90 FROM meter GROUP BY event_type")
def op_agg_percentile(s, d):
    p = F.col("power").cast("double")
    return _m(s, d).groupBy("event_type").agg(F.percentile(p, 0.5).alias("median"), F.percentile(p, 0.9).alias("p90"))


@query("op_rollup_region_day", f"WITH {METER} SELECT region_id, day, count(*) AS n, CAST(sum(power) AS DOUBLE) AS total FROM meter GROUP BY ROLLUP (region_id, day)")
def op_rollup_region_day(s, d):
    return _m(s, d).rollup("region_id", "day").agg(F.count("*").alias("n"), F.sum("power").cast("double").alias("total"))


@query("op_rollup_from_headers", f"WITH {METER} SELECT region_id, day, count(*) AS n, CAST(sum(power) AS DOUBLE) AS total FROM meter GROUP BY ROLLUP (region_id, day)")
def op_rollup_from_headers(s, d):
    """The same from cell headers: coarser groups are sums of cells, no row is read."""
    entries = meter_grid(s, d, "grid_l").entries()
    cells = entries.select(F.col("g_region_id").cast("int").alias("region_id"), F.date_add(F.lit(date(2024, 1, 1)), F.col("g_day").cast("int")).alias("day"), "n", "h_sum_power")
    return cells.rollup("region_id", "day").agg(F.sum("n").alias("n"), F.sum("h_sum_power").cast("double").alias("total"))


@query("op_cube", f"WITH {METER} SELECT region_id, event_type, count(*) AS n FROM meter GROUP BY CUBE (region_id, event_type)")
def op_cube(s, d):
    return _m(s, d).cube("region_id", "event_type").agg(F.count("*").alias("n"))


@query("op_grouping_sets", f"WITH {METER} SELECT region_id, event_type, count(*) AS n FROM meter GROUP BY GROUPING SETS ((region_id), (event_type), ())")
def op_grouping_sets(s, d):
    m = _m(s, d).select("region_id", "event_type")
    return m.groupingSets([[F.col("region_id")], [F.col("event_type")], []], "region_id", "event_type").agg(F.count("*").alias("n"))


# ---- windows, order, sets, subqueries, shapes -----------------------------------------------------------


@query("op_win_rank", f"WITH {METER}, t AS (SELECT region_id, user_id, CAST(sum(power) AS DOUBLE) AS total FROM meter GROUP BY ALL) SELECT region_id, user_id, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM t WINDOW w AS (PARTITION BY region_id ORDER BY total DESC)")
def op_win_rank(s, d):
    w = Window.partitionBy("region_id").orderBy(F.desc("total"))
    t = _m(s, d).groupBy("region_id", "user_id").agg(F.sum("power").cast("double").alias("total"))
    return t.select("region_id", "user_id", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"))


@query("op_win_ntile", f"WITH {METER}, t AS (SELECT user_id, count(*) AS n, min(region_id) AS region_id FROM meter GROUP BY user_id) SELECT user_id, ntile(4) OVER (PARTITION BY region_id ORDER BY n, user_id) AS quarter FROM t")
def op_win_ntile(s, d):
    t = _m(s, d).groupBy("user_id").agg(F.count("*").alias("n"), F.min("region_id").alias("region_id"))
    return t.select("user_id", F.ntile(4).over(Window.partitionBy("region_id").orderBy("n", "user_id")).cast("long").alias("quarter"))


@query("op_win_lag_delta", f"WITH {METER} SELECT rid, CAST(power - lag(power) OVER (PARTITION BY user_id ORDER BY rid) AS DOUBLE) AS delta, lead(rid) OVER (PARTITION BY user_id ORDER BY rid) AS next_rid FROM meter")
def op_win_lag_delta(s, d):
    w = Window.partitionBy("user_id").orderBy("rid")
    return _m(s, d).select("rid", (F.col("power") - F.lag("power").over(w)).cast("double").alias("delta"), F.lead("rid").over(w).alias("next_rid"))


@query("op_win_running", f"WITH {METER} SELECT rid, CAST(sum(power) OVER (PARTITION BY user_id ORDER BY rid ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS running FROM meter")
def op_win_running(s, d):
    w = Window.partitionBy("user_id").orderBy("rid").rowsBetween(Window.unboundedPreceding, 0)
    return _m(s, d).select("rid", F.sum("power").over(w).cast("double").alias("running"))


@query("op_win_range7d", f"WITH {METER}, t AS (SELECT region_id, day, count(*) AS n FROM meter GROUP BY ALL) SELECT region_id, day, CAST(sum(n) OVER (PARTITION BY region_id ORDER BY day RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM t")
def op_win_range7d(s, d):
    t = _m(s, d).groupBy("region_id", "day").agg(F.count("*").alias("n"))
    w = Window.partitionBy("region_id").orderBy(F.unix_date("day").cast("long")).rangeBetween(-6, 0)
    return t.select("region_id", "day", F.sum("n").over(w).alias("week"))


@query("op_topk_users", f"WITH {METER} SELECT user_id, CAST(sum(power) AS DOUBLE) AS total FROM meter GROUP BY user_id ORDER BY sum(power) DESC, user_id LIMIT 10")
def op_topk_users(s, d):
    t = _m(s, d).groupBy("user_id").agg(F.sum("power").alias("total"))
    return t.orderBy(F.desc("total"), "user_id").limit(10).select("user_id", F.col("total").cast("double").alias("total"))


@query("op_topk_per_region", f"WITH {METER}, t AS (SELECT region_id, user_id, sum(power) AS total FROM meter GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY region_id ORDER BY total DESC, user_id) AS k FROM t) SELECT region_id, user_id, k FROM r WHERE k <= 3")
def op_topk_per_region(s, d):
    t = _m(s, d).groupBy("region_id", "user_id").agg(F.sum("power").alias("total"))
    k = F.row_number().over(Window.partitionBy("region_id").orderBy(F.desc("total"), "user_id"))
    return t.withColumn("k", k).where("k <= 3").select("region_id", "user_id", F.col("k").cast("long").alias("k"))


@query("op_union", "SELECT c_custkey AS id, 'c' AS kind FROM customer UNION ALL SELECT s_suppkey, 's' FROM supplier")
def op_union(s, d):
    a = table(s, d, "customer").select(F.col("c_custkey").alias("id"), F.lit("c").alias("kind"))
    return a.unionByName(table(s, d, "supplier").select(F.lit("s").alias("kind"), F.col("s_suppkey").alias("id")))


@query("op_intersect", "SELECT o_custkey AS id FROM orders INTERSECT SELECT user_id FROM events")
def op_intersect(s, d):
    return table(s, d, "orders").select(F.col("o_custkey").alias("id")).intersect(table(s, d, "events").select(F.col("user_id").alias("id")))


@query("op_except", "SELECT CAST(o_orderdate AS DATE) AS day FROM orders EXCEPT SELECT CAST(l_shipdate AS DATE) FROM lineitem WHERE l_quantity > 49")
def op_except(s, d):
    """Days with orders on which no large position was shipped."""
    shipped = table(s, d, "lineitem").where("l_quantity > 49").select(F.col("l_shipdate").cast("date").alias("day"))
    return table(s, d, "orders").select(F.col("o_orderdate").cast("date").alias("day")).subtract(shipped)


@query("op_scalar_subq", "SELECT o_orderkey FROM orders WHERE CAST(o_totalprice AS DECIMAL(18,2)) > (SELECT max(CAST(o_totalprice AS DECIMAL(18,2))) FROM orders) * 0.98")
def op_scalar_subq(s, d):
    table(s, d, "orders").createOrReplaceTempView("cubegrid_orders")
    return s.sql("SELECT o_orderkey FROM cubegrid_orders WHERE CAST(o_totalprice AS DECIMAL(18,2)) > (SELECT max(CAST(o_totalprice AS DECIMAL(18,2))) FROM cubegrid_orders) * 0.98")


@query("op_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT') AND c_acctbal > 0")
def op_exists(s, d):
    urgent = table(s, d, "orders").where("o_orderpriority = '1-URGENT'").select("o_custkey")
    return table(s, d, "customer").where("c_acctbal > 0").join(urgent, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


_TYPES = ["view", "click", "purchase"]


@query("op_pivot_type", f"WITH {METER} SELECT region_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS n_{t}" for t in _TYPES) + " FROM meter GROUP BY region_id")
def op_pivot_type(s, d):
    """Fixed values, so the columns do not depend on the data."""
    got = _m(s, d).groupBy("region_id").pivot("event_type", _TYPES).agg(F.count(F.lit(1)))
    return got.select("region_id", *[F.coalesce(F.col(t), F.lit(0)).alias(f"n_{t}") for t in _TYPES])


@query("op_unpivot", "SELECT s_suppkey, 'nation' AS name, CAST(s_nationkey AS DOUBLE) AS value FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
def op_unpivot(s, d):
    wide = table(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return wide.unpivot("s_suppkey", ["nation", "balance"], "name", "value")


@query("op_sample")
def op_sample(s, d):
    """A sampling operator: shares per event type."""
    m = _m(s, d)
    return m.sampleBy("event_type", dict.fromkeys(_TYPES, 0.1), seed=3).groupBy("event_type").agg(F.count("*").alias("n"))


@query("op_coalesce_ranges")
def op_coalesce_ranges(s, d):
    """Row ranges per file that a query reads, adjacent segments joined."""
    from cubegrid.plans.execute import ranges_by_file
    from cubegrid.plans.planner import GridQuery
    from cubegrid.workloads import SUM, box

    plan = meter_grid(s, d, "grid_m").plan(GridQuery(box("p05"), SUM), headers=False)
    return ranges_by_file(plan.cells).select(F.size("ranges").alias("ranges"), "rows")
