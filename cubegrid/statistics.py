"""Scheduled statistics over readings and reference tables, beside their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid.registry import Registry
from cubegrid.sources.loaders import table
from cubegrid.workloads import METER, meter

query = Registry()


@query("stat_acquisition_rate", f"WITH {METER} SELECT region_id, day, count(DISTINCT user_id) AS reporting, (SELECT count(DISTINCT user_id) FROM meter x WHERE x.region_id = m.region_id) AS expected FROM meter m GROUP BY region_id, day")
def stat_acquisition_rate(s: SparkSession, d: str) -> DataFrame:
    """Meters that reported on a day, against all of the region."""
    m = meter(s, d)
    users = m.groupBy("region_id").agg(F.count_distinct("user_id").alias("expected"))
    return m.groupBy("region_id", "day").agg(F.count_distinct("user_id").alias("reporting")).join(users, "region_id").select("region_id", "day", "reporting", "expected")


@query("stat_power_by_region", f"WITH {METER} SELECT r_name, n_name, day, CAST(sum(power) AS DOUBLE) AS total FROM meter JOIN nation ON region_id = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def stat_power_by_region(s: SparkSession, d: str) -> DataFrame:
    """Totals per nation and day; summed before names (25 and 5 rows) are joined."""
    names = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    sums = meter(s, d).groupBy("region_id", "day").agg(F.sum("power").cast("double").alias("total"))
    return sums.join(F.broadcast(names), F.col("region_id") == F.col("n_nationkey")).select("r_name", "n_name", "day", "total")


@query(
    "stat_loss_by_region",
    """WITH s AS (SELECT c_nationkey AS nation, sum(CAST(o_totalprice AS DECIMAL(18,2))) AS supplied FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1),
 c AS (SELECT c_nationkey AS nation, sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS consumed FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1)
 SELECT s.nation, CAST(supplied AS DOUBLE) AS supplied, CAST(consumed AS DOUBLE) AS consumed, CAST(supplied - consumed AS DOUBLE) AS loss FROM s LEFT JOIN c ON s.nation = c.nation""",
)
def stat_loss_by_region(s: SparkSession, d: str) -> DataFrame:
    """Supplied less consumed per nation: lines are summed by order before they meet customers."""
    money = lambda c: F.col(c).cast("decimal(18,2)")
    orders, users = table(s, d, "orders"), table(s, d, "customer").select("c_custkey", F.col("c_nationkey").alias("nation"))
    by_order = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.sum(money("l_extendedprice")).alias("consumed"))
    joined = orders.select("o_orderkey", "o_custkey", money("o_totalprice").alias("supplied")).join(by_order, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    per_user = joined.groupBy("o_custkey").agg(F.sum("supplied").alias("supplied"), F.sum("consumed").alias("consumed"))
    got = per_user.join(users, F.col("o_custkey") == F.col("c_custkey")).groupBy("nation").agg(F.sum("supplied").alias("supplied"), F.sum("consumed").alias("consumed"))
    return got.select("nation", F.col("supplied").cast("double").alias("supplied"), F.col("consumed").cast("double").alias("consumed"), (F.col("supplied") - F.col("consumed")).cast("double").alias("loss"))


@query("stat_traffic_hourly", "SELECT event_type, date_trunc('hour', ts) AS hr, count(*) AS n FROM events GROUP BY ALL")
def stat_traffic_hourly(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy("event_type", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hr")).agg(F.count("*").alias("n"))


def workflow(steps: list[tuple[str, Callable[[dict[str, DataFrame]], DataFrame]]]) -> dict[str, DataFrame]:
    """Ordered statements of a module, each seeing the results before it; a loop over regions is
    one grouped statement, not one run per region."""
    done: dict[str, DataFrame] = {}
    for name, step in steps:
        done[name] = step(done)
    return done


@query("stat_workflow", f"WITH {METER}, t AS (SELECT region_id, CAST(sum(power) AS DOUBLE) AS total FROM meter GROUP BY 1) SELECT region_id, total, total > (SELECT avg(total) FROM t) AS above FROM t")
def stat_workflow(s: SparkSession, d: str) -> DataFrame:
    done = workflow(
        [
            ("totals", lambda r: meter(s, d).groupBy("region_id").agg(F.sum("power").cast("double").alias("total"))),
            ("mean", lambda r: r["totals"].agg(F.avg("total").alias("mean"))),
            ("report", lambda r: r["totals"].join(F.broadcast(r["mean"])).select("region_id", "total", (F.col("total") > F.col("mean")).alias("above"))),
        ]
    )
    return done["report"]
