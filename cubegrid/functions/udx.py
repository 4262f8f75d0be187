"""User-defined surfaces: a table function that lists the cells of a box, an Arrow function, a custom header."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid import fs
from cubegrid.headers import CUSTOM, Agg, Header
from cubegrid.registry import Registry
from cubegrid.sources.loaders import table

query = Registry()


class CellsInBox:
    """Cells of a two-dimensional box of ticks, for looking at a policy: origins, widths, half-open ranges."""

    def eval(self, o_a: int, w_a: int, lo_a: int, hi_a: int, o_b: int, w_b: int, lo_b: int, hi_b: int):
        for a in range((lo_a - o_a) // w_a, (hi_a - 1 - o_a) // w_a + 1):
            for b in range((lo_b - o_b) // w_b, (hi_b - 1 - o_b) // w_b + 1):
                inner = lo_a <= o_a + a * w_a and o_a + (a + 1) * w_a <= hi_a and lo_b <= o_b + b * w_b and o_b + (b + 1) * w_b <= hi_b
                yield a, b, inner


def arrow_clip(value: pa.Array, most: pa.Array) -> pa.Array:
    """Vectorised scalar function; the engine's own paths use none."""
    return pc.min_element_wise(value, most)


def sum_of_squares(expr: str, name: str) -> Header:
    """A custom header: exact sums of squares are additive, so variances can be derived from cells."""
    return Header.custom("sum_squares", expr, name, lambda: F.sum(F.expr(f"({expr}) * ({expr})")), F.sum)


CUSTOM["sum_squares"] = sum_of_squares


#: Boxes of the customers: 700 keys wide and four nations high, from a little beyond their own.
_BOXES = "SELECT c_custkey + 5 AS lo_a, c_custkey + 705 AS hi_a, CAST(c_nationkey AS BIGINT) + 12 AS lo_b, CAST(c_nationkey AS BIGINT) + 16 AS hi_b FROM customer"


@query(
    "fn_udtf_cells",
    f"""WITH boxes AS ({_BOXES}), a AS (SELECT *, unnest(generate_series(CAST(floor((lo_a - 1) / 500) AS BIGINT), CAST(floor((hi_a - 2) / 500) AS BIGINT))) AS g_a FROM boxes),
 cells AS (SELECT *, unnest(generate_series(CAST(floor((lo_b - 11) / 2) AS BIGINT), CAST(floor((hi_b - 12) / 2) AS BIGINT))) AS g_b FROM a)
 SELECT g_a, g_b, count(*) AS boxes, count(*) FILTER (WHERE lo_a <= 1 + g_a * 500 AND 501 + g_a * 500 <= hi_a AND lo_b <= 11 + g_b * 2 AND 13 + g_b * 2 <= hi_b) AS inner_boxes FROM cells GROUP BY ALL""",
)
def fn_udtf_cells(s, d) -> DataFrame:
    """The cells of every customer's box, listed by the table function: by how many boxes each is touched and covered."""
    key, nation = F.col("c_custkey").cast("long"), F.col("c_nationkey").cast("long")
    boxes = table(s, d, "customer").where("c_custkey IS NOT NULL AND c_nationkey IS NOT NULL").select((key + 5).alias("lo_a"), (key + 705).alias("hi_a"), (nation + 12).alias("lo_b"), (nation + 16).alias("hi_b"))
    lo_a, hi_a, lo_b, hi_b = (F.col(c).outer() for c in boxes.columns)
    listed = F.udtf(CellsInBox, returnType="g_a long, g_b long, is_inner boolean")(F.lit(1), F.lit(500), lo_a, hi_a, F.lit(11), F.lit(2), lo_b, hi_b)
    return boxes.lateralJoin(listed).groupBy("g_a", "g_b").agg(F.count("*").alias("boxes"), F.count_if("is_inner").alias("inner_boxes"))


@query("fn_arrow_udf", "SELECT c_custkey, least(c_acctbal, 1000.0) AS balance FROM customer")
def fn_arrow_udf(s, d) -> DataFrame:
    return table(s, d, "customer").select("c_custkey", F.arrow_udf(arrow_clip, "double")(F.col("c_acctbal"), F.lit(1000.0)).alias("balance"))


@query("custom_header_variance", "SELECT CAST(sum(CAST(p AS DECIMAL(18,2)) * CAST(p AS DECIMAL(18,2))) AS DOUBLE) AS squares, CAST(sum(CAST(p AS DECIMAL(18,2))) AS DOUBLE) AS total, count(*) AS n FROM (SELECT value AS p, user_id FROM events) WHERE user_id >= 20 AND user_id < 77")
def custom_header_variance(s, d) -> DataFrame:
    """Sum, sum of squares and count from headers: enough for mean and variance."""
    from cubegrid.api import GridTable
    from cubegrid.plans.planner import GridQuery
    from cubegrid.plans.predicate import Range
    from cubegrid.policy import Dim, SplitPolicy
    from cubegrid.workloads import once

    rows = table(s, d, "events").select("user_id", F.col("value").cast("decimal(18,2)").alias("p"))
    grid = once(s, d, "variance", lambda: GridTable.create(rows, fs.scratch(s, "variance"), SplitPolicy([Dim("user_id", 0, 10)]), [Header.sum("p"), sum_of_squares("p", "squares")], files=2))
    got = grid.query(GridQuery((Range("user_id", 20, 77),), (Agg("sum_squares", "p", "squares"), Agg("sum", "p", "total"), Agg("count", "*", "n"))))
    return got.select(F.col("squares").cast("double").alias("squares"), F.col("total").cast("double").alias("total"), "n")
