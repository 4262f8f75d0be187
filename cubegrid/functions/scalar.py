"""Scalar functions used around readings: dates, exact steps, strings, arrays, JSON, bits, nulls."""

from __future__ import annotations

from datetime import date

from pyspark.sql import Column
from pyspark.sql import functions as F

from cubegrid.registry import Registry
from cubegrid.sources.loaders import table

query = Registry()


def floor_div(a: Column, b: int) -> Column:
    """Exact integer division towards minus infinity."""
    return F.call_function("div", a - F.pmod(a, F.lit(b)), F.lit(b))


def time_bucket(ts: Column, micros: int) -> Column:
    """Start of the fixed-length interval that holds a timestamp without zone."""
    epoch = F.lit("1970-01-01 00:00:00").cast("timestamp_ntz")
    t = F.timestamp_diff("MICROSECOND", epoch, ts)
    return F.timestamp_add("MICROSECOND", t - F.pmod(t, F.lit(micros)), epoch)


def number_in(props: Column, key: str) -> Column:
    """A number out of a JSON text; NULL where it is none."""
    return F.get_json_object(props, f"$.{key}").try_cast("long")


@query("fn_dates", "SELECT event_id, CAST(ts AS DATE) AS day, CAST(date_trunc('month', ts) AS DATE) AS month_start, CAST(ts AS DATE) - DATE '1970-01-01' AS day_number, CAST(hour(ts) AS BIGINT) AS hr, CAST(date_trunc('month', ts) + INTERVAL 1 MONTH - INTERVAL 1 DAY AS DATE) AS month_end FROM events")
def fn_dates(s, d):
    day = F.to_date("ts")
    return table(s, d, "events").select("event_id", day.alias("day"), F.trunc(day, "month").alias("month_start"), F.unix_date(day).cast("long").alias("day_number"), F.hour("ts").cast("long").alias("hr"), F.last_day(day).alias("month_end"))


@query("fn_time_bucket", "SELECT CAST(epoch_us(ts) // 900000000 AS BIGINT) AS quarter_hour, count(*) AS n FROM events GROUP BY ALL")
def fn_time_bucket(s, d):
    start = time_bucket(F.col("ts"), 15 * 60 * 10**6)
    quarter = F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), start)
    return table(s, d, "events").groupBy(F.call_function("div", quarter, F.lit(900)).alias("quarter_hour")).agg(F.count("*").alias("n"))


@query("fn_math", "SELECT s_suppkey, CAST(floor((s_suppkey - 11) / 2) AS BIGINT) AS cut, CAST((s_suppkey - 11) - 2 * floor((s_suppkey - 11) / 2) AS BIGINT) AS rest, greatest(s_suppkey, 40) AS up, least(s_suppkey, 40) AS down FROM supplier")
def fn_math(s, d):
    off = F.col("s_suppkey") - 11
    return table(s, d, "supplier").select("s_suppkey", floor_div(off, 2).alias("cut"), F.pmod(off, F.lit(2)).cast("long").alias("rest"), F.greatest("s_suppkey", F.lit(40)).alias("up"), F.least("s_suppkey", F.lit(40)).alias("down"))


@query("fn_strings", "SELECT c_custkey, concat_ws('_', lower(c_mktsegment), CAST(c_nationkey AS VARCHAR)) AS corner, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, regexp_extract(c_name, '([0-9]+)$', 1) AS digits, substring(c_name, 1, 4) AS head FROM customer")
def fn_strings(s, d):
    return table(s, d, "customer").select(
        "c_custkey",
        F.concat_ws("_", F.lower("c_mktsegment"), F.col("c_nationkey").cast("string")).alias("corner"),
        F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"),
        F.regexp_extract("c_name", "([0-9]+)$", 1).alias("digits"),
        F.substring("c_name", 1, 4).alias("head"),
    )


@query("fn_arrays", "SELECT user_id, array_to_string(list_sort(list_distinct(list(event_type))), ',') AS kinds, CAST(len(list_distinct(list(event_type))) AS BIGINT) AS n_kinds, list_contains(list(event_type), 'purchase') AS buys FROM events GROUP BY user_id")
def fn_arrays(s, d):
    kinds = F.sort_array(F.collect_set("event_type"))
    got = table(s, d, "events").groupBy("user_id").agg(kinds.alias("k"))
    return got.select("user_id", F.array_join("k", ",").alias("kinds"), F.size("k").cast("long").alias("n_kinds"), F.array_contains("k", "purchase").alias("buys"))


@query("fn_maps", "SELECT user_id, event_type AS name, count(*) AS n FROM events GROUP BY ALL")
def fn_maps(s, d):
    """Header values as a map and back."""
    each = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    packed = each.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return packed.select("user_id", F.explode("m").alias("name", "n"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(s, d):
    return table(s, d, "events").select("event_id", number_in(F.col("props"), "k").alias("k"))


@query("fn_bits", "SELECT l_linenumber, bit_or(CAST(1 AS BIGINT) << CAST(l_quantity AS BIGINT)) AS seen, CAST(bit_count(bit_or(CAST(1 AS BIGINT) << CAST(l_quantity AS BIGINT))) AS BIGINT) AS n FROM lineitem GROUP BY l_linenumber")
def fn_bits(s, d):
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("l_quantity").cast("int"))
    return table(s, d, "lineitem").groupBy("l_linenumber").agg(F.bit_or(bit).alias("seen")).select("l_linenumber", "seen", F.bit_count("seen").cast("long").alias("n"))


@query("fn_nulls", "SELECT o_orderkey, nullif(o_orderstatus, 'O') AS done, coalesce(nullif(o_orderstatus, 'O'), 'open') AS status, CASE WHEN o_custkey % 5 = 0 THEN NULL ELSE CAST(o_orderkey AS DOUBLE) / (o_custkey % 5) END AS ratio FROM orders")
def fn_nulls(s, d):
    done = F.nullif(F.col("o_orderstatus"), F.lit("O"))
    return table(s, d, "orders").select("o_orderkey", done.alias("done"), F.coalesce(done, F.lit("open")).alias("status"), F.try_divide(F.col("o_orderkey").cast("double"), F.col("o_custkey") % 5).alias("ratio"))


@query("fn_from_epoch_days", "SELECT DISTINCT DATE '2024-01-01' + CAST((CAST(ts AS DATE) - DATE '2024-01-01') // 7 * 7 AS INTEGER) AS week_start FROM events")
def fn_from_epoch_days(s, d):
    origin = (date(2024, 1, 1) - date(1970, 1, 1)).days
    week = floor_div(F.unix_date(F.to_date("ts")) - origin, 7) * 7 + origin
    return table(s, d, "events").select(F.date_from_unix_date(week.cast("int")).alias("week_start")).distinct()
