"""Joins that Spark has no operator for: boxes over points, and the last row before a moment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def range_join(points: DataFrame, value: str, ranges: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Points with all half-open ranges [lo, hi) that hold them.

    Both sides are cut into buckets of ``width``: a range goes to every bucket it touches, a point
    to its own, and an equi-join on buckets replaces the comparison of all with all. Choose a width
    near the usual length of a range.
    """
    bucket = lambda c: F.floor(c / F.lit(width)).cast("long")
    spread = ranges.where(F.col(lo) < F.col(hi)).withColumn("__b", F.explode(F.sequence(bucket(F.col(lo)), F.floor((F.col(hi) - 1) / F.lit(width)).cast("long"))))
    return points.withColumn("__b", bucket(F.col(value))).join(spread, "__b").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], left_time: Column, right_time: Column, take: list[str]) -> DataFrame:
    """Each left row with ``take`` of the last right row of the same key at or before its time.

    One shuffle of the union of both sides; the last non-null value carries forward. Right rows of
    equal time are ordered by their values, so the result does not depend on partitions.
    """
    left_names = left.columns
    packed = F.struct(*[F.col(c) for c in take])
    kind = left.select(F.struct(*left_names)).schema[0].dataType
    l_side = left.select(*by, left_time.alias("__t"), F.lit(1).alias("__side"), F.struct(*left_names).alias("__left"), F.lit(None).cast(right.select(packed).schema[0].dataType).alias("__right"))
    r_side = right.select(*by, right_time.alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(kind).alias("__left"), packed.alias("__right"))
    order = Window.partitionBy(*by).orderBy("__t", "__side", "__right").rowsBetween(Window.unboundedPreceding, 0)
    carried = l_side.unionByName(r_side).withColumn("__last", F.last("__right", ignorenulls=True).over(order))
    return carried.where("__side = 1").select("__left.*", *[F.col(f"__last.{c}").alias(c) for c in take])


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int = 16) -> DataFrame:
    """Inner equi-join whose left side has hot keys: they are dealt over ``salts`` copies of the right rows."""
    spread = right.withColumn("__salt", F.explode(F.array(*[F.lit(i) for i in range(salts)])))
    dealt = left.withColumn("__salt", F.pmod(F.xxhash64(*[F.col(c) for c in left.columns]), F.lit(salts)).cast("int"))
    return dealt.join(spread, [on, "__salt"]).drop("__salt")
