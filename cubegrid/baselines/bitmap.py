"""Bitmap index: per value of a column and bucket of row numbers, one bit per row."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class BitmapIndex:
    """Good for columns of few values. ``row_id`` numbers the rows from 0 and is dense."""

    def __init__(self, base: DataFrame, columns: list[str], row_id: str, index: DataFrame | None = None):
        self.base, self.columns, self.row_id = base, columns, row_id
        self.index = index if index is not None else self.build()

    def build(self) -> DataFrame:
        """name, value, bucket, bits."""
        one = F.col(self.row_id) + 1
        values = F.array(*[F.struct(F.lit(c).alias("name"), F.col(c).cast("string").alias("value")) for c in self.columns])
        each = self.base.select(F.bitmap_bucket_number(one).alias("bucket"), F.bitmap_bit_position(one).alias("bit"), F.inline(values))
        return each.groupBy("name", "value", "bucket").agg(F.bitmap_construct_agg("bit").alias("bits"))

    def _selected(self, conditions: dict[str, Column]) -> DataFrame:
        """bucket, bits of rows that meet every condition (on ``value``), one per column."""
        per_column = [self.index.where((F.col("name") == name) & cond).groupBy("bucket").agg(F.bitmap_or_agg("bits").alias("bits")) for name, cond in conditions.items()]
        if len(per_column) == 1:
            return per_column[0]
        union = reduce(DataFrame.unionByName, per_column)
        return union.groupBy("bucket").agg(F.count("*").alias("k"), F.bitmap_and_agg("bits").alias("bits")).where(F.col("k") == len(per_column)).select("bucket", "bits")

    def count(self, conditions: dict[str, Column]) -> DataFrame:
        """Rows that meet all conditions, from bits alone."""
        return self._selected(conditions).agg(F.coalesce(F.sum(F.bitmap_count("bits")), F.lit(0)).alias("n"))

    def rows(self, conditions: dict[str, Column]) -> DataFrame:
        """The rows themselves: buckets are met by a semi-join, then bits are tested."""
        one = F.col(self.row_id) + 1
        hits = self._selected(conditions).select(F.col("bucket").alias("__bucket"), F.col("bits").alias("__bits"))
        keyed = self.base.withColumn("__bucket", F.bitmap_bucket_number(one)).withColumn("__bit", F.bitmap_bit_position(one))
        # the bit lies in byte bit / 8 of the bitmap, lowest first
        byte = F.conv(F.hex(F.substring(F.col("__bits"), (F.col("__bit") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
        on = F.call_function("shiftright", byte, (F.col("__bit") % 8).cast("int")).bitwiseAND(F.lit(1)) == 1
        return keyed.join(hits, "__bucket").where(on).drop("__bucket", "__bit", "__bits")
