"""Joins by time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, *, key: str, time: str, values: list[str], tie: str) -> DataFrame:
    """``left`` with ``values`` of the latest row of ``right`` with the same key at or before ``time`` (null: none); ties go to the greater ``tie``.

    One shuffle by key: both sides are stacked, sorted by time with the right side first, and the last value seen is carried on.
    Both have columns ``key`` and ``time``.  A key that holds a large share of the rows is one window partition; Spark spills it.
    """
    row = F.struct(*values)
    rest = [c for c in left.columns if c not in (key, time)]
    a = left.select(key, time, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[tie].dataType).alias("_tie"), F.struct(*rest).alias("_left"), F.lit(None).alias("_right"))
    b = right.select(key, time, F.lit(0).alias("_side"), F.col(tie).alias("_tie"), F.lit(None).alias("_left"), row.alias("_right"))
    order = Window.partitionBy(key).orderBy(time, "_side", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    carried = a.unionByName(b).withColumn("_seen", F.last("_right", ignorenulls=True).over(order)).where("_side = 1")
    return carried.select(key, time, *(F.col(f"_left.{c}").alias(c) for c in rest), *(F.col(f"_seen.{v}").alias(v) for v in values))
