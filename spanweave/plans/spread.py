"""Joins of many rows with few large ones, and numbering, without gathering a key or a table in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .workspace import settle

#: Keys that hold more than this share of all rows are dealt over several places; there are at most as many of them.
FREQUENT = 200


def slots_of(df: DataFrame) -> int:
    """Tasks that a join which feeds searches is dealt over."""
    spark = df.sparkSession
    return max(spark.sparkContext.defaultParallelism * 4, 8, int(spark.conf.get("spark.sql.shuffle.partitions")))


def beside(rows: DataFrame, large: DataFrame, key: str, *, how: str = "inner", slots: int | None = None) -> DataFrame:
    """``rows`` joined with the one row of ``large`` that has their key, spread over ``slots`` tasks whatever the keys.

    A key with over 1/``FREQUENT`` of the rows gets as many places as it has rows, at most ``slots``: its rows are dealt over them
    by hash, and its large row is copied to each.  Other keys have one place.  Both sides are partitioned alike by key and
    place, in a number of partitions that adaptive execution does not lower.  The frequent keys, fewer than ``FREQUENT``, are
    all that reaches the driver.
    """
    slots = slots or slots_of(rows)
    counts = rows.groupBy(key).agg(F.count("*").alias("rows_of_key"))
    best = counts.where(F.col(key).isNotNull()).orderBy(F.desc("rows_of_key"), key).limit(FREQUENT)
    total = counts.agg(F.sum("rows_of_key")).first()[0] or 0
    hot = [(r[key], min(slots, r["rows_of_key"])) for r in best.collect() if r["rows_of_key"] > 1 and r["rows_of_key"] * FREQUENT > total]
    place = F.lit(0)
    if hot:
        copies = rows.sparkSession.createDataFrame(hot, f"{key} {rows.schema[key].dataType.simpleString()}, copies int")
        rows, large = (df.join(F.broadcast(copies), key, "left") for df in (rows, large))
        place = F.pmod(F.xxhash64(*[c for c in rows.columns if c != "copies"]), F.coalesce("copies", F.lit(1))).cast("int")
        large = large.withColumn("place", F.explode(F.sequence(F.lit(0), F.coalesce("copies", F.lit(1)) - 1))).drop("copies")
        rows = rows.withColumn("place", place).drop("copies")
    else:
        rows, large = rows.withColumn("place", place), large.withColumn("place", place)
    # One column for both, so that a key which is a constant is not optimised away from the partitioning; a null key meets nothing.
    at = F.concat(F.coalesce(F.col(key).cast("string"), F.lit("none")), F.lit(" "), F.col("place").cast("string"))
    left, right = rows.withColumn("at", at).drop("place"), large.where(F.col(key).isNotNull()).withColumn("at", at).drop("place", key)
    return left.repartition(slots, "at").join(right.repartition(slots, "at"), "at", how).drop("at")


def ranked(df: DataFrame, name: str, *order) -> DataFrame:
    """``df`` with ``name``, the place from 0 in the given order: sorted by range, counted by part, numbered within parts.

    Rows with equal order keys are numbered in any order.  One row for each part is broadcast.
    """
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = settle(df.repartitionByRange(parts, *order).withColumn("part_of_rank", F.spark_partition_id()))
    sizes = dealt.groupBy("part_of_rank").agg(F.count("*").alias("size_of_part"))
    before = F.coalesce(F.sum("size_of_part").over(Window.orderBy("part_of_rank").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # a row a part
    offsets = sizes.select("part_of_rank", before.alias("before_part"))
    within = F.row_number().over(Window.partitionBy("part_of_rank").orderBy(*order)) - 1
    numbered = dealt.withColumn(name, within).join(F.broadcast(offsets), "part_of_rank")
    return numbered.withColumn(name, (F.col(name) + F.col("before_part")).cast("bigint")).drop("part_of_rank", "before_part")
