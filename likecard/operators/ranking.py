"""Running values over a whole table in an order, without one task that sorts it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import cut


def _ranges(df: DataFrame, order: list) -> DataFrame:
    """df in range partitions of the order, written, with the number of each row's range."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut(df.repartitionByRange(n, *order).withColumn("_range", F.spark_partition_id()))


def running_sum(df: DataFrame, order: list[str], weight: Column, name: str) -> DataFrame:
    """df with the sum of weight over the rows before each one. Ranges are summed
    on their own; their totals, one row a range, are added up."""
    rows = _ranges(df.withColumn("_w", weight.cast("long")), order)
    ranges = rows.groupBy("_range").agg(F.sum("_w").alias("_t"))
    before = F.sum("_t").over(Window.partitionBy(F.lit(0)).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1))
    ranges = ranges.select("_range", F.coalesce(before, F.lit(0)).alias("_before"))
    own = F.sum("_w").over(Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    out = rows.withColumn("_own", F.coalesce(own, F.lit(0))).join(F.broadcast(ranges), "_range")
    return out.withColumn(name, F.col("_own") + F.col("_before")).drop("_w", "_own", "_range", "_before")


def running_last(df: DataFrame, order: list, value: str) -> DataFrame:
    """df with value replaced by the last one that is not null up to each row."""
    rows = _ranges(df, order)
    place = F.struct(*order)
    ranges = rows.groupBy("_range").agg(F.max_by(value, F.when(F.col(value).isNotNull(), place)).alias("_v"))
    before = F.last("_v", ignorenulls=True).over(Window.partitionBy(F.lit(0)).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1))
    ranges = ranges.select("_range", before.alias("_before"))
    own = F.last(value, ignorenulls=True).over(Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    out = rows.withColumn("_own", own).join(F.broadcast(ranges), "_range")
    return out.withColumn(value, F.coalesce("_own", "_before")).drop("_own", "_range", "_before")
