"""Prefix sums: one window where the rows are known to be few, else range partitions, their totals and local sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.lineage import cut

#: Rows up to which one task may sort a whole group.
LOCAL_ROWS = 1 << 20


def inclusive(frame: DataFrame, order: list[str], value: str, group: list[str] | None = None, rows: int | None = None) -> DataFrame:
    """Adds ``rank`` (from 0) and ``hi`` (running total of ``value``, itself included) within each group.

    ``rows``: the number of rows of ``frame`` where the caller knows it.  Unless that is at most ``LOCAL_ROWS`` no
    window spans a whole group: rows are dealt by ranges, a table with a row for each range and group carries the
    totals, and each range sums its own rows only.
    """
    group = group or []
    if rows is not None and rows <= LOCAL_ROWS:
        whole = Window.partitionBy(*group).orderBy(*order) if group else Window.orderBy(*order)
        return frame.coalesce(1).select("*", (F.row_number().over(whole).cast("long") - 1).alias("rank"), F.sum(value).over(whole.rowsBetween(Window.unboundedPreceding, 0)).alias("hi"))
    dealt = cut(frame.repartitionByRange(*group, *order).withColumn("_range", F.spark_partition_id()))
    totals = dealt.groupBy("_range", *group).agg(F.sum(value).alias("_sum"), F.count("*").alias("_n"))
    before = Window.partitionBy(*group, F.lit(0)).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_range", *group, F.coalesce(F.sum("_sum").over(before), F.lit(0)).alias("_lo"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    local = Window.partitionBy("_range", *group).orderBy(*order)
    return (
        dealt.join(offsets, ["_range", *group])
        .withColumn("rank", F.row_number().over(local) - 1 + F.col("_before"))
        .withColumn("hi", F.sum(value).over(local.rowsBetween(Window.unboundedPreceding, 0)) + F.col("_lo"))
        .drop("_range", "_lo", "_before")
    )
