"""Joins and counts whose hot keys are dealt over several tasks, and broadcasts behind a check of size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows up to which a narrow table may be broadcast.
BESIDE_ROWS = 500_000


def beside(frame: DataFrame, most: int = BESIDE_ROWS) -> tuple[DataFrame, int]:
    """The frame, marked for broadcast if it has few rows, and its number of rows."""
    n = frame.count()
    return (F.broadcast(frame) if n <= most else frame), n


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """Inner join: the large side's rows of a key are dealt over ``salts`` groups by their content, the small side meets each."""
    dealt = large.withColumn("_salt", F.pmod(F.xxhash64(*large.columns, F.monotonically_increasing_id()), F.lit(salts)).cast("int"))
    copies = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copies, [key, "_salt"]).drop("_salt")


def salted_count(rows: DataFrame, key: str, salts: int) -> DataFrame:
    """Counts in two steps, salted and whole."""
    part = rows.groupBy(key, F.spark_partition_id().alias("_p") % salts).agg(F.count("*").alias("n"))
    return part.groupBy(key).agg(F.sum("n").alias("n"))
