"""Tables and edge lists as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

EDGES = StructType([StructField("src", LongType()), StructField("dst", LongType()), StructField("w", LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    """Temporary SQL views of the tables."""
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def read_edges(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """Edges from parquet, orc, csv, json, or text: ``arcs`` (lines ``a src dst w``) and ``pairs`` (``src dst [w]``).

    Text lines of other kinds (comments, headers) are left out.
    """
    if kind in ("parquet", "orc"):
        return spark.read.format(kind).load(path).select("src", "dst", "w")
    if kind in ("csv", "json"):
        return spark.read.schema(EDGES).format(kind).load(path)
    words = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).select(words.alias("x"))
    if kind == "arcs":
        return lines.where("x[0] = 'a' and size(x) = 4").select(*(F.col("x")[i].cast("long").alias(n) for i, n in ((1, "src"), (2, "dst"), (3, "w"))))
    if kind == "pairs":
        own = lines.where("size(x) >= 2 and x[0] rlike '^[0-9]+$'")
        return own.select(F.col("x")[0].cast("long").alias("src"), F.col("x")[1].cast("long").alias("dst"), F.coalesce(F.try_element_at("x", F.lit(3)).cast("long"), F.lit(1)).alias("w"))
    raise ValueError(f"unknown kind of edge list: {kind}")


def write_edges(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    """The inverse of ``read_edges``."""
    if kind == "arcs":
        edges.select(F.concat_ws(" ", F.lit("a"), "src", "dst", "w").alias("value")).write.text(path)
    elif kind == "pairs":
        edges.select(F.concat_ws(" ", "src", "dst", "w").alias("value")).write.text(path)
    else:
        edges.write.format(kind).save(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed and sorted by source, so that traversals join it in place."""
    edges.write.bucketBy(buckets, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(name)
