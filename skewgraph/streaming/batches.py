"""Event streams replayed from files until none is left, with the batch answers that they must give."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..sources import table

Query = Callable[[SparkSession, str], DataFrame]
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def folder(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/.checkpoints"
    return f"{base.rstrip('/')}/streams/{uuid.uuid4().hex}"


def replay(spark: SparkSession, sf_dir: str, transform: Callable[[DataFrame], DataFrame], mode: str = "append", copies: int = 1) -> DataFrame:
    """The rows that ``transform`` of the events' stream writes; each ``copies``-th file once more.

    The events are written as files in the order of time, read one file a batch, and the results are read from the sink.
    """
    where = folder(spark)
    events = table(spark, sf_dir, "events").select(F.col("event_id"), F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
    for _ in range(copies):
        events.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.mode("append").parquet(f"{where}/in")
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 2).parquet(f"{where}/in")
    out = transform(stream)

    def keep(batch: DataFrame, n: int) -> None:
        batch.withColumn("_batch", F.lit(n).cast("long")).write.mode("append").parquet(f"{where}/out")

    out.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start().awaitTermination()
    schema = StructType([*out.schema.fields]).add("_batch", "long")
    return spark.read.schema(schema).parquet(f"{where}/out")


def _last(rows: DataFrame, keys: list[str]) -> DataFrame:
    """The last row that a stream in update or complete mode wrote for each key."""
    rest = [c for c in rows.columns if c not in (*keys, "_batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "_batch").alias("x")).select(*keys, "x.*")


def _seconds(c: str):
    return F.unix_seconds(c)


def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    """Events per type and day."""
    rows = replay(spark, d, lambda s: s.withWatermark("ts", "7 days").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(_seconds("w.start").alias("day"), "event_type", "n"), "update")
    return _last(rows, ["day", "event_type"])


def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    """Events per two days, every day."""
    rows = replay(spark, d, lambda s: s.withWatermark("ts", "7 days").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(_seconds("w.start").alias("day"), "n"), "update")
    return _last(rows, ["day"])


def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Events that come twice count once."""
    rows = replay(spark, d, lambda s: s.withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"), copies=2)
    return rows.groupBy("event_type").agg(F.count("*").alias("n"))


def stream_static(spark: SparkSession, d: str) -> DataFrame:
    """Events with their customers' nations."""
    customers = table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    rows = replay(spark, d, lambda s: s.join(customers, "user_id").select("event_id", "c_nationkey"))
    return rows.groupBy("c_nationkey").agg(F.count("*").alias("n"))


def stream_degree_state(spark: SparkSession, d: str) -> DataFrame:
    """Each user's events so far, kept as state over batches."""
    rows = replay(spark, d, lambda s: s.groupBy("user_id").agg(F.count("*").alias("deg")), "update")
    return _last(rows, ["user_id"])


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (stream_tumbling, stream_sliding, stream_dedup, stream_static, stream_degree_state)}


def oracle_sql() -> dict[str, str]:
    day = "CAST(epoch(date_trunc('day', ts)) AS BIGINT)"
    return {
        "stream_tumbling": f"SELECT {day} AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_sliding": f"SELECT day, count(*) AS n FROM (SELECT {day} - k * 86400 AS day FROM events, range(2) r(k)) GROUP BY 1",
        "stream_dedup": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
        "stream_static": "SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
        "stream_degree_state": "SELECT user_id, count(*) AS deg FROM events GROUP BY 1",
    }
