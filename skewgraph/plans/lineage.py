"""Tables in the shared folder: they cut lineage, carry true sizes and outlive lost executors."""

from __future__ import annotations

import atexit
import uuid
import warnings

from pyspark.sql import DataFrame, Observation, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's ``spark.checkpoint.dir``.

    Where a session has none, a folder of the warehouse; with a warning unless the session runs on one machine.
    """
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            warnings.warn("spark.checkpoint.dir is not set: tables go to the warehouse, which all executors must share", stacklevel=2)
        where = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/.checkpoints"
        spark.sparkContext.setCheckpointDir(where)
    return where.rstrip("/")


class Table:
    """A written table.  Unlike a checkpoint it doesn't inherit the size estimate of the plan that made it.

    With ``keys`` it is bucketed by them, as many buckets as the session has shuffle partitions, so that joins on the
    keys move the other side only.
    """

    def __init__(self, frame: DataFrame, name: str = "table", keys: list[str] | None = None):
        self.spark, self.schema, self.name = frame.sparkSession, frame.schema, None
        tag = uuid.uuid4().hex
        self.path = f"{shared_folder(self.spark)}/graph/{name}-{tag}"
        if keys:
            self.name = f"skewgraph_{tag}"
            buckets = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
            frame.repartition(buckets, *keys).write.bucketBy(buckets, *keys).sortBy(*keys).option("path", self.path).saveAsTable(self.name)
        else:
            frame.write.parquet(self.path)
        atexit.register(self.drop)

    @property
    def frame(self) -> DataFrame:
        return self.spark.table(self.name) if self.name else self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        """Delete the files; frames that read them are of no use from then on."""
        atexit.unregister(self.drop)
        try:
            if self.name:
                self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
            path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # the session has ended: its folder goes with the cluster
            pass


def cut(frame: DataFrame) -> DataFrame:
    """The frame's rows, written and read again; the files go when the process ends."""
    return Table(frame, "cut").frame


def counted(frame: DataFrame, name: str, **sums) -> tuple[Table, dict]:
    """The written table and aggregates over its rows, taken while they are written."""
    seen = Observation()
    table = Table(frame.observe(seen, *(c.alias(n) for n, c in sums.items())), name)
    return table, seen.get
