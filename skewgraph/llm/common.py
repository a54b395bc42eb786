"""Helpers shared by the operators: words, byte-bounded chunks, tables in the shared folder."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Most bytes of text that an operator holds as Python objects at once (one longer text still goes alone).
CHUNK_BYTES = 4 << 20


def words_of(text: bytes, lower: bool = False) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` of UTF-8 text; ``lower`` maps A-Z only.

    ``bytes.split`` and ``bytes.lower`` know exactly these six separators and these 26 letters.
    """
    return (text.lower() if lower else text).split()


def utf8(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """Texts of a string column as UTF-8 bytes; null is empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def chunks(texts: list[bytes], most: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of ``texts`` of at most ``most`` bytes each, one text at least."""
    start, held = 0, 0
    for i, text in enumerate(texts):
        if held and held + len(text) > most:
            yield start, i
            start, held = i, 0
        held += len(text)
    if start < len(texts):
        yield start, len(texts)


def slices(batches: Iterable[pa.RecordBatch], column: str, most: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Each batch in slices of at most ``most`` bytes of ``column``, with those texts as bytes."""
    for batch in batches:
        sizes = batch.column(column).cast(pa.binary())
        lengths = [x or 0 for x in pa.compute.binary_length(sizes).to_pylist()] if len(sizes) else []
        start, held = 0, 0
        cuts = []
        for i, n in enumerate(lengths):
            if held and held + n > most:
                cuts.append((start, i))
                start, held = i, 0
            held += n
        if start < len(lengths):
            cuts.append((start, len(lengths)))
        for a, b in cuts:
            part = batch.slice(a, b - a)
            yield part, utf8(part.column(column))


def shared_folder(spark: SparkSession) -> str:
    """Folder that the driver and all executors share: the session's ``spark.checkpoint.dir``.

    Only where a session has none (tests on one machine) a folder under the warehouse is set.
    """
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        where = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/.checkpoints"
        spark.sparkContext.setCheckpointDir(where)
    return where.rstrip("/")


#: Rows up to which a side of a join may be broadcast; beyond, both sides are shuffled.
BESIDE_ROWS = 1_000_000


def beside(frame: DataFrame, weight: str = "1") -> DataFrame:
    """The frame, marked for broadcast if its rows (or the sum of ``weight`` over them) are few enough.

    The frame is counted, so give it a written table.
    """
    n = frame.agg(F.expr(f"sum({weight})")).first()[0] or 0
    return F.broadcast(frame) if n <= BESIDE_ROWS else frame


def fresh(name: str, taken: list[str]) -> str:
    """``name``, with underscores added until no column is called so."""
    while name.lower() in {c.lower() for c in taken}:
        name += "_"
    return name


class Shared:
    """A table written to the shared folder, which cuts lineage and outlives lost executors."""

    def __init__(self, frame: DataFrame, name: str):
        self.spark = frame.sparkSession
        self.path = f"{shared_folder(self.spark)}/tables/{name}-{uuid.uuid4().hex}"
        frame.write.parquet(self.path)
        self.schema = frame.schema
        atexit.register(self.drop)

    @property
    def frame(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        """Delete the table; frames that read it are of no use from then on."""
        atexit.unregister(self.drop)
        try:
            jvm = self.spark._jvm
            path = jvm.org.apache.hadoop.fs.Path(self.path)
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # the session has ended: its folder goes with the cluster
            pass


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
