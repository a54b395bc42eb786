"""Extendible hashing into shards of bounded bytes, with DataFrame functions only (operator 8).

A row's directory key is 60 bits of a digest of its id.  A bucket is a prefix of the key; only buckets
over the byte limit split on one more bit, so a row's bucket is its shortest prefix whose rows fit.  One
aggregate gives the bytes of every leaf prefix, a second those of all their ancestors; both grow with the
number of shards, not of rows.  Leaves still too large (their rows' keys agree that far) are split further
in the same way on the rest of the key, and rows whose keys agree in all bits are cut by a running sum.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEY_BITS = 60
#: Bits that the first directory looks at beyond those that even buckets would need.
SPARE_BITS = 6


def hash_key(key: Column, text: Column) -> Column:
    """The first 60 bits of the md5 of a key's text, as a long; rows without a key hash by their text."""
    named = F.coalesce(key.cast("string"), text, F.lit("")).cast("binary")
    return F.conv(F.substring(F.md5(named), 1, KEY_BITS // 4), 16, 10).cast("long")


def _first_bits(value: Column, bits: Column | int, depth: Column | int) -> Column:
    """The first ``depth`` of a number of ``bits`` bits."""
    drop = (F.lit(bits) if isinstance(bits, int) else bits) - (F.lit(depth) if isinstance(depth, int) else depth)
    return F.call_function("shiftright", value, drop.cast("int"))


def _buckets(leaves: DataFrame, low: int, high: int, limit: int) -> DataFrame:
    """``leaf`` (``high`` bits), ``bytes`` -> the depth and bytes of its bucket; leaves that don't fit at all are left out."""
    levels = leaves.withColumn("depth", F.explode(F.sequence(F.lit(low), F.lit(high))))
    levels = levels.withColumn("bucket", _first_bits(F.col("leaf"), high, F.col("depth")))
    fitting = levels.groupBy("depth", "bucket").agg(F.sum("bytes").alias("bytes"))
    fitting = fitting.where(F.col("bytes") <= limit)
    return (
        levels.drop("bytes")
        .join(fitting, ["depth", "bucket"])
        .groupBy("leaf")
        .agg(F.min(F.struct("depth", "bucket", "bytes")).alias("own"))
        .select("leaf", "own.depth", "own.bucket", "own.bytes")
    )


def assign(docs: DataFrame, limit: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``n_bytes``, ``shard`` (the bucket's bits as text, then ``/page`` of an overflowing key), ``shard_bytes``, ``oversized``.

    Rows with a null key hash by their text; null texts have no bytes.  Every shard holds at most ``limit``
    bytes, but for a single row larger than that, which is alone in a shard marked ``oversized``.
    Repeated rows stand one by one.  An empty table gives an empty result.
    """
    rows = docs.select(F.col(key), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"), hash_key(F.col(key), F.col(text)).alias("_key"))
    total = rows.agg(F.sum("n_bytes")).first()[0] or 0
    depth = min(KEY_BITS - 1, max(1, int(-(-total // limit) - 1).bit_length() + SPARE_BITS))
    leaf = _first_bits(F.col("_key"), KEY_BITS, depth)
    leaves = rows.groupBy(leaf.alias("leaf")).agg(F.sum("n_bytes").alias("bytes"))
    near = _buckets(leaves, 0, depth, limit).withColumnRenamed("leaf", "_leaf")
    found = rows.withColumn("_leaf", leaf).join(near, "_leaf", "left")
    bits = F.lpad(F.conv(F.col("bucket").cast("string"), 10, 2), F.col("depth"), F.lit("0"))
    bits = F.when(F.col("depth") == 0, F.lit("")).otherwise(bits)
    done = found.where("depth is not null").select(key, "n_bytes", bits.alias("shard"), F.col("bytes").alias("shard_bytes"), F.lit(False).alias("oversized"))
    full = leaves.where(F.col("bytes") > limit)
    if full.isEmpty():
        return done
    rest = found.where("depth is null").drop("depth", "bucket", "bytes")
    deep = _buckets(rest.groupBy(F.col("_key").alias("leaf")).agg(F.sum("n_bytes").alias("bytes")), depth + 1, KEY_BITS, limit).withColumnRenamed("leaf", "_key")
    rest = rest.join(deep, "_key", "left")
    split = rest.where("depth is not null").select(key, "n_bytes", bits.alias("shard"), F.col("bytes").alias("shard_bytes"), F.lit(False).alias("oversized"))
    # keys that agree in all bits: small rows fill pages, of half the limit and one row at most; larger rows stand alone
    same = Window.partitionBy("_key").orderBy("n_bytes", key)
    paged = rest.where("depth is null").drop("depth", "bucket", "bytes")
    big = F.col("n_bytes") * 2 > limit
    running = F.sum(F.when(big, F.lit(0)).otherwise(F.col("n_bytes"))).over(same.rowsBetween(Window.unboundedPreceding, 0))
    page = F.when(big, F.concat(F.lit("/r"), F.row_number().over(same))).otherwise(F.concat(F.lit("/p"), F.floor(running * 2 / limit).cast("string")))
    paged = paged.withColumn("shard", F.concat(F.lpad(F.conv(F.col("_key").cast("string"), 10, 2), KEY_BITS, "0"), page))
    paged = paged.withColumn("shard_bytes", F.sum("n_bytes").over(Window.partitionBy("shard"))).select(key, "n_bytes", "shard", "shard_bytes", (F.col("n_bytes") > limit).alias("oversized"))
    return done.unionByName(split).unionByName(paged)


def write(docs: DataFrame, assigned: DataFrame, path: str, key: str = "doc_id") -> None:
    """Write the documents with a folder for each shard; ``assigned`` is ``assign``'s result for unique keys."""
    own = assigned.select(F.col(key).alias("_shard_of"), "shard")
    out = docs.join(own, docs[key].eqNullSafe(own["_shard_of"])).drop("_shard_of")
    out.repartition("shard").write.partitionBy("shard").parquet(path)
