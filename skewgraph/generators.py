"""Seeded graph generators as pure functions of md5 digests, so that any SQL engine can draw the same edges.

``ids``: a frame whose ``id`` numbers the edges, or the cells of the grid: the keys of a table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def draw(*parts) -> Column:
    """A number below 2**32 from the parts' text."""
    text = F.concat_ws(":", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def rmat(ids: DataFrame, scale: int, seed: int, a: int = 57, b: int = 19, c: int = 19) -> DataFrame:
    """Recursive-matrix edges over 2**scale nodes; quadrant odds in percent, the last takes the rest.  Weights 1..50."""
    i = F.col("id")
    src = dst = F.lit(0).cast("long")
    for level in range(scale):
        p = draw(seed, i, level) % 100
        src = src * 2 + (p >= a + b).cast("long")
        dst = dst * 2 + ((p >= a) & (p < a + b) | (p >= a + b + c)).cast("long")
    return ids.select(src.alias("src"), dst.alias("dst"), (draw(seed, i, "w") % 50 + 1).alias("w"))


def erdos_renyi(ids: DataFrame, n: int, seed: int) -> DataFrame:
    """An edge for each id, with ends drawn evenly from ``n`` nodes."""
    i = F.col("id")
    return ids.select((draw(seed, i, "s") % n).alias("src"), (draw(seed, i, "d") % n).alias("dst"), (draw(seed, i, "w") % 50 + 1).alias("w"))


def lattice(ids: DataFrame, cols: int, seed: int) -> DataFrame:
    """Right and down neighbours of a grid of the ids from 0 on, both ways, one weight for both."""
    i, n = F.col("id"), ids.count()
    right = F.when(((i + 1) % cols != 0) & (i + 1 < n), i + 1)
    down = F.when(i + cols < n, i + cols)
    near = ids.select(i.alias("a"), F.explode(F.array(right, down)).alias("b")).where("b is not null")
    near = near.withColumn("w", draw(seed, F.col("a"), F.col("b")) % 50 + 1)
    return near.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))).alias("e")).select("e.*")
