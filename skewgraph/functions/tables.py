"""Table functions for SQL users: parts of a split node, blocks of a frontier."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="child_no bigint, part_deg bigint")
class SplitNode:
    """The parts of one node of ``deg`` edges under a threshold; none if it needs no split."""

    def eval(self, deg: int, mdt: int) -> Iterator[tuple[int, int]]:
        parts = -(-deg // mdt)
        bounds = [-(-c * deg // parts) for c in range(parts + 1)] if parts > 1 else []
        yield from ((c, b - a) for c, (a, b) in enumerate(zip(bounds, bounds[1:], strict=False)))


@udtf(returnType="worker bigint, node bigint, offset bigint, len bigint")
class FrontierBlocks:
    """Equal blocks over one ordered frontier given as a table ``node``, ``deg``: for frontiers that fit a task."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int]] = []
        self.workers = 1

    def eval(self, row: Row, workers: int) -> None:
        self.rows.append((row["node"], row["deg"]))
        self.workers = workers

    def terminate(self) -> Iterator[tuple[int, int, int, int]]:
        share, at = max(1, -(-sum(d for _, d in self.rows) // self.workers)), 0
        for node, deg in self.rows:
            done = 0
            while done < deg:
                take = min(deg - done, share - at % share)
                yield at // share + 1, node, done, take
                done, at = done + take, at + take


def register(spark: SparkSession) -> None:
    """``split_node(deg, mdt)`` and ``frontier_blocks(table, workers)`` as SQL names."""
    spark.udtf.register("split_node", SplitNode)
    spark.udtf.register("frontier_blocks", FrontierBlocks)
