"""Connected components of a link table by alternating star contractions, as joins and minima only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared

MAX_ROUNDS = 60


def _large_star(edges: DataFrame) -> DataFrame:
    """Every node hands its larger neighbours to its least neighbour (itself included)."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Every node hands itself and its smaller neighbours to the least of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    handed = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return handed.unionByName(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def components(links: DataFrame, name: str = "components") -> Shared:
    """``links``: ``a``, ``b`` (long), undirected; self-links, repeats and nulls are ignored.

    Returns a written table ``id``, ``root`` of every linked node but the roots, which are the least ids of
    their components.  Each round is written to the shared folder, so the lineage never grows and a lost
    executor costs one round at most; the driver sees two sums per round.
    """
    start = links.where("a is not null and b is not null and a <> b").select(F.col("a").cast("long"), F.col("b").cast("long")).distinct()
    table, before = Shared(start, name), None
    for _ in range(MAX_ROUNDS):
        now = tuple(table.frame.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if now == before or not now[0]:
            break
        before = now
        following = Shared(_small_star(_large_star(table.frame)), name)
        table.drop()
        table = following
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    result = Shared(table.frame.select(F.col("a").alias("id"), F.col("b").alias("root")), name)
    table.drop()
    return result
