"""Edges per worker and launch that each strategy gives for the frontiers of a search."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..operators import scan
from ..operators.strategies import split_map


def frontiers(graph: Graph, levels: DataFrame, supersteps: int) -> DataFrame:
    """``superstep`` (from 1), ``node``, ``deg`` of the first supersteps' frontiers, nodes with out-edges only."""
    rows = levels.where(F.col("value") < supersteps).select((F.col("value") + 1).alias("superstep"), "node")
    return rows.join(graph.degrees(), "node").select("superstep", "node", "deg")


def _dealt(rows: DataFrame, load: str, workers: int) -> DataFrame:
    """Round robin by rank."""
    return rows.groupBy("superstep", "launch", (F.col("rank") % workers + 1).alias("worker")).agg(F.sum(load).alias("load"))


def _even(total: DataFrame, workers: int, blocks: bool) -> DataFrame:
    """Loads of ``superstep``, ``launch``, ``a`` edges in blocks, or dealt one by one: no row per edge is ever made."""
    t = F.col("t")
    share = F.ceil(F.col("a") / workers)
    load = F.least(share, F.col("a") - t * share) if blocks else F.floor((F.col("a") - t + workers - 1) / workers)
    rows = total.withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(workers - 1).cast("long"))))
    return rows.select("superstep", "launch", (t + 1).alias("worker"), load.cast("long").alias("load")).where("load > 0")


def loads(strategy: str, front: DataFrame, degrees: DataFrame, workers: int, mdt: int, switch_below: int) -> DataFrame:
    """``superstep``, ``launch`` (from 0), ``worker`` (from 1), ``load``; workers without edges have no row."""
    zero = F.lit(0).cast("long").alias("launch")
    if strategy in ("EP", "WD"):
        return _even(front.groupBy("superstep").agg(F.sum("deg").alias("a")).select("superstep", zero, "a"), workers, strategy == "WD")
    if strategy == "BS":
        return _dealt(scan.inclusive(front, ["node"], "deg", ["superstep"]).select("*", zero), "deg", workers)
    if strategy == "NS":
        parts = split_map(degrees, mdt).withColumnRenamed("parent", "node")
        split = front.join(parts, "node", "left").select("superstep", "node", F.coalesce("child_no", F.lit(0)).alias("child_no"), F.coalesce("part_deg", "deg").alias("part_deg"))
        return _dealt(scan.inclusive(split, ["node", "child_no"], "part_deg", ["superstep"]).select("*", zero), "part_deg", workers)
    slices = front.withColumn("launch", F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(F.col("deg") / mdt).cast("long") - 1)))
    sizes = slices.groupBy("superstep", "launch").agg(F.count("*").alias("size"))
    switch = sizes.where(F.col("size") < switch_below).groupBy("superstep").agg(F.min("launch").alias("switch"))
    slices = slices.join(switch, "superstep", "left")
    plain = slices.where("switch is null or launch < switch").withColumn("part", F.least(F.lit(mdt), F.col("deg") - F.col("launch") * mdt))
    tail = slices.where("launch = switch").groupBy("superstep", "launch").agg(F.sum(F.col("deg") - F.col("launch") * mdt).alias("a"))
    return _dealt(scan.inclusive(plain, ["node"], "part", ["superstep", "launch"]), "part", workers).unionByName(_even(tail, workers, True))


def sublist_report(front: DataFrame, mdt: int, switch_below: int) -> DataFrame:
    """``superstep``, ``launch``, ``size`` of the sublist, ``edges`` handled, ``mode`` (sub or block)."""
    slices = front.withColumn("launch", F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(F.col("deg") / mdt).cast("long") - 1)))
    left = F.col("deg") - F.col("launch") * mdt
    rows = slices.groupBy("superstep", "launch").agg(F.count("*").alias("size"), F.sum(F.least(F.lit(mdt), left)).alias("slice"), F.sum(left).alias("rest"))
    switch = rows.where(F.col("size") < switch_below).groupBy("superstep").agg(F.min("launch").alias("switch"))
    block = F.col("switch").isNotNull() & (F.col("launch") == F.col("switch"))
    return rows.join(switch, "superstep", "left").where("switch is null or launch <= switch").select("superstep", "launch", "size", F.when(block, F.col("rest")).otherwise(F.col("slice")).alias("edges"), F.when(block, "block").otherwise("sub").alias("mode"))


def push_report(graph: Graph, levels: DataFrame, supersteps: int) -> DataFrame:
    """``superstep``, ``edge_pushes`` (each out-edge of each improving relaxation alone), ``chunk_pushes`` (one for each
    improving relaxation), ``nodes`` improved, ``raw`` and ``condensed`` worklist edges, of a level-synchronous search."""
    first = levels.select(F.col("node").alias("src"), F.col("value").alias("from"))
    hits = graph.edges.join(first, "src").join(levels.select(F.col("node").alias("dst"), F.col("value").alias("to")), "dst").where((F.col("to") == F.col("from") + 1) & (F.col("from") < supersteps))
    per_node = hits.groupBy((F.col("from") + 1).alias("superstep"), F.col("dst").alias("node")).agg(F.count("*").alias("times"))
    rows = per_node.join(graph.degrees(), "node", "left").withColumn("deg", F.coalesce("deg", F.lit(0)))
    return rows.groupBy("superstep").agg(F.sum(F.col("times") * F.col("deg")).alias("edge_pushes"), F.sum("times").alias("chunk_pushes"), F.count("*").alias("nodes"), F.sum(F.col("times") * F.col("deg")).alias("raw"), F.sum("deg").alias("condensed"))
