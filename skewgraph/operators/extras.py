"""Further applications of the same loop: minimum spanning forests and betweenness."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..plans.lineage import Table, counted, cut


def _tops(picks: DataFrame) -> DataFrame:
    """``a``, ``root``: where following ``to`` ends, by pointer jumping; of two that pick each other the lesser is the root."""
    back = picks.select(F.col("a").alias("to"), F.col("to").alias("back"))
    parent = cut(picks.join(back, "to").select("a", F.when((F.col("back") == F.col("a")) & (F.col("a") < F.col("to")), F.col("a")).otherwise(F.col("to")).alias("root")))
    while True:
        far = parent.withColumn("old", F.col("root"))
        for _ in range(2):  # four links in one job
            up = far.select(F.col("a").alias("root"), F.col("root").alias("top"))
            far = far.join(up, "root").select("a", F.col("top").alias("root"), "old")
        jumped = cut(far.select("a", "root", (F.col("root") != F.col("old")).alias("moved")))
        if jumped.where("moved").isEmpty():
            return jumped.select("a", "root")
        parent = jumped.drop("moved")


def spanning_forest(edges: DataFrame) -> DataFrame:
    """``w``, ``lo``, ``hi``: the minimum spanning forest of the edges taken as undirected; ties by (lo, hi), so it is unique.

    Each round every tree takes its lightest way out and the trees so joined contract to one node, with the lightest
    edge between any two: at least half of the trees go each round.  Self-loops and heavier parallel edges never count.
    """
    lo, hi = F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi")
    own = edges.where("src <> dst").groupBy(lo, hi).agg(F.min("w").alias("w"))
    live = cut(own.select(F.col("lo").alias("a"), F.col("hi").alias("b"), F.struct("w", "lo", "hi").alias("e")))
    taken = [live.limit(0).select("e.*")]
    while not live.isEmpty():
        both = live.unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b"), "e"))
        best = both.groupBy("a").agg(F.min(F.struct("e", "b")).alias("m"))
        picks = cut(best.select("a", F.col("m.b").alias("to"), F.col("m.e").alias("e")))
        taken.append(picks.select("e.*").distinct())
        tops = _tops(picks.select("a", "to"))
        for side in ("a", "b"):
            live = live.join(tops.select(F.col("a").alias(side), F.col("root").alias(f"_{side}")), side)
        ends = F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b")
        live = cut(live.where("_a <> _b").groupBy(*ends).agg(F.min("e").alias("e")))
    return reduce(DataFrame.unionByName, taken)


def betweenness(graph: Graph, sources: DataFrame | None = None, most_rows: int = 20_000_000) -> DataFrame:
    """``node``, ``score``: how much of the shortest (fewest edges) paths between other nodes runs through each node, exactly.

    ``sources`` (``node``): where paths begin, by default every node.  All sources are swept at once: forwards, level by
    level, the paths are counted; backwards they are shared out.  Sources that reach more than ``most_rows`` (source,
    node) pairs are swept in two halves instead, and so on.  A path's ends score nothing; nodes on no path score 0.
    """
    nodes = cut(graph.nodes())
    starts = cut(sources.select("node").distinct()) if sources is not None else nodes
    edges = cut(graph.edges.select("src", "dst"))
    open_blocks, scores = [(1, 0)], []
    while open_blocks:
        blocks, b = open_blocks.pop()
        found = _swept(edges, starts.where(F.pmod(F.xxhash64("node"), F.lit(blocks)) == b), most_rows)
        if found is None:
            open_blocks += [(2 * blocks, b), (2 * blocks, b + blocks)]
        else:
            scores.append(found)
    total = reduce(DataFrame.unionByName, scores).groupBy("node").agg(F.sum("score").alias("score"))
    return nodes.join(total, "node", "left").select("node", F.round(F.coalesce("score", F.lit(0.0)), 6).alias("score"))


def _swept(edges: DataFrame, starts: DataFrame, most_rows: int) -> DataFrame | None:
    """``source``, ``node``, ``score`` of the paths from a block of sources; None if several reach over ``most_rows`` pairs."""
    table, found = counted(starts.select(F.col("node").alias("source"), "node", F.lit(1.0).alias("paths")), "paths", n=F.count("*"))
    levels, sources, pairs = [table], found["n"], found["n"]
    while True:
        if pairs > most_rows and sources > 1:
            for t in levels:
                t.drop()
            return None
        seen = reduce(DataFrame.unionByName, [t.frame.select("source", "node") for t in levels])
        on = levels[-1].frame.join(edges, F.col("node") == F.col("src")).groupBy("source", F.col("dst").alias("node")).agg(F.sum("paths").alias("paths"))
        table, found = counted(on.join(seen, ["source", "node"], "left_anti"), "paths", n=F.count("*"))
        if not found["n"]:
            break
        levels.append(table)
        pairs += found["n"]
    below, out = levels[-1].frame.withColumn("score", F.lit(0.0)), []
    out.append(below)
    for table in reversed(levels[:-1]):
        share = below.select(F.col("source").alias("_s"), F.col("node").alias("dst"), ((1 + F.col("score")) / F.col("paths")).alias("share"))
        own = table.frame.join(edges, F.col("node") == F.col("src")).join(share, (F.col("source") == F.col("_s")) & (edges["dst"] == share["dst"]), "left")
        met = own.groupBy("source", "node").agg(F.max("paths").alias("paths"), F.sum("share").alias("share"))
        whole = table.frame.join(met.select("source", "node", "share"), ["source", "node"], "left")
        below = Table(whole.select("source", "node", "paths", (F.col("paths") * F.coalesce("share", F.lit(0.0))).alias("score")), "scores").frame
        out.append(below)
    return reduce(DataFrame.unionByName, out).where("source <> node").select("source", "node", "score")


def dependencies(graph: Graph, source) -> DataFrame:
    """``node``, ``score``: the part of ``betweenness`` that the paths from one source give."""
    kind = graph.edges.schema["src"].dataType.simpleString()
    return betweenness(graph, graph.edges.sparkSession.createDataFrame([(source,)], f"node {kind}"))
