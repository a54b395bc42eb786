"""Degree statistics, the splitting threshold, space, ranks and the choice of a strategy."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..graph import Graph

STRATEGIES = ("BS", "EP", "WD", "NS", "HP")
BINS = 10
#: Ease of building a strategy, as the literature ranks them: lower is easier.
COMPLEXITY = {"BS": 1, "EP": 1, "HP": 2, "WD": 3, "NS": 3}


def graph_stats(graph: Graph) -> DataFrame:
    """One row: nodes, edges, greatest, mean, deviation and root mean square outdegree, sinks.  Sums are integers until the last step."""
    d = F.col("deg")
    sums = graph.all_degrees().agg(F.count("*").alias("n"), F.sum(d).alias("e"), F.max(d).alias("max_deg"), F.sum(d * d).alias("ee"), F.sum((d == 0).cast("long")).alias("sinks"))
    n, e, ee = (F.col(c).cast("double") for c in ("n", "e", "ee"))
    return sums.select(
        F.col("n").alias("n_nodes"), F.col("e").alias("n_edges"), "max_deg", F.round(e / n, 6).alias("avg_deg"), F.round(F.sqrt(n * ee - e * e) / n, 4).alias("std_deg"), F.round(F.sqrt(ee / n), 4).alias("rms_deg"), "sinks"
    )


def degree_histogram(degrees: DataFrame) -> DataFrame:
    return degrees.groupBy("deg").agg(F.count("*").alias("n_nodes"))


def bin_of(deg: Column, most: Column, bins: int) -> Column:
    """Upper-inclusive bins from 1; sinks lie in the first."""
    return F.greatest(F.lit(1), F.ceil(deg * bins / F.greatest(most, F.lit(1)))).cast("long")


def degree_bins(degrees: DataFrame, bins: int = BINS) -> DataFrame:
    """``bin``, ``lo`` (exclusive), ``hi`` (inclusive), ``n_nodes`` of every bin, empty ones too; from a histogram by degree, so no row per node is moved."""
    histogram = degree_histogram(degrees)
    most = histogram.agg(F.max("deg").alias("max_deg"))
    held = histogram.join(F.broadcast(most)).groupBy(bin_of(F.col("deg"), F.col("max_deg"), bins).alias("bin")).agg(F.sum("n_nodes").alias("n_nodes"))  # one row beside each
    every = most.select("max_deg", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(bins).cast("long"))).alias("bin"))
    edge = lambda i: F.floor(i * F.col("max_deg") / bins).cast("long")
    return every.join(held, "bin", "left").select("bin", edge(F.col("bin") - 1).alias("lo"), edge(F.col("bin")).alias("hi"), F.coalesce("n_nodes", F.lit(0)).alias("n_nodes"))


def find_mdt(degrees: DataFrame, rule: str | int = "auto", bins: int = BINS, sinks: bool = True) -> int:
    """The greatest outdegree that stays unsplit.

    ``auto``: the modal bin's share of the greatest degree (ties to the larger bin); ``max``; ``max_minus_avg``; or a number.
    """
    if isinstance(rule, int):
        return max(1, rule)
    own = degrees if sinks else degrees.where("deg > 0")
    row = own.agg(F.max("deg").alias("most"), F.sum("deg").alias("e"), F.count("*").alias("n")).first()
    most = int(row["most"] or 0)
    if rule == "max":
        return max(1, most)
    if rule == "max_minus_avg":
        return max(1, most - int(row["e"] or 0) // max(1, row["n"]))
    if rule != "auto":
        raise ValueError(f"unknown rule: {rule}")
    top = degree_bins(own, bins).orderBy(F.desc("n_nodes"), F.desc("bin")).first()
    return max(1, top["bin"] * most // bins) if top else 1


def parts_of(deg: Column, mdt: int) -> Column:
    return F.greatest(F.lit(1), F.ceil(deg / mdt)).cast("long")


def mdt_report(degrees: DataFrame, rules: dict[str, int]) -> DataFrame:
    """``rule``, ``max_deg``, ``mdt``, ``n_split``, ``n_children``, ``split_permille`` for each threshold."""
    cells = [F.max("deg").alias("max_deg"), F.count("*").alias("n")]
    for name, mdt in rules.items():
        over = F.col("deg") > mdt
        cells += [F.sum(over.cast("long")).alias(f"s_{name}"), F.sum(parts_of(F.col("deg"), mdt) - 1).alias(f"c_{name}")]
    row = F.array(*(F.struct(F.lit(name).alias("rule"), F.lit(mdt).cast("long").alias("mdt"), F.col(f"s_{name}").alias("n_split"), F.col(f"c_{name}").alias("n_children")) for name, mdt in rules.items()))
    out = degrees.agg(*cells).select("max_deg", "n", F.explode(row).alias("r")).select("r.*", "max_deg", "n")
    return out.select("rule", "max_deg", "mdt", "n_split", "n_children", F.floor(F.col("n_split") * 1000 / F.col("n")).cast("long").alias("split_permille"))


def memory_words(n: int, e: int, children: int, workers: int, weighted: bool = True) -> dict[str, int]:
    """Four-byte words that each strategy holds at most: its layout and its worklists.

    BS: compact rows and two node lists.  EP: edge list and two edge lists.  WD: BS, degrees beside both lists, two
    words a worker.  NS: BS over nodes and children.  HP: BS and a sublist with its cursor.
    """
    rows, listed = n + e + e * weighted, 2 * e + e * weighted
    return {"BS": rows + 2 * n, "EP": listed + 2 * 2 * e, "WD": rows + 4 * n + 2 * workers, "NS": rows + 2 * n + 3 * children + n, "HP": rows + 2 * n + 2 * n}


def memory_frame(graph: Graph, children: int, workers: int, budget: int) -> DataFrame:
    """``strategy``, ``words``, ``fits``, ``status``."""
    row = graph.all_degrees().agg(F.count("*").alias("n"), F.sum("deg").alias("e")).first()
    words = memory_words(row["n"], row["e"] or 0, children, workers)
    spark = graph.edges.sparkSession
    rows = [(s, w, w <= budget, "runs" if w <= budget else "insufficient_memory") for s, w in words.items()]
    return spark.createDataFrame(rows, "strategy string, words long, fits boolean, status string")


def advise(stats: dict, budget: int, distributive: bool = True, diameter: str = "small", app: str = "sssp", skew_limit: float = 4.0, huge: int = 10**8) -> tuple[str, str]:
    """The strategy to use and the rule that chose it.

    ``stats``: ``n``, ``e``, ``max_deg``, ``children``, ``workers``.  Rules in order: a program that cannot be cut stays node-based;
    the edge list where it fits; hierarchical on huge graphs; blocks where degrees are skewed or paths short; splitting
    on even, long graphs, or plain nodes where a cheap search would split nothing.
    """
    if not distributive:
        return "BS", "program is not distributive"
    words = memory_words(stats["n"], stats["e"], stats["children"], stats["workers"])
    if words["EP"] <= budget:
        return "EP", "edge list fits"
    if stats["e"] >= huge or words["WD"] > budget:
        return "HP", "only compact rows fit"
    if stats["max_deg"] > skew_limit * stats["e"] / max(1, stats["n"]) or diameter == "small":
        return "WD", "skewed degrees or small diameter"
    if app == "bfs" and not stats["children"]:
        return "BS", "cheap search and nothing to split"
    return "NS", "even degrees and large diameter"


def imbalance(loads: DataFrame, keys: list[str], workers: int) -> DataFrame:
    """``max_load``, ``total``, ``imbalance_permille`` (greatest load over the mean of all workers, times 1000) by key, from two small aggregates."""
    return loads.groupBy(*keys).agg(F.max("load").alias("max_load"), F.sum("load").alias("total")).withColumn("imbalance_permille", F.floor(F.col("max_load") * 1000 * workers / F.greatest(F.col("total"), F.lit(1))).cast("long"))


def gini(loads: DataFrame, value: str = "load") -> DataFrame:
    """One row ``gini``: 0 for equal loads.  From a histogram of loads, a row for each different load."""
    held = loads.groupBy(F.col(value).cast("double").alias("x")).agg(F.count("*").cast("double").alias("n"))
    below = Window.orderBy("x").rowsBetween(Window.unboundedPreceding, -1)
    ranked = held.withColumn("before", F.coalesce(F.sum("n").over(below), F.lit(0.0)))
    # the i-th smallest of all loads counts 2i - n - 1 times; equal ones together
    parts = ranked.agg(F.sum("n").alias("n"), F.sum(F.col("x") * F.col("n")).alias("s"), F.sum(F.col("x") * F.col("n") * (2 * F.col("before") + F.col("n") + 1)).alias("w"))
    return parts.select(F.round((F.col("w") - (F.col("n") + 1) * F.col("s")) / (F.col("n") * F.col("s")), 6).alias("gini"))


def variation(loads: DataFrame, keys: list[str], workers: int) -> DataFrame:
    """``cv_permille``: deviation over mean of the loads of all workers (those without a row hold none), by key."""
    sums = loads.groupBy(*keys).agg(F.sum("load").alias("s"), F.sum(F.col("load") * F.col("load")).alias("ss"))
    return sums.select(*keys, F.floor(1000 * F.sqrt(workers * F.col("ss") - F.col("s") * F.col("s")) / F.col("s")).cast("long").alias("cv_permille"))


def reduction(base: float, other: float) -> float:
    """Percent less time than the baseline; below zero for more."""
    return round(100 * (base - other) / base, 1) if base else 0.0


def traversed_per_second(edges: int, seconds: float) -> float:
    """Millions of traversed edges a second."""
    return edges / seconds / 1e6 if seconds > 0 else 0.0
