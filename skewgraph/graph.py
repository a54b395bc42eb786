"""Directed graphs as edge tables, with a paged row layout, a flat one and degree tables."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators.salted import beside
from .plans.lineage import Table

#: Edges of one page: caps rows and arrays whatever a node's degree.
PAGE = 4096


def validate(edges: DataFrame) -> DataFrame:
    """The edges, failing at run time on null ends or weights below zero."""
    bad = F.col("src").isNull() | F.col("dst").isNull() | F.coalesce(F.col("w") < 0, F.lit(True))
    return edges.withColumn("w", F.when(bad, F.raise_error(F.lit("edge with a null end or a weight that is null or below zero"))).otherwise(F.col("w")))


@dataclass
class Graph:
    """``edges``: ``src``, ``dst``, ``w``; every end is a node, and ``isolated`` nodes may be added."""

    edges: DataFrame
    isolated: DataFrame | None = None
    page: int = PAGE
    _made: dict[str, Table] = field(default_factory=dict)
    _given: DataFrame | None = None

    @classmethod
    def of(cls, edges: DataFrame, checked: bool = True, **more) -> Graph:
        own = edges if "w" in edges.columns else edges.withColumn("w", F.lit(1).cast("long"))
        own = own.select("src", "dst", "w")
        return cls(validate(own) if checked else own, **more)

    @classmethod
    def from_rows(cls, spark: SparkSession, rows: Iterable[tuple], kind: str = "long", **more) -> Graph:
        """A graph of rows (src, dst) or (src, dst, w) at hand."""
        full = [(*r, 1)[:3] for r in rows]
        return cls.of(spark.createDataFrame(full, f"src {kind}, dst {kind}, w long"), **more)

    def kept(self, name: str, make, keys: list[str] | None = None) -> DataFrame:
        """A layout written once for a run's many supersteps, bucketed by ``keys``."""
        if name not in self._made:
            self._made[name] = Table(make(), name, keys)
        return self._made[name].frame

    def cached(self) -> Graph:
        """The same graph with its edges and degrees written to the shared folder, for many passes."""
        if "edges" not in self._made:
            self._given, self.edges = self.edges, self.kept("edges", lambda: self.edges)
        self.kept("nodes", self.all_degrees, ["node"])
        return self

    def release(self) -> None:
        """Delete the written layouts; the graph is as it was given."""
        if "edges" in self._made:
            self.edges = self._given
        for table in self._made.values():
            table.drop()
        self._made.clear()

    def nodes(self) -> DataFrame:
        return self.all_degrees().select("node")

    def degrees(self) -> DataFrame:
        """``node``, ``deg`` of nodes with out-edges."""
        if "nodes" in self._made:
            return self._made["nodes"].frame.where("deg > 0")
        return self.edges.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("deg"))

    def all_degrees(self) -> DataFrame:
        """``node``, ``deg`` of every node, sinks included, in one aggregate."""
        if "nodes" in self._made:
            return self._made["nodes"].frame
        ends = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("n")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("n")))).alias("x")).select("x.*")
        if self.isolated is not None:
            ends = ends.unionByName(self.isolated.select("node", F.lit(0).alias("n")))
        return ends.groupBy("node").agg(F.sum("n").alias("deg"))

    def pages(self) -> DataFrame:
        """Paged rows ``node``, ``page``, ``first``, ``deg``, ``adj`` (array of dst, w in order): the compact layout.

        Page p holds the node's edges number p * page and on, so pieces of a node find their pages by arithmetic.  A
        node of at most ``page`` edges is one row.  The edges of larger ones are first dealt by a digest over groups
        of about a page; the groups' sizes give each group's first number and only groups are sorted.  Neither a
        shuffle nor a sort ever brings a hub's edges into one task.
        """
        return self._made["pages"].frame if "pages" in self._made else self._pages()

    def _pages(self) -> DataFrame:
        entry = F.struct("dst", "w")
        hubs, held = beside(self.degrees().where(F.col("deg") > self.page).select(F.col("node").alias("hub"), "deg"))
        rows = lambda edges, **key: edges.groupBy(F.col("src").alias("node"), *(c.alias(n) for n, c in key.items()))
        if not held:
            small = rows(self.edges).agg(F.sort_array(F.collect_list(entry)).alias("adj"))
            return small.select("node", F.lit(0).cast("long").alias("page"), F.lit(0).cast("long").alias("first"), F.size("adj").cast("long").alias("deg"), "adj")
        met = self.edges.join(hubs, F.col("src") == F.col("hub"), "left")
        small = rows(met.where("hub is null")).agg(F.sort_array(F.collect_list(entry)).alias("adj"))
        small = small.select("node", F.lit(0).cast("long").alias("page"), F.size("adj").cast("long").alias("deg"), "adj")
        dealt = met.where("hub is not null").withColumn("group", F.pmod(F.xxhash64("dst", "w"), F.ceil(F.col("deg") / self.page)))
        before = Window.partitionBy("_src").orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)
        sizes = dealt.groupBy(F.col("src").alias("_src"), F.col("group").alias("_group")).agg(F.count("*").alias("n"))
        starts = sizes.select("_src", "_group", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
        inside = F.row_number().over(Window.partitionBy("src", "group").orderBy("dst", "w")) - 1
        numbered = dealt.withColumn("at", inside).join(starts, (F.col("src") == F.col("_src")) & (F.col("group") == F.col("_group"))).withColumn("at", F.col("at") + F.col("start"))
        ordered = F.transform(F.sort_array(F.collect_list(F.struct("at", "dst", "w"))), lambda x: F.struct(x["dst"].alias("dst"), x["w"].alias("w")))
        large = rows(numbered, page=F.floor(F.col("at") / self.page).cast("long")).agg(F.max("deg").alias("deg"), ordered.alias("adj"))
        return small.unionByName(large).select("node", "page", (F.col("page") * self.page).alias("first"), "deg", "adj")

    def flat(self) -> DataFrame:
        """``node``, ``page``, ``at`` (from 0 within the page), ``dst``, ``w``: the edge list with places, made from the paged rows."""
        return self.pages().select("node", "page", F.posexplode("adj").alias("at", "e")).select("node", "page", "at", "e.dst", "e.w")


def to_edges(pages: DataFrame) -> DataFrame:
    """Paged rows as an edge table."""
    return pages.select(F.col("node").alias("src"), F.explode("adj").alias("e")).select("src", "e.dst", "e.w")
