"""Graph views over the given tables: one edge a (src, dst), with the family of graph that each stands for."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .plans.lineage import cut
from .sources import table

#: Offsets that keep the ids of different tables apart.
PARTS, USERS, TYPES = 10**9, 10**9, 2 * 10**9


#: Room for the rounding of a matrix product, within which cosines are compared by their exact sums.
_SLACK = 1e-9
#: Vectors up to which their blocks are broadcast.
_BROADCAST = 50_000


def _both_ways(edges: DataFrame) -> DataFrame:
    turned = F.array(F.struct("src", "dst", "w"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return edges.select(F.explode(turned).alias("e")).select("e.*")


def _least(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src", "dst").agg(F.min("w").alias("w"))


def part_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive lines of an order: near-random, weighted."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    pairs = line.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst"), F.col("l_quantity").cast("long").alias("w"))
    return _least(pairs.where("dst is not null and src <> dst"))


def supplier_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers and their parts: skewed, two-sided."""
    line = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") + PARTS).alias("dst")).distinct()
    return _both_ways(line.withColumn("w", F.lit(1).cast("long")))


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders and their parts: degrees of two kinds, weighted."""
    line = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("src"), (F.col("l_partkey") + PARTS).alias("dst"), F.col("l_quantity").cast("long").alias("w"))
    return _both_ways(_least(line))


def event_hub(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events, their types and users: a few giant hubs."""
    events = table(spark, sf_dir, "events").select("event_id", "event_type", "user_id")
    kinds = events.select("event_type").distinct()  # a row for each type
    kinds = kinds.withColumn("kind", F.dense_rank().over(Window.partitionBy(F.lit(0)).orderBy("event_type")) + TYPES)
    typed = events.join(kinds, "event_type").select(F.col("event_id").alias("src"), F.col("kind").cast("long").alias("dst"))
    used = events.select(F.col("event_id").alias("src"), (F.col("user_id") + USERS).alias("dst"))
    return _both_ways(typed.unionByName(used).withColumn("w", F.lit(1).cast("long")))


def _chain(events: DataFrame, key: str) -> DataFrame:
    """Each event and the next of the same key, day by day so that no key's events meet in one task."""
    day = events.withColumn("day", F.date_trunc("day", "ts"))
    inside = Window.partitionBy(key, "day").orderBy("ts", "event_id")
    steps = day.select(F.col("event_id").alias("src"), F.lead("event_id").over(inside).alias("dst")).where("dst is not null")
    ends = day.groupBy(key, "day").agg(F.min(F.struct("ts", "event_id"))["event_id"].alias("first"), F.max(F.struct("ts", "event_id"))["event_id"].alias("last"))
    across = ends.select(F.col("last").alias("src"), F.lead("first").over(Window.partitionBy(key).orderBy("day")).alias("dst")).where("dst is not null")
    return steps.unionByName(across)


def event_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of events per user and per type: long paths, few edges a node."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    chains = _chain(events, "user_id").unionByName(_chain(events, "event_type"))
    return _both_ways(chains.distinct().withColumn("w", F.lit(1).cast("long"))).distinct()


def part_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts on a square lattice: like roads, weighted."""
    part = table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("long").alias("w"))
    n = part.count()
    width = int(-(-(n**0.5) // 1))
    right = F.when((F.col("p_partkey") + 1) % width != 0, F.col("p_partkey") + 1)
    near = part.select(F.col("p_partkey").alias("src"), F.explode(F.array(right, F.col("p_partkey") + width)).alias("dst"), "w")
    return _both_ways(near.where(F.col("dst") < n))


def _keyed(frame: DataFrame, a: str, b: str, kind_a: str, kind_b: str, parts_b: int = 0) -> DataFrame:
    own = frame.select(F.concat(F.lit(kind_a), F.col(a).cast("string")).alias("src"), F.concat(F.lit(kind_b), F.col(b).cast("string")).alias("dst"))
    return own.distinct()


def fk_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All foreign keys among six tables, with text ids."""
    get = lambda name: table(spark, sf_dir, name)
    lines = get("lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    parts = [
        _keyed(get("nation"), "n_regionkey", "n_nationkey", "r", "n"),
        _keyed(get("customer"), "c_nationkey", "c_custkey", "n", "c"),
        _keyed(get("supplier"), "s_nationkey", "s_suppkey", "n", "s"),
        _keyed(get("orders"), "o_custkey", "o_orderkey", "c", "o"),
        _keyed(lines, "l_orderkey", "l_partkey", "o", "p"),
        _keyed(lines, "l_suppkey", "l_partkey", "s", "p"),
    ]
    out = parts[0]
    for more in parts[1:]:
        out = out.unionByName(more)
    return _both_ways(out.withColumn("w", F.lit(1).cast("long")))


def token_bigram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neighbouring tokens of documents: power law, weighted by occurrences."""
    tokens = table(spark, sf_dir, "documents").select(F.split("text", " ").alias("t"))
    pairs = tokens.select(F.explode(F.arrays_zip(F.slice("t", 1, F.greatest(F.size("t") - 1, F.lit(0))).alias("src"), F.slice("t", 2, F.greatest(F.size("t") - 1, F.lit(0))).alias("dst"))).alias("p")).select("p.*")
    return pairs.where("src <> '' and dst <> ''").groupBy("src", "dst").agg(F.count("*").alias("w"))


def page_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the link targets they hold."""
    pages = table(spark, sf_dir, "pages")
    found = pages.select(F.concat(F.lit("page:"), F.col("page_id").cast("string")).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst"))
    return found.distinct().withColumn("w", F.lit(1).cast("long"))


def turn_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive turns of conversations."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    step = turns.select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")).alias("next"), "conv_id")
    return step.where("next is not null").select("src", (F.col("conv_id") * 1000 + F.col("next")).alias("dst"), F.lit(1).cast("long").alias("w"))


def _running(products: np.ndarray) -> np.ndarray:
    """Sums along the last axis, term by term, whatever the number of rows."""
    return np.add.accumulate(products, axis=-1)[..., -1]


def _nearest(k: int):
    """The k nearest of one block for each vector of another: screened by a matrix product, decided by exact sums."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                ids, others = np.array(x["ids"], np.int64), np.array(x["other_ids"], np.int64)
                q, c = np.array(x["v"]).reshape(len(ids), -1), np.array(x["u"]).reshape(len(others), -1)
                q_norm, c_norm = np.sqrt(_running(q * q)), np.sqrt(_running(c * c))
                near = (q / q_norm[:, None]) @ (c / c_norm[:, None]).T
                near[ids[:, None] == others[None, :]] = -np.inf
                least = np.partition(near, -min(k, len(others)), axis=1)[:, -min(k, len(others))]
                i, j = np.nonzero((near >= least[:, None] - _SLACK) & (near > -np.inf))
                cosine = np.concatenate([np.zeros(0), *(_running(q[i[s : s + 16384]] * c[j[s : s + 16384]]) for s in range(0, len(i), 16384))]) / (q_norm[i] * c_norm[j])
                order = np.lexsort((others[j], -cosine, i))
                i, j, cosine = i[order], j[order], cosine[order]
                first = np.searchsorted(i, i)
                top = np.flatnonzero(np.arange(len(i)) - first < k)
                yield pa.RecordBatch.from_arrays([pa.array(y) for y in (ids[i[top]], others[j[top]], cosine[top])], ["vec_id", "other", "cosine"])

    return work


def embedding_knn(spark: SparkSession, sf_dir: str, k: int = 8, block: int = 1024) -> DataFrame:
    """The k nearest vectors by cosine, ties to the smaller id; blocks of vectors meet two by two.

    Vectors without a direction (null, zero, holding null or a non-finite component) take no part.
    """
    finite = lambda x: x.isNotNull() & (F.abs(x) < float("inf"))  # noqa: E731  (a NaN counts as greater)
    unit = F.transform("embedding", lambda x: x.cast("double"))
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", unit.alias("v")).where(F.forall("v", finite) & F.exists("v", lambda x: x != 0))
    n = vectors.count()
    blocks = cut(vectors.groupBy(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, -(-n // block)))).alias("block")).agg(F.collect_list(F.struct("vec_id", "v")).alias("x")).select(F.col("x.vec_id").alias("ids"), F.flatten("x.v").alias("v")))
    other = blocks.select(F.col("ids").alias("other_ids"), F.col("v").alias("u"))
    met = blocks.repartition(max(1, min(n // block, 200))).crossJoin(F.broadcast(other) if n <= _BROADCAST else other)
    near = met.mapInArrow(_nearest(k), "vec_id long, other long, cosine double")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("cosine"), "other"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select(F.col("vec_id").alias("src"), F.col("other").alias("dst"), (F.col("rank") + 1).cast("long").alias("w"))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (part_next, supplier_part, order_part, event_hub, event_lattice, part_grid, fk_entities, token_bigram, embedding_knn, page_paths, turn_chain)
}
