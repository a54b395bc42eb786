"""Exact top-k inner products by a three-phase uniform threshold (operator 4).

A vector's dimensions are cut into ``lists``; a score is the sum of one partial score from each list.

1. Every block of candidates looks up, for each query and list, its ``k`` best entries and gives the ``k`` best of
   their whole scores.  These give a cutoff: the ``k``-th best of them all is at most the true ``k``-th best.
2. A candidate that reaches the cutoff must reach ``cutoff / lists`` in some list (else the sum would be
   less), whatever the signs.  With the cutoff beside its query, each block collects the entries that do.
3. Only these are resolved to whole scores; those at the cutoff or above go to the final ranking.

Queries and candidates meet block by block, so memory is that of two blocks whatever their numbers.  Query blocks
are broadcast where their bytes are few, else candidate blocks are dealt over lanes and every lane gets the query
blocks.  Components become ``floor(1024 * x)``; sums are taken in doubles while they are exact and in integers
of any size beyond; a score beyond 64 bits is an error.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Shared

BLOCK = 2048
QUERY_BLOCK = 512
LISTS = 4
SCALE = 1024
#: Bytes of query blocks that may be broadcast; lanes of candidate blocks beyond.
BESIDE_BYTES, LANES = 64 << 20, 64
#: A cutoff that every score reaches, where a query has fewer than ``k`` candidates.
NONE = -(1 << 63)
_EXACT = float(1 << 53)


def _vectors(column: pa.Array) -> tuple[np.ndarray, np.ndarray, int]:
    """Rows that hold finite vectors of the usual length, and their scaled components."""
    rows = [(i, x) for i, x in enumerate(column.to_pylist()) if x and None not in x]
    width = max((len(x) for _, x in rows), default=0)
    data = np.array([x for _, x in rows if len(x) == width], np.float64).reshape(-1, width)
    at = np.array([i for i, x in rows if len(x) == width], np.int64)
    good = np.isfinite(data).all(axis=1)
    return at[good], np.floor(SCALE * data[good]), width


def blocks(vectors: DataFrame, size: int) -> DataFrame:
    """``ids``, ``data`` (binary), ``width``: the valid rows packed, at most ``size`` of one width a row."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[int, np.ndarray]]] = {}

        def row(part: list[tuple[int, np.ndarray]]) -> pa.RecordBatch:
            data = np.stack([x for _, x in part])
            return pa.RecordBatch.from_arrays([pa.array([np.array([i for i, _ in part], np.int64).tobytes()]), pa.array([data.tobytes()]), pa.array([data.shape[1]], pa.int32())], ["ids", "data", "width"])

        for batch in batches:
            ids = batch.column("vec_id").to_numpy(zero_copy_only=False)
            for start in range(0, len(batch), size):
                part = batch.slice(start, size).column("embedding")
                lengths = np.array([len(x) if x is not None else 0 for x in part.to_pylist()])
                for width in np.unique(lengths[lengths > 0]):
                    at = np.flatnonzero(lengths == width)
                    own, data, _ = _vectors(part.take(pa.array(at)))
                    held.setdefault(int(width), []).extend(zip(ids[start + at[own]].tolist(), data, strict=True))
                    while len(held[int(width)]) >= size:
                        yield row(held[int(width)][:size])
                        del held[int(width)][:size]
        for part in held.values():
            if part:
                yield row(part)

    return vectors.where("vec_id is not null").select(F.col("vec_id").cast("long"), "embedding").mapInArrow(work, "ids binary, data binary, width int")


def _open(ids: bytes, data: bytes, width: int) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, np.int64), np.frombuffer(data, np.float64).reshape(-1, width)


def _partial(q: np.ndarray, c: np.ndarray, lists: int) -> list[np.ndarray]:
    """Partial scores of each list, exact: doubles where every sum fits them, Python integers otherwise."""
    bound = float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) * q.shape[1]
    if bound >= _EXACT:
        q, c = (np.array([[int(v) for v in row] for row in x.tolist()], object).reshape(x.shape) for x in (q, c))
    cuts = np.array_split(np.arange(q.shape[1]), min(lists, q.shape[1]))
    return [q[:, at] @ c[:, at].T for at in cuts]


SCORES = "query_id long, vec_id long, score long"


def _rows(q_ids: np.ndarray, c_ids: np.ndarray, i: np.ndarray, j: np.ndarray, score: np.ndarray) -> pa.RecordBatch:
    if score.dtype == object and any(not NONE < x < 1 << 63 for x in score.tolist()):
        raise OverflowError("a score doesn't fit 64 bits")
    values = score.astype(np.int64)
    return pa.RecordBatch.from_arrays([pa.array(q_ids[i]), pa.array(c_ids[j]), pa.array(values)], ["query_id", "vec_id", "score"])


def _local_lists(k: int, lists: int):
    """Phase 1: whole scores of each block's best entries, list by list."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                q_ids, q = _open(x["q_ids"], x["q_data"], x["width"])
                c_ids, c = _open(x["ids"], x["data"], x["width"])
                partial = _partial(q, c, lists)
                whole, picked = sum(partial[1:], partial[0]), np.zeros((len(q), len(c)), bool)
                most = min(k + 1, len(c))  # the query itself may be among them
                for part in partial:
                    best = np.argsort(-part, axis=1, kind="stable")[:, :most] if part.dtype == object else np.argpartition(-part, most - 1, axis=1)[:, :most]
                    np.put_along_axis(picked, best, True, axis=1)
                i, j = np.nonzero(picked & (q_ids[:, None] != c_ids[None, :]))
                score = whole[i, j]
                order = sorted(range(len(i)), key=lambda x: (i[x], -score[x])) if score.dtype == object else np.lexsort((-score, i))
                i, j, score = i[order], j[order], score[order]
                best = np.arange(len(i)) - np.searchsorted(i, i) < k
                yield _rows(q_ids, c_ids, i[best], j[best], score[best])

    return work


def _resolve(lists: int):
    """Phases 2 and 3: entries that reach the uniform threshold in some list, then their whole scores."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                q_ids, q = _open(x["q_ids"], x["q_data"], x["width"])
                cutoff = np.frombuffer(x["cutoffs"], np.int64)
                c_ids, c = _open(x["ids"], x["data"], x["width"])
                partial = _partial(q, c, lists)
                reach = np.repeat((cutoff == NONE)[:, None], len(c), axis=1)
                own = cutoff.astype(object) if partial[0].dtype == object else cutoff.astype(float)
                for part in partial:
                    reach |= (part * len(partial) >= own[:, None]).astype(bool)
                i, j = np.nonzero(reach & (q_ids[:, None] != c_ids[None, :]))
                score = sum(part[i, j] for part in partial)
                keep = (score >= own[i]).astype(bool)
                yield _rows(q_ids, c_ids, i[keep], j[keep], score[keep])

    return work


def _best(scores: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scores.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _meeting(asked: DataFrame, queries: DataFrame, candidates: DataFrame) -> DataFrame:
    """Every query block beside every candidate block of its width; ``asked``: the written query blocks, by which their bytes are known."""
    meet = F.col("q_width") == F.col("width")
    if (asked.agg(F.sum(F.octet_length("q_data"))).first()[0] or 0) <= BESIDE_BYTES:
        return candidates.repartition(F.xxhash64("ids")).join(F.broadcast(queries), meet)
    lanes = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(LANES - 1).cast("long")))
    dealt = candidates.withColumn("lane", F.pmod(F.xxhash64("ids"), F.lit(LANES)))
    return dealt.join(queries.withColumn("q_lane", lanes), meet & (F.col("q_lane") == F.col("lane")))


def top_k(vectors: DataFrame, is_query: str, k: int = 10, lists: int = LISTS) -> DataFrame:
    """``query_id``, ``rank``, ``vec_id``, ``score``: each query's ``k`` best scores, ties to the smaller ``vec_id``.

    ``vectors``: ``vec_id``, ``embedding``; ``is_query``: SQL predicate of the queries.  Rows whose vector is
    null, empty or holds a null or non-finite component, or without an id, take no part; vectors of
    different widths never meet; rows that repeat an id count each, but a query never meets its own id; further
    columns are left out, whatever their names; an empty table gives an empty result.
    """
    candidates = Shared(blocks(vectors, BLOCK), "candidate-blocks")
    asked = Shared(blocks(vectors.where(is_query), QUERY_BLOCK).withColumnsRenamed({"ids": "q_ids", "data": "q_data", "width": "q_width"}), "query-blocks")
    columns = ["q_ids", "q_data", "ids", "data", "width"]
    local = _meeting(asked.frame, asked.frame, candidates.frame).select(*columns).mapInArrow(_local_lists(k, lists), SCORES)
    # the best of each task's lists, then the k-th best: a row for each query
    cutoffs = Shared(_best(local.distinct(), k).groupBy("query_id").agg(F.min("score").alias("least"), F.count("*").alias("n")).select("query_id", F.when(F.col("n") >= k, F.col("least")).otherwise(F.lit(NONE)).alias("cutoff")), "cutoffs")

    def ids_of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                ids = np.frombuffer(x["q_ids"], np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([x["q_ids"]] * len(ids), pa.binary()), pa.array(np.arange(len(ids))), pa.array(ids)], ["q_ids", "at", "query_id"])

    per_query = asked.frame.select("q_ids").mapInArrow(ids_of, "q_ids binary, at long, query_id long").join(cutoffs.frame, "query_id", "left").fillna(NONE, ["cutoff"])

    def pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.to_pylist():
                data = np.array([c["cutoff"] for c in sorted(x["own"], key=lambda c: c["at"])], np.int64).tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([x["q_ids"]], pa.binary()), pa.array([data], pa.binary())], ["q_ids", "cutoffs"])

    packed = per_query.groupBy("q_ids").agg(F.collect_list(F.struct("at", "cutoff")).alias("own")).mapInArrow(pack, "q_ids binary, cutoffs binary")
    with_cutoffs = asked.frame.join(packed, "q_ids")
    entries = _meeting(asked.frame, with_cutoffs, candidates.frame).select(*columns, "cutoffs").mapInArrow(_resolve(lists), SCORES)
    return _best(entries, k).select("query_id", "rank", "vec_id", "score")
