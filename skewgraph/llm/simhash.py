"""SimHash near-duplicates over word shingles (operator 5)."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import Shared, beside, fresh, slices, words_of
from .components import components
from .hamming import dealt, linker, links, roots, segments, spread

SEED = 42


#: For each byte its eight bits, the highest first, in eight byte-wide lanes.
_LANES = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).view(np.uint64).ravel()


def majority(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """SimHash of consecutive groups of 64-bit hashes: the bits set in over half of each group's; empty groups: zero."""
    out = np.zeros(len(sizes), np.uint64)
    at = np.flatnonzero(sizes)
    if not len(at):
        return out
    sizes = sizes[at]
    pieces = -(-sizes // 255)  # a lane counts to 255
    first = np.concatenate([[0], np.cumsum(pieces)[:-1]])
    nth = np.arange(pieces.sum()) - np.repeat(first, pieces)
    starts = np.repeat(np.concatenate([[0], np.cumsum(sizes)[:-1]]), pieces) + nth * 255
    lanes = _LANES[hashes.astype(">u8").view(np.uint8).reshape(-1, 8)]
    counts = np.add.reduceat(lanes, starts, axis=0).view(np.uint8).reshape(-1, 64).astype(np.int64)
    if len(counts) > len(sizes):
        counts = np.add.reduceat(counts, first, axis=0)
    out[at] = np.packbits(2 * counts > sizes[:, None], axis=1).view(">u8").ravel()
    return out


def bands(hashes: np.ndarray, sizes: np.ndarray, count: int, rows: int) -> np.ndarray:
    """``count`` 32-bit digests, each of ``rows`` MinHashes, of consecutive non-empty groups of 64-bit hashes."""
    out = np.zeros((len(sizes), count), np.uint64)
    if not len(sizes):
        return out.astype(np.int32)
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    multipliers = np.random.default_rng(42).integers(1 << 63, size=count * rows, dtype=np.uint64) | np.uint64(1)
    with np.errstate(over="ignore"):
        mixed = hashes ^ (hashes >> np.uint64(29))
        for i, by in enumerate(multipliers):
            least = np.minimum.reduceat(mixed * by, starts)
            least ^= least >> np.uint64(31)
            out[:, i % count] = (out[:, i % count] ^ least) * np.uint64(0x9E3779B97F4A7C15)
    return (out >> np.uint64(32)).astype(np.uint32).view(np.int32)


def shingle_hashes(words: list[bytes], width: int) -> list[int]:
    """XXH64 of the words' shingles, repeats included; a text of fewer than ``width`` words is one shingle."""
    n = len(words)
    if not n:
        return []
    text = b" ".join(words)
    if n <= width:
        return [xxh64_intdigest(text, SEED)]
    ends = list(accumulate(map(len, words), lambda a, x: a + x + 1))
    return [xxh64_intdigest(text[a:b], SEED) for a, b in zip(chain((0,), (e + 1 for e in ends)), ends[width - 1 :], strict=False)]


def fingerprints(docs: DataFrame, width: int) -> DataFrame:
    """``doc_id``, ``fp`` (the 64 bits as a long) of every whole text; null and empty texts: zero."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text"):
            parts = [np.array(shingle_hashes(words_of(t, lower=True), width), np.uint64) for t in texts]
            found = majority(np.concatenate(parts), np.array([len(x) for x in parts], np.int64))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(work, "doc_id long, fp long")


def near_duplicates(docs: DataFrame, width: int = 5, k: int = 3) -> DataFrame:
    """``doc_id``, ``fp``, ``component_id`` of every row: the least ``doc_id`` that links of at most ``k`` bits reach.

    Equal fingerprints collapse to one before any search, so groups of copies cost one row.  Rows
    without a ``doc_id`` keep a null id, stand under the least ``doc_id`` of their fingerprint and found no group.
    """
    own = Shared(fingerprints(docs, width), "fingerprints")
    distinct = Shared(own.frame.groupBy("fp").agg(F.min("doc_id").alias("id")), "distinct-fingerprints")
    found = components(links(distinct.frame.where("id is not null"), k), "near-duplicates")
    classes = distinct.frame.join(found.frame, "id", "left").select("fp", F.coalesce("root", "id").alias("component_id"))
    return own.frame.join(classes, "fp").select("doc_id", "fp", "component_id")


#: Rows of one group of near texts that a task compares at once.
VERIFY_GROUP = 1024
#: SimHash bits in which candidates may differ.
NEAR_BITS = 7
#: MinHash bands of a text, and values of a band: texts with a Jaccard similarity of 0.8 share one with a chance of 99.96 %.
BANDS, ROWS = 20, 5


def shingle_bands(docs: DataFrame, width: int) -> DataFrame:
    """``doc_id``, ``fp``, ``bands``, ``h``, ``size`` of every text that has words and a ``doc_id``: SimHash and MinHash bands of its shingles, the digest of its words, its distinct shingles."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text"):
            words = [words_of(t, lower=True) for t in texts]
            batch = batch.filter(pa.array([bool(x) for x in words], pa.bool_()))
            words = [x for x in words if x]
            if not words:
                continue
            hashes = [np.array(shingle_hashes(x, width), np.uint64) for x in words]
            fps = majority(np.concatenate(hashes), np.array([len(x) for x in hashes], np.int64))
            sets = [np.unique(x) for x in hashes]
            sizes = np.array([len(x) for x in sets], np.int64)
            found = bands(np.concatenate(sets), sizes, BANDS, ROWS)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, found.size + 1, BANDS, dtype=np.int32)), pa.array(found.ravel()))
            digest = np.array([xxh64_intdigest(b" ".join(x), SEED) for x in words], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fps.view(np.int64)), lists, pa.array(digest.view(np.int64)), pa.array(sizes)], ["doc_id", "fp", "bands", "h", "size"])

    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long"), "text").mapInArrow(work, "doc_id long, fp long, bands array<int>, h long, size long")


def _shingle_sets(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """``sig``, ``id``, ``shingles`` (sorted distinct hashes) of the texts of ``wanted`` (``sig``, ``id``, ``h``)."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text"):
            words = [words_of(t, lower=True) for t in texts]
            own = np.array([xxh64_intdigest(b" ".join(x), SEED) for x in words], np.uint64).view(np.int64)
            keep = pa.array(own == batch.column("h").to_numpy())  # another row may repeat the doc_id
            sets = pa.array([np.unique(np.array(shingle_hashes(x, width), np.uint64)).tobytes() for x in words], pa.binary())
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("sig", "id")), sets], ["sig", "id", "shingles"]).filter(keep)

    held = docs.select(F.col("doc_id").cast("long"), "text").join(wanted, F.col("doc_id") == F.col("id")).select("sig", "id", "h", "text")
    return held.mapInArrow(work, "sig long, id long, shingles binary")


def _common(sets: list[np.ndarray], similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs whose sets have a Jaccard similarity of ``similarity`` or more."""
    x, y = np.triu_indices(len(sets), 1)
    sizes = np.array([len(s) for s in sets])
    fit = np.minimum(sizes[x], sizes[y]) >= similarity * np.maximum(sizes[x], sizes[y]) - 1e-9
    x, y = x[fit], y[fit]
    if len(x) <= 8 * len(sets):
        both = np.array([len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for i, j in zip(x.tolist(), y.tolist(), strict=True)], np.int64)
    else:
        _, column, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        row = np.repeat(np.arange(len(sets)), sizes)
        shared = times[column] > 1
        row, column = row[shared], np.unique(column[shared], return_inverse=True)[1]
        order = np.argsort(column, kind="stable")
        row, column = row[order], column[order]
        counts = np.zeros((len(sets), len(sets)), np.float32)
        for start in range(0, int(column[-1]) + 1 if len(column) else 0, 2048):
            a, b = np.searchsorted(column, [start, start + 2048])
            held = np.zeros((len(sets), 2048), np.float32)
            held[row[a:b], column[a:b] - start] = 1
            counts += held @ held.T
        both = counts[x, y].astype(np.int64)
    good = both >= similarity * (sizes[x] + sizes[y] - both) - 1e-9
    return x[good], y[good]


def _verifier(similarity: float):
    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in segments(batches):
            part = part.sort_by([("sig", "ascending"), ("id", "ascending")])
            sig, ids, raw = part["sig"].to_numpy(), part["id"].to_numpy(), part["shingles"].to_pylist()
            cuts = [*np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]])).tolist(), len(sig)]
            left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for start, end in zip(cuts[:-1], cuts[1:], strict=True):
                pairs = _common([np.frombuffer(x, np.uint64) for x in raw[start:end]], similarity)
                root = roots(end - start, *pairs)
                at = np.flatnonzero(root != np.arange(end - start))
                left.append(ids[start + at])
                right.append(ids[start + root[at]])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(left)), pa.array(np.concatenate(right))], ["a", "b"])

    return work


def similar_groups(docs: DataFrame, width: int = 5, similarity: float = 0.8) -> Shared:
    """A written table ``doc_id``, ``component_id`` of every row with words: the least ``doc_id`` that similar texts reach.

    Two texts are similar if the Jaccard similarity of their distinct ``width``-word shingles reaches
    ``similarity``; those with SimHashes within ``NEAR_BITS`` are candidates, and, since such a similarity leaves some
    pairs further apart, those that share a MinHash band; whole groups of them are compared exactly.  Texts of the
    same words collapse first; only texts with a candidate bring their shingles, once each.
    """
    own = Shared(shingle_bands(docs, width), "shingle-bands")
    distinct = Shared(own.frame.groupBy("h").agg(F.min("doc_id").alias("id"), F.first("fp").alias("fp"), F.first("bands").alias("bands"), F.first("size").alias("size")), "distinct-texts")
    rows = distinct.frame.select("id", "size", F.posexplode("bands").alias("at", "band"))
    rows = rows.select(F.xxhash64("at", "band").alias("sig"), F.lit(0).cast("long").alias("fp"), "id", "size")
    linked = dealt(spread(rows)).select("sig", "fp", "id", "size").mapInArrow(linker(0, similarity - 1e-9), "a long, b long")
    near = components(links(distinct.frame, NEAR_BITS, ratio=similarity - 1e-9).unionByName(linked), "near-groups")
    members = near.frame.select("id", F.col("root").alias("sig")).unionByName(near.frame.select(F.col("root").alias("id"), F.col("root").alias("sig")).distinct())
    wanted = Shared(distinct.frame.select("id", "h").join(members, "id"), "near-texts")
    sets = Shared(_shingle_sets(docs, beside(wanted.frame), width), "shingle-sets")
    found = dealt(spread(sets.frame, VERIFY_GROUP)).select("sig", "id", "shingles").mapInArrow(_verifier(similarity), "a long, b long")
    groups = components(found, "similar-groups")
    classes = distinct.frame.join(groups.frame, "id", "left").select("h", F.coalesce("root", "id").alias("component_id"))
    result = Shared(own.frame.join(classes, "h").select("doc_id", "component_id"), "similar")
    for table in (own, distinct, near, wanted, sets, groups):
        table.drop()
    return result


def keep_one(docs: DataFrame, width: int = 5, similarity: float = 0.8) -> DataFrame:
    """The documents that are the least of their group of similar texts; all columns.

    Texts without words are no copies of one another; of rows that repeat a ``doc_id`` with the same text one
    stays; rows without a ``doc_id`` stay; further columns stay, whatever their names; an empty table gives an empty result.
    """
    found = similar_groups(docs, width, similarity)
    name = fresh("_gone", docs.columns)
    gone = beside(Shared(found.frame.where("doc_id <> component_id").select(F.col("doc_id").alias(name)).distinct(), "gone").frame)
    kept = docs.join(gone, docs["doc_id"] == gone[name], "left_anti")
    if found.frame.groupBy("doc_id").count().where("count > 1").isEmpty():
        return kept
    return kept.where("doc_id is null").unionByName(kept.where("doc_id is not null").dropDuplicates(["doc_id", "text"]))
