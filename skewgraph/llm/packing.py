"""Packing documents into fixed sequences by cutting-stock column generation (operator 9).

Every document gives full sequences and one rest.  The rests' lengths form a histogram over a fixed set
of size classes; a pattern says how many rests of each class share a sequence.  A linear program over
patterns covers the histogram with the fewest sequences; its dual prices value the classes, and a
knapsack dynamic program over the sequence finds the pattern worth most, which joins the program until
none is worth more than a sequence.  Rounded down, the patterns take the documents by rank within their
class; what remains is packed by first fit decreasing over the same classes.

Driver and model hold the histogram and the patterns only, whose sizes are fixed by the classes.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import Vocabulary
from .common import Shared, slices

SEQUENCE = 2048
END = 1
MAX_COLUMNS = 3000
#: Patterns join while one is worth so much more than a sequence.
GAP = 1e-3
#: Pricings at most; what the program has not improved by then only costs padding.
ROUNDS = 200


def class_sizes(most: int = SEQUENCE) -> np.ndarray:
    """Sizes that rests are rounded up to: exact up to 16, then steps of at most an eighth, 8 at most; ``most`` itself last."""
    out = list(range(1, min(16, most) + 1))
    while out[-1] < most:
        step = max(1, min(8, 1 << max(0, (out[-1]).bit_length() - 4)))
        out.append(min(most, out[-1] + step))
    return np.array(out, np.int64)


@dataclass(frozen=True)
class Cut:
    """One kind of sequence: how many rests of each class, and how many such sequences."""

    counts: tuple[int, ...]
    times: int


def best_patterns(values: np.ndarray, sizes: np.ndarray, most: int, worth_more: float) -> tuple[float, list[np.ndarray]]:
    """Unbounded knapsack: the highest value within ``most``, and for each class the best pattern that holds it.

    Only patterns of a value over ``worth_more``, the best first.
    """
    worth, took = np.zeros(most + 1), np.full(most + 1, -1)
    for room in range(1, most + 1):
        worth[room] = worth[room - 1]
        if fits := int(np.searchsorted(sizes, room, "right")):
            got = worth[room - sizes[:fits]] + values[:fits]
            i = int(got.argmax())
            if got[i] > worth[room] + 1e-12:
                worth[room], took[room] = got[i], i
    with_class = values + worth[most - sizes]
    out = []
    for i in np.argsort(-with_class, kind="stable"):
        if with_class[i] <= worth_more:
            break
        counts, room = np.zeros(len(sizes), np.int64), int(most - sizes[i])
        counts[i] = 1
        while room > 0:
            if took[room] < 0:
                room -= 1
            else:
                counts[took[room]] += 1
                room -= int(sizes[took[room]])
        out.append(counts)
    return float(worth[most]), out


def first_fit(left: np.ndarray, sizes: np.ndarray, most: int) -> np.ndarray:
    """The pattern that first fit decreasing fills from what is left."""
    pattern, room = np.zeros(len(sizes), np.int64), most
    for i in np.flatnonzero(left >= 1)[::-1]:
        pattern[i] = min(int(left[i]), room // int(sizes[i]))
        room -= int(pattern[i] * sizes[i])
    return pattern


def _first_basis(need: np.ndarray, sizes: np.ndarray, most: int) -> np.ndarray:
    """First fit decreasing as a basis: each pattern uses up one class, a pattern of that class alone where several end at once."""
    n, left = len(need), need.astype(float).copy()
    basis = np.diag((most // sizes).astype(float))
    while (left >= 1).any():
        pattern = first_fit(left, sizes, most)
        used = np.flatnonzero(pattern)
        ends = used[int((left[used] / pattern[used]).argmin())]
        left -= pattern * (left[ends] / pattern[ends])
        left[ends] = 0
        basis[:, ends] = pattern
    assert basis.shape == (n, n)
    return basis


def _inverse(matrix: np.ndarray) -> np.ndarray:
    """Gauss-Jordan with row pivots.  The driver stays clear of threaded LAPACK, whose pool can hang beside a JVM."""
    n = len(matrix)
    work = np.concatenate([matrix, np.eye(n)], axis=1)
    for i in range(n):
        best = i + int(np.abs(work[i:, i]).argmax())
        if best != i:
            work[[i, best]] = work[[best, i]]
        work[i] /= work[i, i] or np.nan
        factor = work[:, i].copy()
        factor[i] = 0
        use = np.flatnonzero(factor)
        work[use] -= factor[use, None] * work[i]
    return work[:, n:]


def _apply(matrix: np.ndarray, vector: np.ndarray) -> np.ndarray:
    return (matrix * vector).sum(axis=1)


def solve(demand: np.ndarray, sizes: np.ndarray, most: int = SEQUENCE, columns: int = MAX_COLUMNS) -> tuple[list[Cut], float]:
    """Patterns that cover the demand exactly, and the linear program's lower bound on sequences."""
    demand = demand.astype(np.int64)
    at = np.flatnonzero(demand)
    if not len(at):
        return [], 0.0
    size, need = sizes[at], demand[at].astype(float)
    n = len(at)
    basis = _first_basis(need, size, most)  # a pattern a column
    inverse = _inverse(basis)
    joined = 0
    for _ in range(ROUNDS):
        best, patterns = best_patterns(np.maximum(inverse.sum(axis=0), 0), size, most, 1 + 1e-9)
        sequences = float(_apply(inverse, need).sum())
        if joined >= columns or best <= 1 + GAP or sequences - sequences / best < 1:  # no cover needs fewer than sequences / best
            break
        before, sound = joined, (basis.copy(), inverse)
        for column in patterns:
            if (inverse.sum(axis=0) * column).sum() <= 1 + 1e-9:  # prices have changed
                continue
            use, have = _apply(inverse, column), _apply(inverse, need)
            if not (use > 1e-7).any():
                continue
            ratio = np.where(use > 1e-7, np.maximum(have, 0) / np.where(use > 1e-7, use, 1), np.inf)
            out = int(ratio.argmin())
            basis[:, out] = column
            pivot = inverse[out] / use[out]
            inverse = inverse - np.outer(use, pivot)
            inverse[out] = pivot
            joined += 1
        inverse = _inverse(basis)
        if not np.isfinite(inverse).all() or np.abs(_apply(basis, _apply(inverse, need)) - need).max() > 1e-6 * need.max():
            basis, inverse = sound  # a pivot too small: what was found before stands
            break
        if joined == before:  # only prices below zero stood in the way
            break
    amounts = np.maximum(_apply(inverse, need), 0)
    left, cuts = demand[at].copy(), []
    for j in np.argsort(-amounts, kind="stable"):
        pattern = basis[:, j].round().astype(np.int64)
        times = int(min(np.floor(amounts[j] + 1e-9), *(left[pattern > 0] // pattern[pattern > 0]))) if pattern.any() else 0
        if times > 0:
            cuts.append((pattern, times))
            left -= pattern * times
    while left.any():  # first fit decreasing, sequences of one kind at a time
        pattern = first_fit(left, size, most)
        times = int(min(left[pattern > 0] // pattern[pattern > 0]))
        cuts.append((pattern, times))
        left -= pattern * times
    wide = []
    for pattern, times in cuts:
        full = np.zeros(len(sizes), np.int64)
        full[at] = pattern
        wide.append(Cut(tuple(full.tolist()), times))
    return wide, float(amounts.sum())


_ENCODERS: dict[str, tiktoken.Encoding] = {}


def encoder(path: str, pattern: str) -> tiktoken.Encoding:
    """Encoder over a rank file; the same ids as the tokenizer file that the ranks were taken from."""
    if path not in _ENCODERS:
        _ENCODERS[path] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=Vocabulary.load_ranks(path), special_tokens={})
    return _ENCODERS[path]


PIECES = "block long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, class int, nth long"


def pieces(docs: DataFrame, path: str, pattern: str, most: int = SEQUENCE, end: int = END) -> DataFrame:
    """Full pieces and the rest of every document, each with its class and its number in the block's class.

    A block is one partition of this job's output; its number is the task's, so a task run anew gives the
    same rows.  Null and empty texts are one end token.
    """
    sizes = class_sizes(most)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        own, block, seen = encoder(path, pattern), TaskContext.get().partitionId(), np.zeros(len(sizes), np.int64)
        for batch, texts in slices(batches, "text"):
            rows: list[tuple] = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), texts, strict=True):
                ids = np.array([*own.encode_ordinary(text.decode()), end], "<u4")
                for start in range(0, len(ids), most):
                    part = ids[start : start + most]
                    kind = int(np.searchsorted(sizes, len(part)))
                    rows.append((block, doc, start, len(part), zlib.crc32(part.tobytes()), len(ids), kind, int(seen[kind])))
                    seen[kind] += 1
            names = [x.split()[0] for x in PIECES.split(", ")]
            cols = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if k == "class" else pa.int64()) for k, c in zip(names, cols, strict=True)], names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(work, PIECES)


@dataclass(frozen=True)
class Layout:
    """Where the rests of each class go, in order of rank: ``cuts`` whose sequences are numbered one after another."""

    cuts: tuple[Cut, ...]

    def slots(self) -> list[tuple[int, int, int, int, int, int]]:
        """(class, first rank, ranks, sequence of the first, ranks a sequence, slots before it in the sequence)."""
        out, ranks, sequence = [], {}, 0
        for cut in self.cuts:
            before = 0
            for kind in range(len(cut.counts) - 1, -1, -1):
                if n := cut.counts[kind]:
                    first = ranks.get(kind, 0)
                    out.append((kind, first, n * cut.times, sequence, n, before))
                    ranks[kind] = first + n * cut.times
                    before += n
            sequence += cut.times
        return out


def pack(docs: DataFrame, path: str, pattern: str, most: int = SEQUENCE, end: int = END) -> DataFrame:
    """``doc_id``, ``start``, ``length``, ``ids_crc32``, ``doc_tokens``, ``sequence_id``, ``offset`` of every piece.

    Each id of each document (its text's, then ``end``) lies in one piece; a sequence's pieces stand gapless
    from 0.  Documents that fit are never cut; longer ones are cut at multiples of ``most``.  Repeated rows
    are packed one by one, rows with a null ``doc_id`` too; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    table = Shared(pieces(docs, path, pattern, most, end), "pieces")
    sizes = class_sizes(most)
    counts = Shared(table.frame.groupBy("block", "class").agg(F.count("*").alias("n")), "piece-counts")
    histogram = np.zeros(len(sizes), np.int64)
    for row in counts.frame.groupBy("class").agg(F.sum("n").alias("n")).collect():  # a row for each class
        histogram[row["class"]] = row["n"]
    cuts, _ = solve(histogram, sizes, most)
    slots = Layout(tuple(cuts)).slots()
    # a class's slots as one sorted array, found by binary search in each task
    by_class = {k: np.array([s[1:] for s in slots if s[0] == k], np.int64) for k in {s[0] for s in slots}}
    before = Window.partitionBy("class").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    ranked = counts.frame.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0))).select("block", "class", "first")

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kind = batch.column("class").to_numpy()
            rank = batch.column("nth").to_numpy() + batch.column("first").to_numpy()
            sequence, slot = np.zeros(len(kind), np.int64), np.zeros(len(kind), np.int64)
            for k in np.unique(kind):
                at = np.flatnonzero(kind == k)
                own = by_class[int(k)]
                row = own[np.searchsorted(own[:, 0], rank[at], "right") - 1]
                nth = rank[at] - row[:, 0]
                sequence[at], slot[at] = row[:, 2] + nth // row[:, 3], row[:, 4] + nth % row[:, 3]
            kept = [batch.column(c) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sequence), pa.array(slot)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "slot"])

    placed = table.frame.join(ranked, ["block", "class"]).mapInArrow(place, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, slot long")
    inside = Window.partitionBy("sequence_id").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    return placed.withColumn("offset", F.coalesce(F.sum("length").over(inside), F.lit(0))).drop("slot")
