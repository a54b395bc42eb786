"""Links between 64-bit fingerprints at a small Hamming distance, by the generalised pigeonhole.

The 64 bits are cut into partitions, correlated bits together.  Partition ``i`` gets a threshold
``t_i >= -1`` with ``sum(t_i + 1) = k + 1``: two fingerprints within ``k`` bits must be within ``t_i`` in
some partition, so probing each partition to its own threshold (-1: not at all) misses no pair.  Which
thresholds are cheapest follows from statistics of all fingerprints by dynamic programming.

A signature names a partition and a value of its bits; rows that share one are compared.  Each
signature's rows give a spanning forest of their links, never all pairs.  A signature with more than
``GROUP`` rows is cut into chunks that meet two by two, so no task holds more than two chunks of it.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Shared, beside

#: Rows of one signature that a task compares at once; larger groups meet chunk by chunk.
GROUP = 4096
#: Work of dealing out one signature row, in comparisons of two fingerprints.
ROW_COST = 500.0
#: Cells in which signatures are counted together before any is counted alone.
CELLS = 1 << 18
#: Segments up to this many rows are compared by shifting whole batches.
_SHORT = 128
_PARTS = (2, 3, 4)


@dataclass(frozen=True)
class Plan:
    """Bits of each partition (0 is the highest) and its threshold."""

    bits: tuple[tuple[int, ...], ...]
    thresholds: tuple[int, ...]

    def masks(self) -> list[int]:
        return [sum(1 << (63 - b) for b in part) for part in self.bits]


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def bit_statistics(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Rows, and how often each pair of bits is set together, over every fingerprint (64 x 64 numbers)."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((64, 64)), 0
        for batch in batches:
            bits = unpack(batch.column("fp").to_numpy(zero_copy_only=False)).astype(np.float32)
            for at in range(0, len(bits), 1 << 16):
                part = bits[at : at + (1 << 16)]
                total += part.T @ part
            n += len(bits)
        yield pa.RecordBatch.from_arrays([pa.array([*range(4096), 4096], pa.int32()), pa.array([*total.ravel().astype(np.int64), n], pa.int64())], ["cell", "n"])

    rows = fps.select("fp").mapInArrow(work, "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    flat = np.zeros(4097)
    flat[rows["cell"].to_numpy()] = rows["n"].to_numpy()
    return int(flat[-1]), flat[:-1].reshape(64, 64)


def unpack(fps: np.ndarray) -> np.ndarray:
    """64 columns of bits, the highest first."""
    return np.unpackbits(fps.astype(np.int64).astype(">i8").view(np.uint8).reshape(-1, 8), axis=1)


def _grouped(together: np.ndarray, n: int, parts: int) -> tuple[tuple[int, ...], ...]:
    """Equal partitions, each grown from a seed by the bits that correlate most with it."""
    p = np.diag(together) / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-9))
    corr = np.abs((together / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
    free, out = set(range(64)), []
    for i in range(parts):
        size = (64 - 64 * i // parts) - (64 - 64 * (i + 1) // parts)
        group = [max(free, key=lambda b: (sum(corr[b, c] for c in free), -b))]
        free.discard(group[0])
        while len(group) < size:
            group.append(max(free, key=lambda b: (sum(corr[b, c] for c in group), -b)))  # noqa: B023
            free.discard(group[-1])
        out.append(tuple(sorted(group)))
    return tuple(out)


def _near_share(p: np.ndarray, corr: float, most: int) -> np.ndarray:
    """Estimated share of pairs within 0..``most`` bits on a partition; correlation narrows its width."""
    agree = p * p + (1 - p) * (1 - p)
    agree = agree ** (1 / (1 + corr))
    at = np.zeros(most + 1)
    at[0] = 1
    for q in agree:
        at[1:] = at[1:] * q + at[:-1] * (1 - q)
        at[0] *= q
    return np.cumsum(at)


def allocate(n: int, together: np.ndarray, k: int, parts: Iterable[int] = _PARTS) -> Plan:
    """The partitions and thresholds with the least estimated work.

    Work of a partition with threshold ``t``: a row for each signature probed, and the pairs that
    share one.  The dynamic program spends ``k + 1`` units over the partitions, ``t + 1`` on each.
    """
    best: tuple[float, Plan] | None = None
    p = np.diag(together) / max(n, 1)
    for m in parts:
        groups = _grouped(together, n, m)
        spread = np.sqrt(np.maximum(p * (1 - p), 1e-9))
        corr = np.abs((together / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
        costs = []
        for g in groups:
            inner = corr[np.ix_(g, g)]
            near = _near_share(p[list(g)], float((inner.sum() - len(g)) / max(1, len(g) * (len(g) - 1))) * len(g), k)
            row = [0.0]
            for t in range(k + 1):
                probes = sum(_choose(len(g), d) for d in range(t + 1))
                row.append(ROW_COST * max(n, 1) * probes + near[t] * n * n / 2)
            costs.append(row)
        table: dict[int, tuple[float, tuple[int, ...]]] = {0: (0.0, ())}
        for row in costs:
            following: dict[int, tuple[float, tuple[int, ...]]] = {}
            for spent, (cost, taken) in table.items():
                for units, more in enumerate(row):
                    if spent + units <= k + 1 and ((s := spent + units) not in following or cost + more < following[s][0]):
                        following[s] = (cost + more, (*taken, units - 1))
            table = following
        if k + 1 in table and (best is None or table[k + 1][0] < best[0]):
            best = (table[k + 1][0], Plan(groups, table[k + 1][1]))
    assert best
    return best[1]


def equal_blocks(n: int, together: np.ndarray, k: int) -> Plan:
    """The plain pigeonhole: ``k + 1`` blocks, one of which two fingerprints within ``k`` bits share; correlated bits together."""
    return Plan(_grouped(together, n, k + 1), (0,) * (k + 1))


def _choose(n: int, k: int) -> int:
    out = 1
    for i in range(k):
        out = out * (n - i) // (i + 1)
    return out


def signatures(fps: DataFrame, plan: Plan) -> DataFrame:
    """``sig``, ``fp``, ``id`` and the further columns: a row for each signature a fingerprint is found or probed under."""
    found: list[Column] = []
    for i, (mask, bits, most) in enumerate(zip(plan.masks(), plan.bits, plan.thresholds, strict=True)):
        value = F.col("fp").bitwiseAND(F.lit(signed(mask)))
        for d in range(most + 1):
            for flips in combinations(bits, d):
                flip = sum(1 << (63 - b) for b in flips)
                found.append(F.xxhash64(F.lit(i), value.bitwiseXOR(F.lit(signed(flip)))))
    return fps.withColumn("sig", F.explode(F.array(*found)))


def spread(sigs: DataFrame, group: int = GROUP) -> DataFrame:
    """The signatures' rows with hot signatures cut into chunks that meet two by two.

    The cells, ``CELLS`` rows at most, are broadcast, so only sums move until the hot signatures are known; those are
    one row for each ``group`` rows at most, and are broadcast only if few enough.
    """
    cell = F.pmod("sig", F.lit(CELLS))
    cells = Shared(sigs.groupBy(cell.alias("cell")).count().where(F.col("count") > group).select("cell"), "hot-cells")
    if cells.frame.isEmpty():  # no signature has more rows than its cell
        return sigs
    counts = sigs.join(F.broadcast(cells.frame), cell == F.col("cell"), "left_semi").groupBy("sig").count()
    table = Shared(counts.where(F.col("count") > group).select("sig", F.ceil(F.col("count") / (group // 2)).cast("int").alias("chunks")), "hot-signatures")
    cells.drop()
    if table.frame.isEmpty():
        return sigs
    hot = beside(table.frame)
    own = F.pmod(F.xxhash64("id", F.lit(7)), F.col("chunks")).cast("int")
    met = F.when(F.col("chunks").isNull(), F.array(F.lit(None).cast("int"))).otherwise(F.sequence(F.lit(0), F.col("chunks") - 1))
    return (
        sigs.join(hot, "sig", "left")
        .withColumn("other", F.explode(met))
        .withColumn("sig", F.when(F.col("other").isNull(), F.col("sig")).otherwise(F.xxhash64("sig", F.least(own, "other"), F.greatest(own, "other"))))
        .drop("other", "chunks")
    )


def roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least index reachable over the pairs, for each of ``n`` indices."""
    root = np.arange(n)
    while len(a):
        low, high = np.minimum(root[a], root[b]), np.maximum(root[a], root[b])
        if (low == high).all():
            break
        np.minimum.at(root, high, low)
        while (root[root] != root).any():
            root = root[root]
    return root


def pairs(sig: np.ndarray, fp: np.ndarray, k: int, size: np.ndarray, ratio: float) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs within ``k`` bits, and of sizes within ``ratio``, among rows sorted by signature."""
    n, fp = len(sig), fp.view(np.uint64)  # of signed numbers bitwise_count counts the absolute value
    starts = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
    sizes = np.diff(np.append(starts, n))
    left, right = [], []
    size_of = np.repeat(sizes, sizes)
    for d in range(1, min(_SHORT, int(sizes.max(initial=1)))):
        at = np.flatnonzero((sig[d:] == sig[:-d]) & (size_of[:-d] <= _SHORT))
        if len(at):
            at = at[np.bitwise_count(fp[at] ^ fp[at + d]) <= k]
            at = at[np.minimum(size[at], size[at + d]) >= ratio * np.maximum(size[at], size[at + d])]
            left.append(at)
            right.append(at + d)
    for s, m in zip(starts[sizes > _SHORT], sizes[sizes > _SHORT], strict=True):
        own = fp[s : s + m]
        free = np.arange(m)
        for i in range(0, m, 256):  # what is found linked to an earlier block is not paired up again
            near = np.bitwise_count(own[i : i + 256, None] ^ own[None, :]) <= k
            a, b = size[s : s + m][i : i + 256, None], size[s : s + m][None, :]
            near &= np.minimum(a, b) >= ratio * np.maximum(a, b)
            x, y = np.nonzero(near)
            keep = x + i < y
            x, y = x[keep] + i, y[keep]
            root = roots(m, np.concatenate([x, np.arange(m)]), np.concatenate([y, free]))
            free = root
        at = np.flatnonzero(free != np.arange(m))
        left.append(free[at] + s)
        right.append(at + s)
    empty = np.zeros(0, np.int64)
    return np.concatenate([empty, *left]).astype(np.int64), np.concatenate([empty, *right]).astype(np.int64)


def segments(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Batches of a partition sorted by ``sig``, cut so that no signature is torn apart."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not len(batch):
            continue
        sig = batch.column("sig").to_numpy(zero_copy_only=False)
        cut = int(np.searchsorted(sig, sig[-1]))  # the last signature may go on in the next batch
        if held and (sig[0] != held[-1].column("sig")[-1].as_py() or cut):
            own = int(np.searchsorted(sig, held[-1].column("sig")[-1].as_py(), "right")) if sig[0] == held[-1].column("sig")[-1].as_py() else 0
            yield pa.Table.from_batches([*held, batch.slice(0, own)])
            held = []
            batch, sig = batch.slice(own), sig[own:]
            if not len(batch):
                continue
            cut = int(np.searchsorted(sig, sig[-1]))
        if cut:
            yield pa.Table.from_batches([batch.slice(0, cut)])
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held)


def linker(k: int, ratio: float):
    """Links between a signature's rows (``sig``, ``fp``, ``id``, ``size``) within ``k`` bits and of sizes within ``ratio``."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in segments(batches):
            sig, fp, ids, size = (part[c].to_numpy() for c in ("sig", "fp", "id", "size"))
            order = np.lexsort((ids, sig))  # the least id of a group is its root
            sig, fp, ids, size = sig[order], fp[order], ids[order], size[order]
            root = roots(len(sig), *pairs(sig, fp, k, size, ratio))
            at = np.flatnonzero(ids[root] != ids)
            yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(ids[root[at]])], ["a", "b"])

    return work


def dealt(sigs: DataFrame) -> DataFrame:
    """All rows of a signature in one partition, together."""
    return sigs.repartition("sig").sortWithinPartitions("sig")


def links(fps: DataFrame, k: int = 3, plan: Plan | None = None, group: int = GROUP, ratio: float = 0.0) -> DataFrame:
    """``a``, ``b``: links that join every two fingerprints within ``k`` bits, directly or over others within them.

    ``fps``: ``id``, ``fp`` (long), read several times: give it a written table.  With a ``ratio``, only pairs whose
    ``size`` columns are within it are linked: sets of that similarity can't differ more in size.
    """
    plan = plan or allocate(*bit_statistics(fps), k)
    size = F.col("size").cast("long") if ratio else F.lit(1).cast("long").alias("size")
    rows = fps.select("id", "fp", size)
    return dealt(spread(signatures(rows, plan), group)).select("sig", "fp", "id", "size").mapInArrow(linker(k, ratio), "a long, b long").distinct()
