"""Fuzzy line deduplication over the corpus (operator 6).

Lines are normalised (lower case, digits alike, ASCII punctuation dropped, white space even) and get
``BANDS`` MinHashes of ``ROWS`` values each, and a SimHash, of their longer words.  Equal normalised lines
collapse first, whatever their length.  Lines that share a band, are of like length and have SimHashes within
``k`` bits are candidates; only those that have such a partner bring their text, and a pair counts if its edit
similarity reaches ``similarity``.  Of each connected group the first occurrence stays and all others go; lines
without a letter or digit always stay.

Words, line digests and fingerprints are computed for whole chunks of text at once, as arrays over its bytes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import Shared, beside, fresh, slices
from .components import components
from .hamming import GROUP, dealt, pairs, roots, segments
from .simhash import bands, majority

#: SimHash bits in which candidates may differ: edits of a fifth of the words change about 14, unrelated lines differ in 32.
K = 23
SIMILARITY = 0.8
#: MinHash bands, and values of a band: lines that share 65 % of their longer words meet with a chance of 99 %.
BANDS, ROWS = 14, 3
#: Words of up to so many bytes say little about a line: they only count where it has no longer ones.
SHORT_WORD = 4
_DROP = bytes(c for c in range(33, 127) if not chr(c).isalnum())
_DIGITS = bytes.maketrans(b"0123456789", b"0" * 10)
_STEP = 0x9E3779B97F4A7C15
#: Letters from which a bound over words is tried before the distance; letters of the pairs that are compared at once.
_LONG, _CELLS = 200, 1 << 22
#: The highest of 64 bits.
_HIGHEST = np.uint64(1 << 63)
#: Pairs that are compared at once, so that few are compared that others link meanwhile.
_PAIRS = 8192
#: Bytes of texts whose signatures are taken together, so that many pairs of like length are compared at once.
_TAKEN = 12 << 20
#: Bytes of text whose lines are digested at once: arrays of that many numbers stay in the cache.
_DIGESTED = 512 << 10
#: A line under one of its bands, as it moves to the shard of that signature.
_ROW = np.dtype([("id", "<i8"), ("fp", "<u8"), ("sig", "<u4"), ("size", "<u4"), ("at", "u1")])
#: A line among those of its digest, ``n`` of them so far.
_LINE = np.dtype([("id", "<i8"), ("doc_id", "<i8"), ("fp", "<i8"), ("n", "<i8"), ("line", "<i4"), ("size", "<i4"), ("bands", "<i4", (BANDS,))])
#: Lines of a shard on average, and lines dealt out at once.
_LINE_SHARD, _LINES_DEALT = 1 << 16, 1 << 17
#: Rows of a shard on average, rows dealt out at once, and rows of a signature in one chunk of lines from which it is counted.
_SHARD, _DEALT, _COUNTED = 1 << 18, 1 << 20, 3
#: Powers of an odd number, by which bytes of a word and words of a line are weighted; longer ones begin anew.
_POWERS = np.array([pow(_STEP, i + 1, 1 << 64) for i in range(4096)], np.uint64)


def normal_words(line: bytes) -> list[bytes]:
    return line.translate(_DIGITS, _DROP).split()


def _lowered(text: bytes) -> bytes:
    return text if text.isascii() and text.islower() else text.decode().lower().encode()


def _mixed(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        return x ^ (x >> np.uint64(32))


def _weighted(values: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """64-bit digests of consecutive runs of numbers."""
    at = np.arange(len(values)) - np.repeat(starts, sizes)
    with np.errstate(over="ignore"):
        by = _POWERS.take(at, mode="wrap")
        by *= values
        if sizes.max() > len(_POWERS):
            by ^= (at >> 12).astype(np.uint64)
        return _mixed(np.add.reduceat(by, starts) + sizes.astype(np.uint64))


@dataclass(frozen=True)
class _Lines:
    """The lines with words of some texts: where they stand, their digests, sizes in characters and telling words."""

    text: np.ndarray
    line: np.ndarray
    h: np.ndarray
    size: np.ndarray
    words: np.ndarray
    n_words: np.ndarray


def _digested(texts: list[bytes]) -> _Lines | None:
    """All lines of ``texts`` at once.  A line's digest depends on its normalised words and their order alone."""
    data = b"\n\0".join(_lowered(t).replace(b"\0", b"") for t in texts)  # a null byte begins each further text
    codes = np.frombuffer(data.translate(_DIGITS, _DROP) + b" ", np.uint8)
    space = (codes == 32) | ((codes >= 9) & (codes <= 13)) | (codes == 0)
    edge = np.diff(np.concatenate([[True], space]).view(np.int8))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    if not len(starts):
        return None
    if len(ends) < len(starts):
        ends = np.append(ends, len(codes))
    sizes = ends - starts
    inside = codes[~space]
    first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    word = _weighted(inside, first, sizes)
    chars = np.add.reduceat(((inside & 0xC0) != 0x80).astype(np.int64), first)
    row = np.cumsum(codes == 10)[starts]
    heads = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
    per_line = np.diff(np.append(heads, len(row)))
    telling = sizes > SHORT_WORD
    none = np.add.reduceat(telling.astype(np.int64), heads) == 0
    telling |= np.repeat(none, per_line)
    first_row = np.concatenate([[0], np.cumsum(codes == 10)[np.flatnonzero(codes == 0)]])
    line_row = row[heads]
    text = np.searchsorted(first_row, line_row, side="right") - 1
    return _Lines(text, line_row - first_row[text], _weighted(word, heads, per_line), np.add.reduceat(chars, heads) + per_line - 1, word[telling], np.add.reduceat(telling.astype(np.int64), heads))


def _same(a: str, b: str) -> int:
    """Length of the common beginning, by halving."""
    low, high = 0, min(len(a), len(b))
    while low < high:
        mid = (low + high + 1) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid - 1
    return low


def _trimmed(a: str, b: str) -> tuple[str, str]:
    """Two texts without their common ends, the longer first."""
    start = _same(a, b)
    a, b = a[start:], b[start:]
    end = _same(a[::-1], b[::-1])
    a, b = a[: len(a) - end], b[: len(b) - end]
    return (a, b) if len(a) >= len(b) else (b, a)


def _reach(a: str, b: str, most: int) -> int:
    """Cells to either side of the diagonal that a path of at most ``most`` edits can cross: it has to come back to the last cell."""
    return (most + len(a) - len(b)) // 2


def _within(rows: list[str], columns: list[str], most: np.ndarray) -> np.ndarray:
    """Whether the Levenshtein distance of each pair of texts is at most ``most``, all pairs at once.

    Only the band of cells that such a distance can cross is computed, column by column: each pair has some words of
    bits, the band's lowest cell on top.  Known are the value of that cell (``low``) and whether each cell is one more
    (``up``) or less (``down``) than the one above.  Texts are brought to one number of columns by a common end, which
    leaves the distance as it is.  ``low`` never falls, so pairs in which it exceeds what ``most`` allows are left out
    on the way.
    """
    n, m, k = len(rows), np.array([len(x) for x in rows]), np.array([len(x) for x in columns])
    reach = (most + m - k) // 2  # as in ``_reach``
    words, width, every, one = int(2 * reach.max()) // 64 + 1, int(k.max()), np.arange(n), np.uint64(1)
    band = 64 * words
    begin, rest = band - 1 - reach, width - k
    letters, points = np.unique(np.frombuffer("".join(rows + columns).encode("utf-32-le"), np.uint32), return_inverse=True)
    kinds = len(letters) + 1  # the last one is the common end
    place = lambda at, sizes: np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes - at, sizes)
    at = np.zeros(((width + band) // 64 + 2, n * kinds), np.uint64)  # for each pair's letters the rows that hold them
    row = np.concatenate([place(begin, m), place(begin + m, rest)])
    cell = np.concatenate([np.repeat(every, m) * kinds + points[: m.sum()], np.repeat(every, rest) * kinds + kinds - 1])
    np.bitwise_or.at(at, (row >> 6, cell), one << (row & 63).astype(np.uint64))
    letter = np.repeat((every * kinds + kinds - 1)[None, :], width, axis=0)
    letter[place(0 * k, k), np.repeat(every, k)] = np.repeat(every, k) * kinds + points[m.sum() :]

    def cells(least: np.ndarray, end: int) -> np.ndarray:
        """The band's bits from ``least`` up to ``end``."""
        bit = np.arange(band)
        return np.packbits((bit >= least[:, None]) & (bit < end), axis=1, bitorder="little").view("<u8").T.copy()

    up = cells(begin, band)
    down = np.zeros_like(up)
    low, limit = reach.copy(), most + reach + k - m
    out = np.zeros(n, bool)
    for j in range(width):
        held, shift = at[j >> 6 : (j >> 6) + words + 1].take(letter[j], axis=1), np.uint64(j & 63)
        same = held[:-1] >> shift
        if shift:
            same |= held[1:] << (np.uint64(64) - shift)
        met = same & up
        total = met + up
        over = total < met
        for w in range(1, words):
            total[w] += over[w - 1]
            over[w] |= (total[w] == 0) & over[w - 1]
        level = (total ^ up) | same | down  # cells equal to the one before them on the diagonal
        more, less = down | ~(level | up), level & up
        low += level[-1] < _HIGHEST
        after = level >> one
        after[:-1] |= level[1:] << np.uint64(63)
        up, down = less | ~(after | more), after & more
        if j % 16 == 15:
            on = low <= limit
            left = np.count_nonzero(on)
            if not left:
                return out
            if 4 * left <= 3 * len(on):
                letter, up, down, low, limit, every = letter[:, on], up[:, on], down[:, on], low[on], limit[on], every[on]
    below = (width + reach - (m + rest))[every]  # cells of the last column under the last row; the band has moved on by one
    under = cells(band - 1 - below, band - 1)
    out[every] = low - np.bitwise_count(up & under).sum(axis=0, dtype=np.int64) + np.bitwise_count(down & under).sum(axis=0, dtype=np.int64) <= most[every]
    return out


def _near(a: str, b: str, most: int) -> bool:
    """The same of one pair, its band one long number: for few pairs."""
    at: dict[str, int] = {}
    reach = _reach(a, b, most)
    for i, c in enumerate(a, reach):
        at[c] = at.get(c, 0) | 1 << i
    full = (1 << 2 * reach + 1) - 1
    up, down, low, limit = full >> reach << reach, 0, reach, most + reach + len(b) - len(a)
    for j, c in enumerate(b):
        same = at.get(c, 0) >> j & full
        level = ((((same & up) + up) ^ up) | same | down) & full
        more, less = down | (full ^ (level | up)), level & up
        after = level >> 1
        if not level >> 2 * reach:
            low += 1
            if low > limit:
                return False
        up, down = less | (full ^ (after | more)), after & more
    below = len(b) + reach - len(a)
    under = ((1 << below) - 1) << (2 * reach - below)
    return low - (up & under).bit_count() + (down & under).bit_count() <= most


def _distance(a: str, b: str) -> int:
    """Levenshtein distance of two texts with letters, as one bit-parallel number a column: for few pairs."""
    at: dict[str, int] = {}
    for i, c in enumerate(a):
        at[c] = at.get(c, 0) | 1 << i
    full, last, score = (1 << len(a)) - 1, 1 << (len(a) - 1), len(a)
    up, down = full, 0  # where a cell is one more, one less, than the cell above
    for c in b:
        same = at.get(c, 0)
        keep = same | down
        across = ((((same & up) + up) ^ up) | same) & full
        more, less = (down | ~(across | up)) & full, up & across
        score += bool(more & last) - bool(less & last)
        more, less = (more << 1 | 1) & full, (less << 1) & full
        up, down = (less | ~(keep | more)) & full, more & keep
    return score


def edit_distance(a: str, b: str) -> int:
    """Levenshtein distance."""
    a, b = _trimmed(a, b)
    return _distance(a, b) if b else len(a)


def _bound(a: str, b: str, most: float) -> int:
    """An upper bound of the distance: words that both have in order stay, what lies between is rewritten."""
    x, y = a.split(" "), b.split(" ")
    places: dict[tuple[str, str], int] = {}
    for q in range(len(y) - 1, 0, -1):
        places[y[q - 1], y[q]] = q - 1
    i = j = cost = 0
    width = lambda part: sum(map(len, part)) + len(part)
    while i < len(x) and j < len(y):
        if x[i] == y[j]:
            i, j = i + 1, j + 1
            continue
        for p in range(i, len(x) - 1):
            q = places.get((x[p], x[p + 1]), -1)
            if q >= j:
                break
        else:
            break
        cost += max(width(x[i:p]), width(y[j:q]))
        if cost > most:
            return cost
        i, j = p, q
    return cost + max(width(x[i:]), width(y[j:]))


def all_alike(pairs_of: list[tuple[str, str]], similarity: float) -> np.ndarray:
    """For each pair whether ``1 - distance / longer length`` reaches ``similarity``."""
    out = np.zeros(len(pairs_of), bool)
    open_at, rows, columns, limits = [], [], [], []
    for i, (a, b) in enumerate(pairs_of):
        most = (1 - similarity) * max(len(a), len(b)) + 1e-9
        if abs(len(a) - len(b)) > most:
            continue
        x, y = _trimmed(a, b)
        if len(x) <= most or len(x) > _LONG and _bound(a, b, most) <= most:
            out[i] = True
        elif y and len(x) - len(y) <= most:
            open_at.append(i)
            rows.append(x)
            columns.append(y)
            limits.append(most)
    wide = [(2 * _reach(a, b, int(most)) // 64 + 1).bit_length() for a, b, most in zip(rows, columns, limits, strict=True)]
    order = sorted(range(len(rows)), key=lambda i: (wide[i], len(rows[i])))
    while order:
        longest, widest = len(rows[order[-1]]), wide[order[-1]]
        size = max(1, _CELLS // (2 * longest))
        size = min(size, sum(1 for i in order[-size:] if wide[i] == widest and 3 * len(rows[i]) >= 2 * longest))  # pairs of like length and band go together
        part, order = order[-size:], order[:-size]
        a, b, most = [rows[i] for i in part], [columns[i] for i in part], [int(limits[i]) for i in part]
        if len(part) >= 100 + longest // 256:
            found = _within(a, b, np.array(most)).tolist()
        else:
            found = map(_near, a, b, most)
        for i, good in zip(part, found, strict=True):
            out[open_at[i]] = good
    return out


def alike(a: str, b: str, similarity: float) -> bool:
    """Whether ``1 - distance / longer length`` reaches ``similarity``."""
    return bool(all_alike([(a, b)], similarity)[0])


LINES = "doc_id long, line int, h long, raw long, fp long, size int, bands array<int>"


def line_hashes(docs: DataFrame, packed: bool = False) -> DataFrame:
    """``doc_id``, ``line`` (from 0), ``h`` (of the normalised line), ``raw`` (Spark's ``xxhash64`` of the line), ``fp`` (SimHash), ``size`` (characters of the normalised line), ``bands`` (``packed``: as bytes) of every line with words."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text", _DIGESTED):
            if (found := _digested(texts)) is None:
                continue
            given = [t.split(b"\n") for t in texts]
            raw = np.fromiter((xxh64_intdigest(given[t][i], 42) for t, i in zip(found.text.tolist(), found.line.tolist(), strict=True)), np.uint64, len(found.text))
            fp, marks = majority(found.words, found.n_words), bands(found.words, found.n_words, BANDS, ROWS)
            if packed:
                lists = _as_bytes(marks)
            else:
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, marks.size + 1, BANDS, dtype=np.int32)), pa.array(marks.ravel()))
            doc_ids = batch.column("doc_id").take(pa.array(found.text))
            hashes = (pa.array(x.view(np.int64)) for x in (found.h, raw, fp))
            yield pa.RecordBatch.from_arrays([doc_ids, pa.array(found.line.astype(np.int32)), *hashes, pa.array(found.size.astype(np.int32)), lists], ["doc_id", "line", "h", "raw", "fp", "size", "bands"])

    schema = LINES.replace("array<int>", "binary") if packed else LINES
    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long"), "text").mapInArrow(work, schema)


def _as_bytes(rows: np.ndarray) -> pa.Array:
    """Each row of an array as a cell of bytes."""
    width = rows.nbytes // max(1, len(rows))
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(np.arange(len(rows) + 1, dtype=np.int32) * np.int32(width)), pa.py_buffer(np.ascontiguousarray(rows))])


def _bands_of(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Bands, as lists or bytes, as rows of an array."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not pa.types.is_binary(column.type):
        return column.flatten().to_numpy().reshape(-1, BANDS)
    if not len(column):
        return np.zeros((0, BANDS), np.int32)
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(np.int32).reshape(-1, BANDS)


def _blocks(shard: np.ndarray, shards: int, rows: np.ndarray) -> pa.RecordBatch:
    """``shard``, ``rows``: for each shard its rows in one cell."""
    shard = shard.astype(np.uint16 if shards <= 1 << 16 else np.uint32)
    order = np.argsort(shard, kind="stable")
    shard = shard[order]
    first = np.flatnonzero(np.concatenate([[True], shard[1:] != shard[:-1]]))
    ends = (np.append(first, len(shard)) * rows.itemsize).astype(np.int32)
    cells = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(ends), pa.py_buffer(rows[order].view(np.uint8))])
    return pa.RecordBatch.from_arrays([pa.array(shard[first].astype(np.int32)), cells], ["shard", "rows"])


def _by_shard(batches: Iterable[pa.RecordBatch], kind: np.dtype) -> Iterator[tuple[int, np.ndarray]]:
    """Each shard of a partition that is sorted by ``shard``, with its rows put together."""
    last, held = None, []
    for batch in batches:
        for shard, cell in zip(batch.column("shard").to_pylist(), batch.column("rows"), strict=True):
            if shard != last and held:
                yield last, np.concatenate(held)
                held = []
            last = shard
            held.append(np.frombuffer(cell.as_buffer(), kind))
    if held:
        yield last, np.concatenate(held)


def _firsts(rows: np.ndarray) -> np.ndarray:
    """Of each digest the first line, with the number of all."""
    order = np.lexsort((rows["line"], rows["doc_id"], rows["id"]))
    ids = rows["id"][order]
    first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
    out = rows[order[first]]
    out["n"] = np.add.reduceat(rows["n"][order], first)
    return out


def distinct_lines(lines: DataFrame) -> DataFrame:
    """``id``, ``fp``, ``size``, ``bands`` (bytes), ``doc_id``, ``line``, ``n``: for each digest of ``line_hashes`` its first occurrence, and how many there are.

    Lines move to the shards of their digests as blocks of rows, equal ones of a block as one.
    """
    shards = max(8, -(-lines.count() // _LINE_SHARD))

    def deal(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def blocks() -> pa.RecordBatch:
            rows = _firsts(np.concatenate(held))
            held.clear()
            return _blocks(rows["id"].view(np.uint64) % np.uint64(shards), shards, rows)

        for batch in batches:
            rows = np.empty(len(batch), _LINE)
            for to, name in (("id", "h"), ("doc_id", "doc_id"), ("fp", "fp"), ("line", "line"), ("size", "size")):
                rows[to] = batch.column(name).to_numpy()
            rows["n"], rows["bands"] = 1, _bands_of(batch.column("bands"))
            held.append(rows)
            if sum(map(len, held)) >= _LINES_DEALT:
                yield blocks()
        if sum(map(len, held)):
            yield blocks()

    def collapse(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["id", "fp", "size", "doc_id", "line", "n"]
        for _, rows in _by_shard(batches, _LINE):
            rows = _firsts(rows)
            yield pa.RecordBatch.from_arrays([*(pa.array(np.ascontiguousarray(rows[c])) for c in names), _as_bytes(rows["bands"])], [*names, "bands"])

    dealt_out = lines.select("h", "doc_id", "line", "fp", "size", "bands").mapInArrow(deal, "shard int, rows binary").repartition("shard").sortWithinPartitions("shard")
    return dealt_out.mapInArrow(collapse, "id long, fp long, size int, doc_id long, line int, n long, bands binary")


def _texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``id``, ``fp``, ``text``: the normalised texts of lines ``id``, ``fp``, ``doc_id``, ``line``."""
    by_doc = wanted.groupBy(F.col("doc_id").alias("_doc")).agg(F.collect_list(F.struct("line", "id", "fp")).alias("wanted"))
    held = docs.select(F.col("doc_id").cast("long"), "text").join(beside(by_doc, "size(wanted)"), F.col("doc_id") == F.col("_doc")).select("text", "wanted")

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text"):
            picked = []
            for text, own in zip(texts, batch.column("wanted").to_pylist(), strict=True):
                lines = _lowered(text).split(b"\n")
                picked += [(x["id"], x["fp"], b" ".join(normal_words(lines[x["line"]].replace(b"\0", b"")))) for x in own if x["line"] < len(lines)]
            picked = [x for x in picked if x[2]]
            found = _digested([x[2] for x in picked]) if picked else None
            if found is None:
                continue
            ids = np.array([x[0] for x in picked], np.int64)
            keep = np.flatnonzero(found.h.view(np.int64) == ids)  # another row may repeat the doc_id
            cols = zip(*(picked[i] for i in keep.tolist()), strict=True)
            if len(keep):
                ids, fps, own = cols
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(fps, pa.int64()), pa.array([x.decode() for x in own], pa.string())], ["id", "fp", "text"])

    return held.mapInArrow(work, "id long, fp long, text string").dropDuplicates(["id"])


def _met(sig: np.ndarray, fp: np.ndarray, at: np.ndarray, held: np.ndarray, k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of one signature within ``k`` bits that share no earlier band, for small groups all at once, for a large one row by row."""
    cuts = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
    sizes = np.diff(np.append(cuts, len(sig)))
    size_of = np.repeat(sizes, sizes)
    earlier = np.arange(held.shape[1])[None, :] < at[:, None]
    new = lambda i, j: ~((held[i] == held[j]) & earlier[i]).any(axis=1)
    for d in range(1, min(64, int(sizes.max(initial=1)))):
        i = np.flatnonzero((sig[d:] == sig[:-d]) & (size_of[:-d] <= 64))
        i = i[np.bitwise_count(fp[i] ^ fp[i + d]) <= k]
        i = i[new(i, i + d)]
        yield i, i + d
    for start, size in zip(cuts[sizes > 64].tolist(), sizes[sizes > 64].tolist(), strict=True):
        for i in range(start, start + size - 1):
            j = np.flatnonzero(np.bitwise_count(fp[i + 1 : start + size] ^ fp[i]) <= k) + i + 1
            i_of = np.full(len(j), i)
            keep = new(i_of, j)
            yield i_of[keep], j[keep]


def _taken(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches put together until their texts reach ``_TAKEN`` bytes."""
    held: list[pa.RecordBatch] = []
    n = 0
    for batch in batches:
        held.append(batch)
        n += batch.column("text").nbytes
        if n >= _TAKEN:
            yield pa.concat_batches(held)
            held, n = [], 0
    if held:
        yield pa.concat_batches(held)


def _gathered(found: Iterator[tuple[np.ndarray, np.ndarray]]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs, at least ``_PAIRS`` at a time but for the last."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    n = 0
    for i, j in found:
        if len(i):
            held.append((i, j))
            n += len(i)
        if n >= _PAIRS:
            yield np.concatenate([x for x, _ in held]), np.concatenate([x for _, x in held])
            held, n = [], 0
    if held:
        yield np.concatenate([x for x, _ in held]), np.concatenate([x for _, x in held])


def _nearest(i: np.ndarray, j: np.ndarray, common: np.ndarray, n: int) -> np.ndarray:
    """Of the pairs those that have the most bands in common among the pairs of one of their lines."""
    most = np.zeros(n, common.dtype)
    np.maximum.at(most, i, common)
    np.maximum.at(most, j, common)
    at = np.flatnonzero((common == most[i]) | (common == most[j]))
    first = np.unique(np.where(common[at] == most[i[at]], i[at], n + j[at]), return_index=True)[1]
    return at[np.sort(first)]


def _verifier(k: int, similarity: float):
    """Links between a signature's lines: near in bits and alike in text, unless others link them already.

    Two lines are compared under the first band that they share only, those of most common bands first, so that few
    are compared that a task's other links join anyway.
    """

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right = np.zeros(0, np.int64), np.zeros(0, np.int64)  # all links of the task so far
        for part in segments(_taken(batches)):
            sig, fp, ids, texts = part["sig"].to_numpy(), part["fp"].to_numpy().view(np.uint64), part["id"].to_numpy(), part["text"].to_pylist()
            at, held = part["at"].to_numpy(), _bands_of(part["bands"])
            every, own = np.unique(np.concatenate([ids, left, right]), return_inverse=True)
            root = roots(len(every), *np.split(own[len(ids) :], 2))
            own, before = own[: len(ids)], len(left)
            for i, j in _gathered(_met(sig, fp, at, held, k)):
                for last in (False, True):
                    apart = np.flatnonzero(root[own[i]] != root[own[j]])
                    i, j = i[apart], j[apart]
                    now = np.arange(len(i)) if last else _nearest(own[i], own[j], (held[i] == held[j]).sum(axis=1), len(every))
                    good = now[all_alike([(texts[a], texts[b]) for a, b in zip(i[now].tolist(), j[now].tolist(), strict=True)], similarity)]
                    if len(good):
                        root = roots(len(root), np.concatenate([root[own[i[good]]], np.arange(len(root))]), np.concatenate([root[own[j[good]]], root]))
                        left, right = np.concatenate([left, ids[i[good]]]), np.concatenate([right, ids[j[good]]])
                    rest = np.ones(len(i), bool)
                    rest[now] = False
                    i, j = i[rest], j[rest]
            yield pa.RecordBatch.from_arrays([pa.array(left[before:]), pa.array(right[before:])], ["a", "b"])

    return work


def _signatures(marks: np.ndarray) -> np.ndarray:
    """A row's signatures, one for each band: different for different bands."""
    with np.errstate(over="ignore"):
        return _mixed(marks.view(np.uint32).astype(np.uint64) | np.arange(BANDS, dtype=np.uint64) << np.uint64(32))


def _some(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches in pieces whose lines have at most ``_DEALT`` bands."""
    for batch in batches:
        for start in range(0, len(batch), _DEALT // BANDS):
            yield batch.slice(start, _DEALT // BANDS)


def _counter(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``sig``, ``n`` of the signatures that are frequent in some lines together."""
    held: list[np.ndarray] = []

    def counted() -> pa.RecordBatch:
        sig = np.sort(np.concatenate(held))
        first = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))
        n = np.diff(np.append(first, len(sig)))
        often = n >= _COUNTED
        return pa.RecordBatch.from_arrays([pa.array(sig[first[often]].view(np.int64)), pa.array(n[often])], ["sig", "n"])

    for batch in _some(batches):
        held.append(_signatures(_bands_of(batch.column("bands"))).ravel())
        if sum(map(len, held)) >= _DEALT:
            yield counted()
            held.clear()
    if held:
        yield counted()


def _hot(distinct: DataFrame, group: int) -> tuple[np.ndarray, np.ndarray]:
    """Signatures of over ``group`` lines, sorted, and into how many chunks each is cut.

    Each task counts a chunk of lines at a time and leaves out what has under ``_COUNTED`` rows there, so little moves;
    a signature may thus have that many rows more for each chunk before it counts as hot.
    """
    rows = distinct.select("bands").mapInArrow(_counter, "sig long, n long").groupBy("sig").agg(F.sum("n").alias("n")).where(F.col("n") > group).toArrow()
    sig, n = rows["sig"].to_numpy().view(np.uint64), rows["n"].to_numpy()
    order = np.argsort(sig)
    return sig[order], -(-n[order] // max(1, group // 2))


def _dealer(hot: np.ndarray, cut: np.ndarray, shards: int):
    """Lines (``id``, ``fp``, ``size``, ``bands``) as ``shard``, ``rows``: the ``_ROW`` of each of their bands, many in a cell.

    Rows of a hot signature go to chunks that meet two by two, each pair of chunks under a signature of its own.
    """

    def rows(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        sig = _signatures(_bands_of(batch.column("bands"))).ravel()
        out = np.empty(len(sig), _ROW)
        out["id"] = np.repeat(batch.column("id").to_numpy(), BANDS)
        out["fp"] = np.repeat(batch.column("fp").to_numpy().view(np.uint64), BANDS)
        out["size"] = np.repeat(batch.column("size").to_numpy(), BANDS)
        out["at"] = np.tile(np.arange(BANDS, dtype=np.uint8), len(batch))
        if len(hot):
            place = np.minimum(np.searchsorted(hot, sig), len(hot) - 1)
            often = hot[place] == sig
            at = np.flatnonzero(often)
            while len(at):  # as many at a time as make few enough rows
                total = np.cumsum(cut[place[at]])
                now, at = np.split(at, [max(1, int(np.searchsorted(total, _DEALT, "right")))])
                chunks = cut[place[now]]
                own = np.repeat((_mixed(out["id"][now].view(np.uint64)) % chunks.astype(np.uint64)).astype(np.int64), chunks)
                other = np.arange(chunks.sum()) - np.repeat(np.cumsum(chunks) - chunks, chunks)
                with np.errstate(over="ignore"):
                    met = _mixed(np.repeat(sig[now], chunks) + np.uint64(_STEP) * (np.minimum(own, other) << 32 | np.maximum(own, other)).astype(np.uint64))
                yield met, np.repeat(out[now], chunks)
            sig, out = sig[~often], out[~often]
        yield sig, out

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def blocks() -> pa.RecordBatch:
            sig, out = (np.concatenate([x[i] for x in held]) for i in (0, 1))
            held.clear()
            out["sig"] = sig >> np.uint64(32)
            return _blocks((sig & np.uint64(0xFFFFFFFF)) % np.uint64(shards), shards, out)

        for batch in _some(batches):
            for found in rows(batch):
                held.append(found)
                if sum(len(x) for x, _ in held) >= _DEALT:
                    yield blocks()
        if sum(len(x) for x, _ in held):
            yield blocks()

    return work


def _candidates(k: int, ratio: float):
    """``sig``, ``at``, ``id`` of the lines that have another within ``k`` bits, and of a size within ``ratio``, under a signature."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard, rows in _by_shard(batches, _ROW):
            sig = rows["sig"]
            order = np.argsort(sig)
            sig = sig[order]
            same = sig[1:] == sig[:-1]
            order = order[np.concatenate([same, [False]]) | np.concatenate([[False], same])]  # others have no partner
            if not len(order):
                continue
            rows = rows[order]
            sig, size = np.ascontiguousarray(rows["sig"]), rows["size"].astype(np.int64)
            root = roots(len(sig), *pairs(sig, np.ascontiguousarray(rows["fp"]), k, size, ratio))
            linked = np.flatnonzero(root != np.arange(len(sig)))
            at = np.unique(np.concatenate([linked, root[linked]]))
            whole = _mixed(sig[at].astype(np.uint64) << np.uint64(32) | np.uint64(shard)).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(whole), pa.array(rows["at"][at].astype(np.int64)), pa.array(rows["id"][at])], ["sig", "at", "id"])

    return work


def line_links(docs: DataFrame, distinct: DataFrame, k: int = K, similarity: float = SIMILARITY, group: int = GROUP) -> DataFrame:
    """``a``, ``b``: links between distinct lines (``id``, ``fp``, ``size``, ``bands``, ``doc_id``, ``line``) that are near and alike.

    Lines move to the shards of their bands as blocks of rows, which Spark neither reads nor sorts one by one.
    """
    shards = max(8, -(-distinct.count() * BANDS // _SHARD))
    blocks = distinct.select("id", "fp", "size", "bands").mapInArrow(_dealer(*_hot(distinct, group), shards), "shard int, rows binary")
    places = Shared(blocks.repartition("shard").sortWithinPartitions("shard").mapInArrow(_candidates(k, similarity - 1e-9), "sig long, at long, id long"), "near-line-signatures")
    wanted = Shared(distinct.join(places.frame.select("id").distinct(), "id"), "near-line-places")
    texts = Shared(_texts_of(docs, wanted.frame).join(wanted.frame.select("id", "bands"), "id"), "near-line-texts")
    wanted.drop()
    held = places.frame.join(texts.frame, "id").select("sig", "at", "fp", "id", "bands", "text")
    return dealt(held).mapInArrow(_verifier(k, similarity), "a long, b long").distinct()


def removals(docs: DataFrame, k: int = K, similarity: float = SIMILARITY) -> Shared:
    """A written table ``doc_id``, ``gone`` (array of line, raw): each document's lines of which another occurrence stays."""
    lines = Shared(line_hashes(docs, packed=True), "lines")
    distinct = Shared(distinct_lines(lines.frame), "distinct-lines")
    linked = components(line_links(docs, distinct.frame, k, similarity), "line-groups")
    groups = linked.frame
    members = groups.unionByName(groups.select(F.col("root").alias("id"), "root").distinct())
    every = distinct.frame.drop("bands")
    placed = every.join(members, "id")
    first = placed.groupBy("root").agg(F.min(F.struct("doc_id", "line")).alias("first"))
    of_groups = placed.join(first, "root").select(F.col("id").alias("h"), F.col("first.doc_id").alias("_doc"), F.col("first.line").alias("_line"))
    alone = every.where("n > 1").join(members, "id", "left_anti")
    stays = of_groups.unionByName(alone.select(F.col("id").alias("h"), F.col("doc_id").alias("_doc"), F.col("line").alias("_line")))
    stays = Shared(stays, "groups-of-lines")
    gone = lines.frame.join(beside(stays.frame), "h").where("doc_id <> _doc or line <> _line")
    result = Shared(gone.groupBy("doc_id").agg(F.collect_list(F.struct("line", "raw")).alias("gone")), "gone-lines")
    for table in (lines, distinct, linked, stays):
        table.drop()
    return result


def dedup(docs: DataFrame, k: int = K, similarity: float = SIMILARITY, measures: bool = True) -> DataFrame:
    """The documents without repeated lines: their columns with ``text`` cut down, and ``n_lines``, ``n_removed``.

    Occurrences are ordered by ``doc_id``, then line.  Rows without a ``doc_id`` take no part and come back as they are,
    null texts too; rows that repeat a ``doc_id`` and text keep the same lines; a document may end up empty but never
    goes; an empty table gives an empty result.  ``measures``: given columns called as the two are replaced by them;
    without, the columns are the given ones, and documents that lost lines and have no word left go: all they held
    stays elsewhere.  No other column name clashes.
    """
    doc, gone, cut = (fresh(n, docs.columns) for n in ("_doc", "_gone", "_cut"))
    own = beside(removals(docs, k, similarity).frame.select(F.col("doc_id").alias(doc), F.col("gone").alias(gone)), f"size({gone})")
    joined = docs.join(own, docs["doc_id"] == own[doc], "left").drop(doc)
    whole = F.struct(F.col("text").alias("text"), F.lit(0).cast("long").alias("n"))
    shorter = _let(F.split("text", "\n"), lambda given: _let(_places(given, F.col(gone)), lambda at: _without(given, at)))
    joined = joined.withColumn(cut, F.when(F.col("text").isNull() | F.col(gone).isNull(), whole).otherwise(shorter))
    kept = [c for c in docs.columns if not measures or c.lower() not in ("n_lines", "n_removed")]
    columns = [F.col(cut)["text"].alias(c) if c == "text" else F.col(f"`{c}`") for c in kept]
    if measures:
        n_lines = F.when(F.col("text").isNull(), F.lit(0)).otherwise(F.size(F.split("text", "\n"))).cast("long")
        return joined.select(*columns, n_lines.alias("n_lines"), F.col(cut)["n"].alias("n_removed"))
    return joined.where((F.col(cut)["n"] == 0) | F.col(cut)["text"].rlike(r"[^\x20\x09-\x0D]")).select(*columns)


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is computed once, however often it is used."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _places(given: Column, gone: Column) -> Column:
    """The lines to go: of a row that repeats a doc_id with another text only those that are the ones meant."""
    meant = F.filter(gone, lambda x: F.xxhash64(F.get(given, x["line"])) == x["raw"])
    return F.concat(F.array(F.lit(-1)), F.array_sort(F.array_distinct(F.transform(meant, lambda x: x["line"]))), F.array(F.size(given)))


def _without(given: Column, at: Column) -> Column:
    """The runs of lines between the places, put together."""
    run = lambda i: F.slice(given, F.get(at, i) + 2, F.get(at, i + 1) - F.get(at, i) - 1)
    stays = F.flatten(F.transform(F.sequence(F.lit(0), F.size(at) - 2), run))
    return F.struct(F.array_join(stays, "\n").alias("text"), (F.size(at) - 2).cast("long").alias("n"))
