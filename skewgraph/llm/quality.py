"""Quality rules: hashed n-gram log-likelihood ratio between trusted and raw text (operator 2).

Word 1-grams and 2-grams of every text are hashed to ``buckets`` cells.  Two multinomials over the
cells are counted, one over the trusted documents and one over the whole corpus, and a document's
score is the mean over its n-grams of ``log p_trusted - log p_raw`` (length-normalised, so that long
texts are not favoured).  A few words averaged over a long text don't show there, so a second ratio of the same
kind sets documents labelled toxic against the corpus, over cells of lower-cased words and of their first
``PREFIX`` bytes, counted once a document; a text's toxicity is its strongest run of ``WINDOW`` words.  A document is
kept if it passes the base rules, its score reaches a fixed threshold and its toxicity stays below another.

Counts leave each task as one row per cell and kind, never as one row per word, so a hot source
costs its own tasks only; the model is arrays of ``buckets`` and ``TOXIC_BUCKETS`` numbers whatever the input.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, beside, slices, words_of

BUCKETS = 1 << 16
#: Mean log-ratio below which a document goes.
THRESHOLD = -0.15
#: Pseudo-count of every cell, as a share of the cell's raw probability.
PRIOR = 20_000.0
#: Cells of the toxic ratio; documents added to its observed and expected counts of each cell, so that rare words say little.
TOXIC_BUCKETS, TOXIC_PRIOR = 1 << 17, 8.0
#: Words of a run, the log-ratio's sum at which a run is toxic, and the least that a word can take from it.
WINDOW, TOXIC_RUN, TOXIC_FLOOR = 10, 3.1, -0.5
#: Bytes of a word's beginning that are a feature of their own.
PREFIX = 5
_SYMBOLS = b"#*$%&|<>"
_SPACES = b" \t\n\v\f\r"
#: Hashes of words seen by this worker; emptied when full.
_CACHE_WORDS = 300_000


class _WordHash(dict):
    """word -> 32-bit hash, computed on a miss."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_WORDS:
            self.clear()
        value = self[word] = zlib.crc32(word)
        return value


class _StemHash(dict):
    """word -> cells of the lower-cased word and of its beginning, the latter in the high half; short words are their own beginning."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_WORDS:
            self.clear()
        low = word.lower()
        whole = zlib.crc32(low) % TOXIC_BUCKETS
        value = self[word] = (zlib.crc32(low[:PREFIX], PREFIX) % TOXIC_BUCKETS if len(low) > PREFIX else whole) << 32 | whole
        return value


_HASHES, _STEMS = _WordHash(), _StemHash()


@dataclass(frozen=True)
class RatioModel:
    """Log-ratios of the cells; ``toxic``: those of the toxic ratio, none without labels."""

    weights: np.ndarray
    toxic: np.ndarray | None = None

    @property
    def buckets(self) -> int:
        return len(self.weights)


def cells(words: list[bytes], buckets: int) -> np.ndarray:
    """Cells of the 1-grams, then of the 2-grams, of one text."""
    h = np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))
    return _cells(h, buckets)


def stems(words: list[bytes]) -> np.ndarray:
    """Cells of each word and of its beginning (2 x words)."""
    h = np.fromiter(map(_STEMS.__getitem__, words), np.int64, len(words))
    return np.stack([h & 0xFFFFFFFF, h >> 32])


def toxicity(found: np.ndarray, weights: np.ndarray) -> float:
    """The greatest sum over ``WINDOW`` neighbouring words (all, if fewer) of the stronger ratio of a word and its beginning."""
    each = np.maximum(weights[found].max(axis=0), TOXIC_FLOOR)
    if len(each) <= WINDOW:
        return float(each.sum())
    run = np.concatenate([[0.0], np.cumsum(each, dtype=np.float64)])
    return float((run[WINDOW:] - run[:-WINDOW]).max())


def _mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
        return x ^ (x >> np.uint64(29))


def _cells(h: np.ndarray, buckets: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        two = h[:-1] * np.uint64(0x100000001B3) + h[1:] + np.uint64(1 << 40)
    return (_mix(np.concatenate([h, two])) % np.uint64(buckets)).astype(np.int64)


def repeated_words(ids: np.ndarray, window: int = 5) -> int:
    """Words that lie in a window of ``window`` words found twice or more in the text."""
    n = len(ids) - window + 1
    if n < 2:
        return 0
    code = ids[:n].astype(np.uint64)
    for k in range(1, window):  # exact: pairs of ranks never collide
        pair = code * np.uint64(1 << 32) + ids[k : k + n].astype(np.uint64)
        code = np.unique(pair, return_inverse=True)[1].astype(np.uint64)
    hit = np.bincount(code.astype(np.int64))[code.astype(np.int64)] > 1
    if not hit.any():
        return 0
    edges = np.zeros(len(ids) + 1, np.int64)
    edges[:n] += hit
    edges[window:] -= hit
    return int((np.cumsum(edges[:-1]) > 0).sum())


def base_counts(text: bytes, words: list[bytes]) -> tuple[int, int, int, int]:
    """word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    word_chars = len(text.decode()) - sum(text.count(c) for c in _SPACES)
    symbols = sum(text.count(c) for c in _SYMBOLS)
    lines = [x for x in text.split(b"\n") if x.strip(_SPACES)]
    dup = len(lines) - len(set(lines))
    repeat = 0
    if len(words) > 5 and len(set(words)) < len(words):  # a repeated window needs a repeated word
        seen: dict[bytes, int] = {}
        ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
        if len(seen) <= len(ids) - 5:  # five words at least recur
            repeat = _repeats(ids)
    return word_chars, symbols, dup, repeat


def _repeats(ids: np.ndarray) -> int:
    """Two-word windows first: most texts have no repeated pair that could grow to five words."""
    n = len(ids)
    pair = ids[:-1] * n + ids[1:]
    order = np.sort(pair)
    if not (order[1:] == order[:-1]).any():
        return 0
    return repeated_words(ids)


def fit(docs: DataFrame, trusted: DataFrame, flagged: DataFrame | None = None, buckets: int = BUCKETS, prior: float = PRIOR) -> RatioModel:
    """Count the multinomials over every text.

    ``docs``: ``doc_id``, ``text`` (null: no words); further columns are ignored, whatever their names.  ``trusted``,
    ``flagged``: the ``doc_id`` of trusted and of toxic documents, repeats and nulls allowed.  Without any trusted text
    all log-ratios are zero; without any flagged one no text is toxic.  The trusted cells are smoothed towards the raw
    distribution by ``prior`` n-grams.  Rows that repeat a document count each; an empty table gives zeros.
    """
    marks = trusted.select(F.col("doc_id").alias("_id"), F.lit(1).alias("trusted"), F.lit(0).alias("flagged"))
    if flagged is not None:
        marks = marks.unionByName(flagged.select(F.col("doc_id").alias("_id"), F.lit(0).alias("trusted"), F.lit(1).alias("flagged")))
    ids = Shared(marks.where("_id is not null").groupBy("_id").agg(F.max("trusted").alias("trusted"), F.max("flagged").alias("flagged")), "marked")
    marked = docs.select("doc_id", "text").join(beside(ids.frame), F.col("doc_id") == F.col("_id"), "left")
    rows = (
        marked.select("text", F.coalesce("trusted", F.lit(0)).alias("trusted"), F.coalesce("flagged", F.lit(0)).alias("flagged"))
        .mapInArrow(_counter(buckets, flagged is not None), "cell int, marked long, raw long")
        .groupBy("cell")
        .agg(F.sum("marked").alias("marked"), F.sum("raw").alias("raw"))
        .toArrow()
    )
    ids.drop()
    marked_n, raw_n = np.zeros(buckets + TOXIC_BUCKETS + 1), np.zeros(buckets + TOXIC_BUCKETS + 1)
    at = rows["cell"].to_numpy()
    marked_n[at], raw_n[at] = rows["marked"].to_numpy(), rows["raw"].to_numpy()
    return RatioModel(_ratios(marked_n[:buckets], raw_n[:buckets], prior), _toxic_ratios(marked_n[buckets:-1], raw_n[buckets:-1], marked_n[-1], raw_n[-1]))


def _ratios(trusted_n: np.ndarray, raw_n: np.ndarray, prior: float) -> np.ndarray:
    if not trusted_n.sum():
        return np.zeros(len(raw_n), np.float32)
    raw_p = (raw_n + 1) / (raw_n.sum() + len(raw_n))
    trusted_p = (trusted_n + prior * raw_p) / (trusted_n.sum() + prior)
    return (np.log(trusted_p) - np.log(raw_p)).astype(np.float32)


def _toxic_ratios(toxic_n: np.ndarray, raw_n: np.ndarray, toxic_all: float, raw_all: float) -> np.ndarray | None:
    """Observed over expected counts among ``toxic_all`` of ``raw_all`` marks, both with ``TOXIC_PRIOR`` added."""
    if not toxic_all:
        return None
    expected = (raw_n + 1) / (raw_all + len(raw_n)) * toxic_all
    return np.log((toxic_n + TOXIC_PRIOR) / (expected + TOXIC_PRIOR)).astype(np.float32)


def _counter(buckets: int, toxic: bool):
    """Cells of n-grams with their trusted and raw counts; beyond ``buckets`` cells of words with the toxic and all documents that hold them, and at the very end the sums of these."""

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, buckets), np.int64)
        held = np.zeros((2, TOXIC_BUCKETS + 1), np.int64)
        for batch, texts in slices(batches, "text"):
            marks = batch.column("trusted").to_pylist()
            words = [words_of(t) for t in texts]
            for mark in (0, 1):
                got = [cells(w, buckets) for w, m in zip(words, marks, strict=True) if m == mark and w]
                if got:
                    total[mark] += np.bincount(np.concatenate(got), minlength=buckets)
            if not toxic:
                continue
            marks = batch.column("flagged").to_pylist()
            for mark in (0, 1):
                got = [np.unique(stems(w)) for w, m in zip(words, marks, strict=True) if m == mark and w]
                if got:
                    every = np.concatenate(got)
                    held[mark, :-1] += np.bincount(every, minlength=TOXIC_BUCKETS)
                    held[mark, -1] += len(every)
        raw = np.concatenate([total.sum(axis=0), held.sum(axis=0)])
        marked = np.concatenate([total[1], held[1]])
        at = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(marked[at]), pa.array(raw[at])], ["cell", "marked", "raw"])

    return count


SCORED = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, score double, toxicity double, base_failed boolean, kept boolean"


def judge(docs: DataFrame, model: RatioModel, threshold: float = THRESHOLD, toxic_run: float = TOXIC_RUN, keep_columns: bool = False) -> DataFrame:
    """Base counts, score, toxicity and verdict of every document.

    Null and empty texts have no words, score and toxicity 0 and fail the base rule; repeated rows are judged one by
    one; ties with ``threshold`` are kept, with ``toxic_run`` rejected.  ``keep_columns`` returns the kept documents'
    own columns, whatever their names, instead of the measures.  An empty table gives an empty result.
    """
    weights, toxic = model.weights, model.toxic

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "text"):
            rows = []
            for text in texts:
                words = words_of(text)
                n = len(words)
                counts = base_counts(text, words)
                score = float(weights[cells(words, len(weights))].mean(dtype=np.float64)) if n else 0.0
                failed = n < 10 or 100 * counts[3] > 20 * n
                harm = toxicity(stems(words), toxic) if n and toxic is not None else 0.0
                rows.append((n, *counts, score, harm, failed, not failed and score >= threshold and harm < toxic_run))
            cols = list(zip(*rows, strict=True))
            if keep_columns:
                yield batch.filter(pa.array(cols[-1], pa.bool_()))
                continue
            kinds = [pa.int64()] * 5 + [pa.float64()] * 2 + [pa.bool_()] * 2
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)

    names = [x.split()[0] for x in SCORED.split(", ")]
    if keep_columns:
        return docs.mapInArrow(work, docs.schema)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(work, SCORED)


def trusted_ids(labels: DataFrame) -> DataFrame:
    """Documents whose labels all say good and not toxic."""
    return labels.groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("toxic").alias("t")).where("q = 1 and t = 0").select("doc_id")


def toxic_ids(labels: DataFrame) -> DataFrame:
    """Documents that some label calls toxic."""
    return labels.where("toxic = 1").select("doc_id").distinct()


def fit_labelled(docs: DataFrame, labels: DataFrame) -> RatioModel:
    """Both ratios from ``labels`` (``doc_id``, ``quality``, ``toxic``)."""
    return fit(docs, trusted_ids(labels), toxic_ids(labels))
