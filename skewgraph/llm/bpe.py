"""Byte-level BPE by prefix dynamic programming (operator 3).

For every byte prefix of a piece there is exactly one token that can end its encoding: the token whose
predecessor (the unique last token of the shorter prefix) forms a valid pair with it.  One array of
last tokens therefore holds the encodings of *all* prefixes: appending bytes extends the array, an edit
redoes it from the first changed byte only, and the encoding is read off backwards.

A pair of tokens is valid if no merge would cross their border before both are complete.  Only the
tokens on the right spine of the left one and on the left spine of the right one ever touch the border,
so a pair is checked against those few.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: Entries of a worker's caches; a full cache is emptied.
CACHE_PIECES, CACHE_PAIRS = 400_000, 1_500_000
_NEVER = 1 << 62


class Vocabulary:
    """Ranks of a byte-level BPE, with each token's last merge and the spines of its merge tree."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {r: t for t, r in ranks.items()}
        self.longest = max(map(len, ranks))
        sizes: dict[bytes, set[int]] = {}
        for token in ranks:
            if len(token) > 2:
                sizes.setdefault(token[-3:], {1, 2}).add(len(token))
        #: For each three bytes the lengths of the tokens that end in them, the longest first; of other ends 2 and 1.
        self.sizes = {end: tuple(sorted(found, reverse=True)) for end, found in sizes.items()}
        self.merged: dict[tuple[int, int], int] = {}  # a pair's token
        self.parts: dict[int, tuple[int, int]] = {}
        self._right: dict[int, list[tuple[int, int]]] = {}
        self._left: dict[int, list[tuple[int, int]]] = {}
        self._pairs: dict[int, bool] = {}
        for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
            if len(token) > 1:
                self._learn(token, rank)

    @staticmethod
    def load_ranks(path: str) -> dict[bytes, int]:
        with open(path, "rb") as lines:
            return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        return cls(cls.load_ranks(path))

    def _learn(self, token: bytes, rank: int) -> None:
        """The last merge of a token: the one split into two earlier tokens that stay apart until then."""
        for i in range(1, len(token)):
            a, b = self.ranks.get(token[:i], _NEVER), self.ranks.get(token[i:], _NEVER)
            if a < rank and b < rank and self._valid(a, b):
                self.parts[rank] = (a, b)
                self.merged[a, b] = rank
                return

    def _spine(self, token: int, side: int, memo: dict[int, list[tuple[int, int]]]) -> list[tuple[int, int]]:
        """(token at the border, rank of the merge that ends it), from the whole token inwards."""
        if (found := memo.get(token)) is None:
            found, ends = [], _NEVER
            at = token
            while True:
                found.append((at, ends))
                if at not in self.parts:
                    break
                at, ends = self.parts[at][side], at
            memo[token] = found
        return found

    def _valid(self, left: int, right: int) -> bool:
        merged = self.merged
        for a, a_ends in self._spine(left, 1, self._right):
            for b, b_ends in self._spine(right, 0, self._left):
                # of equal merges the leftmost goes first: one that ends b lies right of the border
                if (rank := merged.get((a, b), _NEVER)) < a_ends and rank <= b_ends and rank < _NEVER:
                    return False
        return True

    def valid(self, left: int, right: int) -> bool:
        """Whether the encoding of both tokens' bytes together is just these two tokens."""
        key = left << 32 | right
        if (found := self._pairs.get(key)) is None:
            if len(self._pairs) >= CACHE_PAIRS:
                self._pairs.clear()
            found = self._pairs[key] = self._valid(left, right)
        return found

    def extend(self, data: bytes, last: list[int], upto: int | None = None) -> None:
        """Fill ``last`` up to the end of ``data`` (or ``upto``); it already holds the last tokens of the first prefixes."""
        token_of, sizes, known, n = self.ranks.get, self.sizes.get, self._pairs.get, len(data) if upto is None else upto
        for end in range(len(last) + 1, n + 1):
            for size in sizes(data[end - 3 : end], (2, 1)) if end > 2 else (2, 1)[2 - end :]:
                if size >= end:
                    if size == end and (token := token_of(data[:end])) is not None:
                        last.append(token)
                        break
                elif (token := token_of(data[end - size : end])) is not None:
                    left = last[end - size - 1]
                    if (good := known(left << 32 | token)) or (good is None and self.valid(left, token)):
                        last.append(token)
                        break
            else:
                raise ValueError(f"byte {data[end - 1]} has no token")

    def encode_piece(self, data: bytes) -> list[int]:
        if (whole := self.ranks.get(data)) is not None:
            return [whole]
        last: list[int] = []
        self.extend(data, last)
        return self.read(last)

    def read(self, last: list[int], end: int | None = None) -> list[int]:
        """The encoding of the first ``end`` bytes."""
        at, out = len(last) if end is None else end, []
        while at > 0:
            out.append(last[at - 1])
            at -= len(self.bytes_of[last[at - 1]])
        return out[::-1]


class PrefixEncoding:
    """One piece's table of last tokens: exact appends, and edits that redo only what they change.

    ``redone``: prefixes computed by the last append or edit.
    """

    def __init__(self, vocabulary: Vocabulary, data: bytes = b""):
        self.vocabulary, self.data, self.last, self.redone = vocabulary, b"", [], 0
        self.append(data)

    def append(self, data: bytes) -> None:
        self.data += data
        self.redone = len(data)
        self.vocabulary.extend(self.data, self.last)

    def replace(self, start: int, end: int, data: bytes) -> None:
        """Put ``data`` in the place of bytes ``start`` to ``end``.

        Prefixes up to ``start`` stay as they are.  A last token follows from the bytes and last tokens of the longest
        token's length before it, so once that many in a row behind the edit are what they were, all further ones are.
        """
        rest, self.data = self.last[end:], self.data[:start] + data + self.data[end:]
        del self.last[start:]
        behind, same, self.redone = start + len(data), 0, 0
        for upto in range(start + 1, len(self.data) + 1):
            self.vocabulary.extend(self.data, self.last, upto)
            self.redone += 1
            if upto > behind:
                same = same + 1 if self.last[-1] == rest[upto - behind - 1] else 0
                if same == self.vocabulary.longest:
                    self.last += rest[upto - behind :]
                    return

    def tokens(self, end: int | None = None) -> list[int]:
        """Tokens of the first ``end`` bytes (all)."""
        return self.vocabulary.read(self.last, end)


class Codec:
    """Encoder and decoder of whole texts: each match of a pattern is a piece of its own."""

    def __init__(self, vocabulary: Vocabulary, pattern: str):
        self.vocabulary, self.find = vocabulary, regex.compile(pattern).findall
        self.pieces: dict[str, bytes] = {}

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        pieces, out = self.pieces, []
        for piece in self.find(text):
            if (ids := pieces.get(piece)) is None:
                ids = array("I", self.vocabulary.encode_piece(piece.encode())).tobytes()
                if len(piece) <= 64:  # rare giants don't fill the cache
                    if len(pieces) >= CACHE_PIECES:
                        pieces.clear()
                    pieces[piece] = ids
            out.append(ids)
        return b"".join(out)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.vocabulary.bytes_of.__getitem__, array("I", ids)))


_CODECS: dict[tuple[str, str], Codec] = {}


def codec(path: str, pattern: str) -> Codec:
    """This worker's codec of a rank file."""
    if (path, pattern) not in _CODECS:
        _CODECS[path, pattern] = Codec(Vocabulary.load(path), pattern)
    return _CODECS[path, pattern]


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id``, ``ids`` (binary, little-endian unsigned 32-bit) of every whole text; null is empty."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch, texts in slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([own.encode(t.decode()) for t in texts], pa.binary())], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(work, "doc_id long, ids binary")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id``, ``text`` (binary) of ``encode``'s result; null ids are empty."""

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([own.decode(x or b"") for x in batch.column("ids").to_pylist()], pa.binary())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(work, "doc_id long, text binary")


DIGEST = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def round_trip(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encode and decode every whole text in one pass; digests of ids and decoded bytes.

    Null and empty texts have no ids and the digest of no bytes; repeated rows give repeated results.
    """

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, pattern)
        for batch, texts in slices(batches, "text"):
            n, ids_hex, text_hex = [], [], []
            for text in texts:
                ids = own.encode(text.decode())
                n.append(len(ids) // 4)
                ids_hex.append(hashlib.sha256(ids).hexdigest())
                text_hex.append(hashlib.sha256(own.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_hex), pa.array(text_hex)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(work, DIGEST)
