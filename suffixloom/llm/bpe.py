"""Byte-level BPE with a hierarchical-bitmap rank queue.

Pairs wait in buckets, one for each merge rank; a bucket is a heap of list positions. Which buckets hold entries
is written in two levels of bitmaps, so the lowest rank is found by a find-first-set on each. Symbols form
a doubly linked list over byte positions. A merge makes the entries of the neighbouring pairs stale; they
stay in their buckets and are skipped when popped. Each merge costs a few bitmap steps whatever the length, so
a pre-token of a million bytes takes no quadratic time.

Defined results: a null or empty text has no ids; ids of repeated rows repeat; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
from heapq import heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map
from .pretokens import splitter

#: Pre-tokens in each of the cache's two halves; when the younger is full it becomes the older. Bounds memory, never results.
CACHE_ENTRIES = 400_000
#: Longer pre-tokens are encoded each time and not kept.
CACHE_BYTES = 64


class RankQueue:
    """Positions by rank; pop() gives the leftmost position of the lowest rank.

    Two levels of bitmaps: words of 256 ranks, and a top word that says which of those have a bit set (under 200
    bits for 50,000 ranks).
    """

    __slots__ = ("buckets", "words", "top")

    def __init__(self) -> None:
        self.buckets: dict[int, list[int]] = {}
        self.words: dict[int, int] = {}
        self.top = 0

    def fill(self, ranks: list[int | None]) -> None:
        """Push each rank at its index, from left to right, into an empty queue."""
        buckets, words = self.buckets, self.words
        for i, rank in enumerate(ranks):
            if rank is not None:
                if rank in buckets:
                    buckets[rank].append(i)
                else:
                    buckets[rank] = [i]
                    word = rank >> 8
                    words[word] = words.get(word, 0) | 1 << (rank & 255)
        for word in words:
            self.top |= 1 << word

    def push(self, rank: int, position: int) -> None:
        bucket = self.buckets.get(rank)
        if bucket is not None:
            heappush(bucket, position)
            return
        self.buckets[rank] = [position]
        word = rank >> 8
        self.words[word] = self.words.get(word, 0) | 1 << (rank & 255)
        self.top |= 1 << word

    def pop(self) -> tuple[int, int] | None:
        top = self.top
        if not top:
            return None
        word = (top & -top).bit_length() - 1
        bits = self.words[word]
        first = bits & -bits
        rank = word << 8 | first.bit_length() - 1
        bucket = self.buckets[rank]
        if len(bucket) > 1:
            return rank, heappop(bucket)
        del self.buckets[rank]
        bits ^= first
        self.words[word] = bits
        if not bits:
            self.top = top ^ 1 << word
        return rank, bucket[0]


class ByteBpe:
    """Encoder and decoder over a table of byte strings and their ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self.tokens = {i: b for b, i in ranks.items()}
        self.names = {i: str(i) for i in self.tokens}
        self.split = splitter(pattern)
        self.cache: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}

    @classmethod
    def from_file(cls, path: str, pattern: str) -> ByteBpe:
        with open(path, "rb") as lines:
            return cls({base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}, pattern)

    def merge(self, data: bytes) -> list[int]:
        """Ids of one pre-token: always the pair of lowest rank first, the leftmost among equals."""
        ranks = self.ranks
        if (whole := ranks.get(data)) is not None:
            return [whole]
        n = len(data)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        queue = RankQueue()
        get, push, pop = ranks.get, queue.push, queue.pop
        waiting: list[int | None] = [get(data[i : i + 2]) for i in range(n - 1)]
        queue.fill(waiting)
        waiting.append(None)
        while (top := pop()) is not None:
            rank, i = top
            if waiting[i] != rank:
                continue  # stale: this pair was merged away or has another rank by now
            gone = after[i]
            end = after[gone]
            after[i], waiting[gone] = end, None
            waiting[i] = None
            if end < n:
                before[end] = i
                if (new := get(data[i : after[end]])) is not None:
                    waiting[i] = new
                    push(new, i)
            if (left := before[i]) >= 0:
                waiting[left] = new = get(data[left:end])
                if new is not None:
                    push(new, left)
        ids, i = [], 0
        while i < n:
            ids.append(ranks[data[i : after[i]]])
            i = after[i]
        return ids

    def pieces(self, piece: str) -> tuple[int, ...]:
        """Ids of a pre-token that is not in the younger half of the cache."""
        found = self.older.get(piece) or tuple(self.merge(piece.encode("utf-8", "surrogatepass")))
        if len(piece) <= CACHE_BYTES:
            if len(self.cache) >= CACHE_ENTRIES:
                self.older = self.cache.copy()
                self.cache.clear()
            self.cache[piece] = found
        return found

    def encode(self, text: str) -> list[int]:
        ids: list[int] = []
        extend, get = ids.extend, self.cache.get
        for piece in self.split(text):
            extend(get(piece) or self.pieces(piece))
        return ids

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


_loaded: dict[tuple[str, str], ByteBpe] = {}


def loaded(path: str, pattern: str) -> ByteBpe:
    """The tables of path, read once for each worker process."""
    key = (path, pattern)
    if key not in _loaded:
        _loaded[key] = ByteBpe.from_file(path, pattern)
    return _loaded[key]


def encode_texts(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and ids (array of int) of each whole text. ranks_path must exist on every executor."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        bpe = loaded(ranks_path, pattern)
        return {"doc_id": batch.column(0).to_pylist(), "ids": [bpe.encode(text or "") for text in batch.column(1).to_pylist()]}

    return arrow_map(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), rows, "doc_id long, ids array<int>")


def decode_ids(encoded: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id and the bytes of each array of ids; a null array gives no bytes."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        bpe = loaded(ranks_path, pattern)
        return {"doc_id": batch.column(0).to_pylist(), "data": [bpe.decode(ids or ()) for ids in batch.column(1).to_pylist()]}

    return arrow_map(encoded.select(F.col(id_col).alias("doc_id"), F.col(ids_col).alias("ids")), rows, "doc_id long, data binary")


def round_trip(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Digests of ids and of their decoding, made in one pass so that neither ids nor bytes are shipped."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        bpe = loaded(ranks_path, pattern)
        out: dict[str, list] = {"doc_id": batch.column(0).to_pylist(), "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
        for text in batch.column(1):
            ids = bpe.encode(text.as_py() or "")
            out["n_tokens"].append(len(ids))
            out["ids_sha256"].append(hashlib.sha256(" ".join(map(bpe.names.__getitem__, ids)).encode()).hexdigest())
            out["decoded_sha256"].append(hashlib.sha256(bpe.decode(ids)).hexdigest())
        return out

    return arrow_map(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), rows, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
