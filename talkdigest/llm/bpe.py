"""Byte-level BPE encoding and decoding by a rank file.

Each match of the pattern is encoded by itself: its bytes form a linked list, every adjacent pair that has a merge
rank waits in that rank's bucket, and a hierarchical bitmap of the non-empty buckets gives the least rank by
find-first-set. Buckets hold positions in ascending order; an entry whose pair has changed since is stale and
skipped. The cost is near linear in the bytes, also for pre-tokens of millions of bytes.

Defined results: null text counts as empty (no tokens, empty decoding); lone surrogates cannot occur in a Spark
string; ids outside the vocabulary raise KeyError when decoded; repeated rows are encoded alike.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache
from heapq import heappop, heappush

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPAN = 8
MASK = (1 << SPAN) - 1
CACHED = 600_000  # pre-tokens in a generation of what a worker remembers
CACHED_BYTES = 64  # longer ones aren't remembered


class BitQueue:
    """A set of small integers that gives its least one: a bit for every member in words of 2 ** SPAN, and a bit above for every word that isn't empty."""

    __slots__ = ("top", "words")

    def __init__(self):
        self.top, self.words = 0, {}

    def add(self, x: int) -> None:
        word = x >> SPAN
        self.words[word] = self.words.get(word, 0) | 1 << (x & MASK)
        self.top |= 1 << word

    def remove(self, x: int) -> None:
        word = x >> SPAN
        left = self.words[word] & ~(1 << (x & MASK))
        if left:
            self.words[word] = left
        else:
            del self.words[word]
            self.top &= ~(1 << word)

    def least(self) -> int:
        """-1 if empty."""
        top = self.top
        if not top:
            return -1
        word = (top & -top).bit_length() - 1
        bits = self.words[word]
        return word << SPAN | ((bits & -bits).bit_length() - 1)


class Vocabulary:
    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.pieces = {b: a for a, b in self.ranks.items()}
        self.names = {b: str(b) for b in self.pieces}
        self.single = [self.ranks.get(bytes([a]), -1) for a in range(256)]
        self.pairs = [self.ranks.get(bytes([a, b]), -1) for a in range(256) for b in range(256)]
        self.split = regex.compile(pattern)
        self.known: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}

    def merged(self, data: bytes) -> tuple[int, ...]:
        """The ids of one pre-token."""
        rank_of = self.ranks.get
        if (whole := rank_of(data)) is not None:
            return (whole,)
        n, pairs = len(data), self.pairs
        waits = [pairs[a << 8 | b] for a, b in zip(data, data[1:])]  # rank of the pair that starts at a position, -1 for none or a merged one
        waits.append(-1)
        queue, buckets = BitQueue(), {}
        add, remove, least = queue.add, queue.remove, queue.least
        for i, rank in enumerate(waits):
            if rank >= 0:
                if rank in buckets:
                    buckets[rank].append(i)
                else:
                    buckets[rank] = [i]
                    add(rank)
        ends, before = list(range(1, n + 1)), list(range(-1, n))  # of the piece that starts here; start of the piece before
        while buckets:
            rank = least()
            bucket = buckets[rank]
            i = heappop(bucket) if len(bucket) > 1 else bucket.pop()
            if not bucket:
                del buckets[rank]
                remove(rank)
            if waits[i] != rank:
                continue  # stale
            middle = ends[i]
            end = ends[i] = ends[middle]
            waits[middle] = -1
            before[end] = i
            rank = waits[i] = rank_of(data[i:ends[end]], -1) if end < n else -1
            if rank >= 0:
                if rank in buckets:
                    heappush(buckets[rank], i)
                else:
                    buckets[rank] = [i]
                    add(rank)
            if i:
                j = before[i]
                rank = waits[j] = rank_of(data[j:end], -1)
                if rank >= 0:
                    if rank in buckets:
                        heappush(buckets[rank], j)
                    else:
                        buckets[rank] = [j]
                        add(rank)
        ids, i, single = [], 0, self.single
        while i < n:
            end = ends[i]
            ids.append(single[data[i]] if end == i + 1 else rank_of(data[i:end]))
            i = end
        return tuple(ids)

    def remembered(self, piece: str) -> tuple[int, ...]:
        """From the older generation of the memory, or encoded; a full generation becomes the older one."""
        got = self.older.get(piece)
        if got is None:
            data = piece.encode()
            got = self.merged(data)
            if len(data) > CACHED_BYTES:
                return got
        if len(self.known) >= CACHED:
            self.older, self.known = self.known, {}
        self.known[piece] = got
        return got

    def encode(self, text: str) -> list[int]:
        ids = []
        for piece in self.split.findall(text):
            ids += self.known.get(piece) or self.remembered(piece)
        return ids

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids))


@lru_cache(2)
def vocabulary(path: str, pattern: str) -> Vocabulary:
    """One for each worker process; path is readable on every node, as the tokenizer files are installed there."""
    return Vocabulary(path, pattern)


def _digests(path: str, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(path, pattern)
        names = vocab.names.__getitem__
        for batch in batches:
            counts, encoded, decoded = [], [], []
            for text in batch.column(1):
                ids = vocab.encode(text.as_py() or "")
                counts.append(len(ids))
                encoded.append(hashlib.sha256(" ".join(map(names, ids)).encode()).hexdigest())
                decoded.append(hashlib.sha256(vocab.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(encoded, pa.string()), pa.array(decoded, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def digests(documents: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of the encoding and its decoding, one row a document."""
    kind = dict(documents.dtypes)["doc_id"]
    return documents.select("doc_id", "text").mapInArrow(_digests(path, pattern), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encoded(documents: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, ids array<int>)."""
    def run(batches):
        vocab = vocabulary(path, pattern)
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([vocab.encode(t or "") for t in part.column(1).to_pylist()], pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return documents.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(documents.dtypes)['doc_id']}, ids array<int>")


def decoded(rows: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, bytes binary) of (doc_id, ids)."""
    def run(batches):
        vocab = vocabulary(path, pattern)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([vocab.decode(ids or []) for ids in batch.column(1).to_pylist()], pa.binary())], names=["doc_id", "bytes"])

    return rows.select("doc_id", "ids").mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, bytes binary")
