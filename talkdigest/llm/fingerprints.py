"""Document fingerprints from prefix polynomial hashes.

For a text c_0 .. c_n-1 of code points the prefix array holds S_i = sum of (c_j + 1) * B^j below i, modulo a prime.
The hash of any span is (S_b - S_a) * B^-a, so spans are compared in constant time and the longest common extension
of two positions, to either side, is found by binary search. A fingerprint is the hash of the whole text under two
primes, its length, and the KEPT least hashes of its spans of WIDTH code points, for those who keep no texts.

The likeness of two fingerprints is computed from the prefix arrays behind them: the share of the code points of both
texts that lie in a span of WIDTH or more that the other text holds too, or in the longest common prefix or suffix. It
is exact but for collisions under two primes, at any length of text; resemblance() estimates from the strings alone.

The next document is found without a global sort: doc_ids are cut into ranges at quantiles, an id or a null that many rows
have also by the hash of the text; each range is sorted in a task and streamed, and a copy of the first document of the next
range ends it. Only the cuts and the firsts of the ranges, at most CHUNKS numbers each, pass through the driver.

Defined results: null text is empty; the only document is its own next one; repeated or null doc_ids are ordered by
a hash of the text (nulls before all others); equal texts have equal fingerprints; two empty texts are alike (1), an empty
and another one aren't (0); any ids, of the whole long range, will do; empty table: no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIMES = (2147483647, 2147483629)
BASES = (1000003, 998244353)
WIDTH, KEPT = 24, 32
CHUNKS = 1 << 15
ROWS_A_CHUNK = 512


class Powers:
    """Powers of a base and of its inverse modulo a prime, as many as the longest text so far needs."""

    def __init__(self, base: int, prime: int):
        self.prime, self.base, self.back = prime, base, pow(base, -1, prime)
        self.up = self.down = np.ones(1, np.uint64)

    def grow(self, n: int) -> None:
        while len(self.up) < n:
            k = len(self.up)
            self.up = np.concatenate([self.up, self.up * np.uint64(pow(self.base, k, self.prime)) % np.uint64(self.prime)])
            self.down = np.concatenate([self.down, self.down * np.uint64(pow(self.back, k, self.prime)) % np.uint64(self.prime)])


POWERS = [Powers(b, p) for b, p in zip(BASES, PRIMES)]


def points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


class Prefixes:
    def __init__(self, code: np.ndarray):
        self.n, values = len(code), code.astype(np.uint64) + np.uint64(1)
        self.sums, self._sorted = [], None
        for powers in POWERS:
            powers.grow(self.n + 1)
            prime = np.uint64(powers.prime)
            total = np.zeros(self.n + 1, np.uint64)
            np.cumsum(values * powers.up[:self.n] % prime, out=total[1:])  # below 2^31 each: exact for 2^33 code points
            self.sums.append(total % prime)

    def span(self, a: int, b: int) -> tuple[int, ...]:
        return tuple(int((int(s[b]) - int(s[a])) % p.prime * int(p.down[a]) % p.prime) for s, p in zip(self.sums, POWERS))

    def spans(self, start: int = 0, end: int | None = None, width: int = WIDTH) -> np.ndarray:
        """Hashes of all spans of a width from start on, before end: both primes in one number."""
        end = self.n if end is None else end
        if end - start < width:
            return np.empty(0, np.uint64)
        one, two = ((s[start + width:end + 1] + (prime - s[start:end + 1 - width])) % prime * p.down[start:end + 1 - width] % prime
                    for s, p in zip(self.sums, POWERS) for prime in (np.uint64(p.prime),))
        return one << np.uint64(32) | two

    def sorted(self) -> np.ndarray:
        """Hashes of all spans of WIDTH, ascending."""
        if self._sorted is None:
            self._sorted = np.sort(self.spans())
        return self._sorted


def common_extension(a: Prefixes, i: int, b: Prefixes, j: int) -> int:
    """Length of the longest common prefix of a's text from i and b's text from j."""
    low, high = 0, min(a.n - i, b.n - j)
    while low < high:
        middle = (low + high + 1) // 2
        if a.span(i, i + middle) == b.span(j, j + middle):
            low = middle
        else:
            high = middle - 1
    return low


def common_extension_back(a: Prefixes, i: int, b: Prefixes, j: int) -> int:
    """Length of the longest common suffix of a's text before i and b's text before j."""
    low, high = 0, min(i, j)
    while low < high:
        middle = (low + high + 1) // 2
        if a.span(i - middle, i) == b.span(j - middle, j):
            low = middle
        else:
            high = middle - 1
    return low


def covered(a: Prefixes, b: Prefixes, prefix: int, suffix: int) -> int:
    """How many code points of a lie in a span of WIDTH or more that b holds too, or in the common prefix or suffix."""
    start, end = max(0, prefix - WIDTH + 1), min(a.n, a.n - suffix + WIDTH - 1)  # spans that reach between the two
    mine, there = a.spans(start, end), b.sorted()
    if not len(mine) or not len(there):
        return min(a.n, prefix + suffix)
    at = np.minimum(np.searchsorted(there, mine), len(there) - 1)
    inside = np.zeros(a.n + 1, np.int32)
    inside[0] += 1
    inside[prefix] -= 1
    inside[a.n - suffix] += 1
    hits = start + np.flatnonzero(there[at] == mine)
    inside[hits] += 1
    inside[hits + WIDTH] -= 1
    return int((np.cumsum(inside[:-1]) > 0).sum())


def likeness(a: Prefixes, b: Prefixes) -> float:
    if a.n == b.n and a.span(0, a.n) == b.span(0, b.n):
        return 1.0
    if not a.n or not b.n:
        return 0.0
    prefix = common_extension(a, 0, b, 0)
    suffix = common_extension_back(a, a.n, b, b.n)
    return (covered(a, b, prefix, suffix) + covered(b, a, prefix, suffix)) / (a.n + b.n)


def shown(prefixes: Prefixes) -> str:
    """The fingerprint as a string."""
    whole, least = prefixes.span(0, prefixes.n), prefixes.sorted()
    some = np.unique(least[:8 * KEPT])[:KEPT]
    if len(some) < KEPT:
        some = np.unique(least)[:KEPT]
    return f"{prefixes.n:x}.{whole[0]:08x}{whole[1]:08x}.{some.astype('>u8').tobytes().hex()}"


def resemblance(a: str, b: str) -> float:
    """Of two strings of shown(): 1 if equal, else an estimate of the Jaccard of their spans of WIDTH from the least hashes."""
    if a == b:
        return 1.0
    x, y = (np.frombuffer(bytes.fromhex(s.rpartition(".")[2]), ">u8").astype(np.uint64) for s in (a, b))
    both = np.union1d(x, y)[:KEPT] if max(len(x), len(y)) >= KEPT else np.union1d(x, y)
    return float(np.isin(both, np.intersect1d(x, y)).mean()) if len(both) else 0.0


def edited(code: np.ndarray, following: np.ndarray) -> np.ndarray:
    """The last quarter (rounded down) replaced by the first as many code points of the following text."""
    k = len(code) // 4
    return np.concatenate([code[:len(code) - k], following[:k]])


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, same_prefix long"


def _stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows are sorted by chunk, then order; `ends` marks the copy that only ends a chunk."""
    held = None
    out: list[tuple] = []

    def flush():
        cols = list(zip(*out))
        out.clear()
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=[c.split()[0] for c in OUT.split(", ")])

    for batch in batches:
        for chunk, ends, doc_id, text in zip(*(batch.column(batch.schema.get_field_index(c)) for c in ("chunk", "ends", "doc_id", "text"))):
            code = points(text.as_py())
            mine = (chunk.as_py(), doc_id.as_py(), code, Prefixes(code))
            if held is not None and held[0] == mine[0]:
                changed = edited(held[2], code)
                after = Prefixes(changed)
                out.append((held[1], len(held[2]), hashlib.sha256(changed.tobytes().decode("utf-32-le").encode()).hexdigest(), shown(held[3]), shown(after), likeness(held[3], after), likeness(held[3], mine[3]), common_extension(held[3], 0, after, 0)))
            held = None if ends.as_py() else mine
            if len(out) >= 512:
                yield flush()
    if out:
        yield flush()


def cuts(documents: DataFrame, n: int) -> list[int]:
    """Ids that cut n rows into about equal ranges; an id that many rows have stands several times. Any cuts give right results."""
    chunks = max(1, min(CHUNKS, -(-n // ROWS_A_CHUNK)))
    shares = [k / chunks for k in range(1, chunks)]
    found = documents.where("doc_id is not null").select(F.col("doc_id").cast("double").alias("at")).approxQuantile("at", shares, max(1e-5, 0.2 / chunks)) if shares else []
    return sorted(max(-(1 << 63), min((1 << 63) - 1, int(x))) for x in found)


def _at_most(bounds: Column, n: int, below) -> Column:
    """How many of n ascending bounds satisfy below(bound), which holds for a first part of them: a binary search."""
    steps = F.array(*[F.lit(1 << k) for k in reversed(range(n.bit_length()))])

    def ahead(place, step):
        there = place + step
        return F.when((there <= n) & below(F.get(bounds, F.least(there, F.lit(n)) - 1)), there).otherwise(place)

    return F.aggregate(steps, F.lit(0), ahead)


def _share(order_key: Column) -> Column:
    """A hash as a share, 0 to below 1, in the hash's order."""
    return F.least(order_key / float(1 << 64) + 0.5, F.lit(1 - 2.0 ** -53))


def chunked(rows: DataFrame, bounds: list[int], nulls: int) -> DataFrame:
    """rows (doc_id, order_key, ...) with `chunk`, which grows with (doc_id nulls first, order_key)."""
    if bounds:
        table = F.split(F.lit(",".join(map(str, bounds))), ",").cast("array<bigint>")  # folded to one literal
        rows = rows.withColumn("under", _at_most(table, len(bounds), lambda b: b < F.col("doc_id")))
        rows = rows.withColumn("upto", _at_most(table, len(bounds), lambda b: b <= F.col("doc_id")))
    else:
        rows = rows.withColumn("under", F.lit(0)).withColumn("upto", F.lit(0))
    parts = max(1, -(-nulls // ROWS_A_CHUNK))
    within = F.floor(_share(F.col("order_key")) * (F.col("upto") - F.col("under") + 1))
    chunk = F.when(F.col("doc_id").isNull(), F.floor(_share(F.col("order_key")) * parts) - parts).otherwise(F.col("under") + within)
    return rows.withColumn("chunk", chunk.cast("long")).drop("under", "upto")


def fingerprinted(documents: DataFrame) -> DataFrame:
    """(doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, same_prefix), one row a document; same_prefix: code points that
    the text and the edited text have in common from the start."""
    n, nulls = documents.agg(F.count("*"), F.count_if(F.col("doc_id").isNull())).first()
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = chunked(rows.withColumn("order_key", F.xxhash64("text")), cuts(documents, n), nulls)
    firsts = sorted((r.chunk, r.first) for r in rows.groupBy("chunk").agg(F.min(F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id", "order_key")).alias("first")).collect())  # at most CHUNKS rows, and the nulls' parts
    # the first row of a chunk also ends the one before it
    ends = rows.sparkSession.createDataFrame([(own, x.doc_id, x.order_key, firsts[i - 1][0]) for i, (own, x) in enumerate(firsts)] or [(0, 0, 0, 0)], "of_chunk long, first_id long, first_key long, ended long")
    rows = rows.join(F.broadcast(ends), (F.col("chunk") == F.col("of_chunk")) & F.col("doc_id").eqNullSafe(F.col("first_id")) & (F.col("order_key") == F.col("first_key")), "left")
    goes = F.when(F.col("ended").isNull(), F.array(F.struct("chunk", F.lit(False).alias("ends")))).otherwise(
        F.array(F.struct("chunk", F.lit(False).alias("ends")), F.struct(F.col("ended").alias("chunk"), F.lit(True).alias("ends"))))
    rows = rows.select("doc_id", "order_key", "text", F.inline(goes))
    spread = rows.repartition("chunk").sortWithinPartitions("chunk", "ends", F.asc_nulls_first("doc_id"), "order_key")
    return spread.select("chunk", "ends", "doc_id", "text").mapInArrow(_stream, OUT)
