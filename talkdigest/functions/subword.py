"""Sub-word tokens: adjacent-pair merges learned from word counts, applied in Arrow batches."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .text import words


TOP = 1000  # pairs that reach the driver in a round


def fit(df: DataFrame, n_merges: int, text: str = "text") -> list[tuple[str, str]]:
    """Merges in order. All words take part; words and pairs are counted on the cluster, and only the TOP best pairs of a round reach
    the driver. A round gives all merges that are certain from its counts."""
    from ..operators.iteration import cut

    rows = df.select(F.explode(words(F.col(text))).alias("w")).groupBy("w").agg(F.count("*").alias("n")).select(F.split("w", "").alias("parts"), "n")
    merges: list[tuple[str, str]] = []
    new: list[tuple[str, str]] = []
    while len(merges) < n_merges:
        rows = cut(rows.mapInArrow(_merging(new), "parts array<string>, n long"))
        counts = rows.mapInArrow(_pairs, "a string, b string, n long").groupBy("a", "b").agg(F.sum("n").alias("n"))
        top = [((r.a, r.b), r.n) for r in counts.orderBy(F.desc("n"), "a", "b").limit(TOP).collect()]
        if not top:
            break
        new = certain(top, len(top) < TOP)[:n_merges - len(merges)]
        merges += new
    return merges


def certain(top: list[tuple[tuple[str, str], int]], whole: bool) -> list[tuple[str, str]]:
    """The merges that a step by step choice makes first, of pairs sorted by count: as long as none changes another's count and no
    pair that they bring forth (at most as often as a pair beside them) can come before the next one. whole: there are no further pairs."""
    out: list[tuple[str, str]] = []
    lefts, rights = set(), set()
    for k, (pair, n) in enumerate(top):
        beside = lambda p: p[0] in rights or p[1] in lefts
        if out and (not whole and n == top[-1][1] or any(beside(p) for p, m in top[k:] if m == n)):
            break
        out.append(pair)
        lefts.add(pair[0])
        rights.add(pair[1])
        if pair[0] == pair[1]:
            break
    return out


def _merging(merges: list[tuple[str, str]]):
    chosen = {p: i for i, p in enumerate(merges)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Words under the merges; one that is a single piece has no pairs and goes."""
        for batch in batches:
            parts, counts = [], []
            for word, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                word = tuple(word)
                for _, pair in sorted({(chosen[p], p) for p in zip(word, word[1:]) if p in chosen}):
                    word = joined(word, pair)
                if len(word) > 1:
                    parts.append(word)
                    counts.append(n)
            yield pa.RecordBatch.from_arrays([pa.array(parts, pa.list_(pa.string())), pa.array(counts, pa.int64())], names=["parts", "n"])

    return run


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        pairs: Counter = Counter()
        for word, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            for pair in zip(word, word[1:]):
                pairs[pair] += n
        a, b = zip(*pairs) if pairs else ((), ())
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.string()), pa.array(b, pa.string()), pa.array(pairs.values(), pa.int64())], names=["a", "b", "n"])


def joined(word: tuple[str, ...], pair: tuple[str, str]) -> tuple[str, ...]:
    out, i = [], 0
    while i < len(word):
        if word[i:i + 2] == pair:
            out.append(word[i] + word[i + 1])
            i += 2
        else:
            out.append(word[i])
            i += 1
    return tuple(out)


def pieces(word: str, ranks: dict[tuple[str, str], int]) -> tuple[str, ...]:
    parts = tuple(word)
    while len(parts) > 1:
        rank, pair = min((ranks.get(p, len(ranks)), p) for p in zip(parts, parts[1:]))
        if rank == len(ranks):
            break
        parts = joined(parts, pair)
    return parts


def encode(df: DataFrame, merges: list[tuple[str, str]], text: str = "text") -> DataFrame:
    """df with `pieces array<string>`; joined again they give the words."""
    ranks = df.sparkSession.sparkContext.broadcast({tuple(p): i for i, p in enumerate(merges)})

    @F.pandas_udf("array<string>")
    def split(column: pd.Series) -> pd.Series:
        cut = lru_cache(100_000)(lambda w: pieces(w, ranks.value))
        return column.map(lambda ws: [p for w in ws for p in cut(w)])

    return df.withColumn("pieces", split(words(F.col(text))))
