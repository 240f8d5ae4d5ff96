"""ROUGE-1, -2 and -L by clipped counts and longest common subsequences, no stemming."""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import grams, sentences, words


def scored(match: Column, cand: Column, ref: Column) -> Column:
    """struct(p, r, f) with every 0/0 as 0."""
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    return F.struct(ratio(match, cand).alias("p"), ratio(match, ref).alias("r"), ratio(2.0 * match, cand + ref).alias("f"))


def ngram(pairs: DataFrame, n: int = 1) -> DataFrame:
    """(key, match, cand, ref) of pairs (key, cand array<string>, ref array<string>).

    Both sides' grams are counted in one aggregation, so there is one exchange by (key, gram) and no join."""
    if n < 1:
        raise ValueError(f"n must be 1 or more, not {n}")
    side = lambda c, a, b: pairs.select("key", F.explode_outer(F.col(c) if n == 1 else grams(F.col(c), n)).alias("gram"), F.lit(a).alias("a"), F.lit(b).alias("b"))
    both = side("cand", 1, 0).unionByName(side("ref", 0, 1))
    counts = both.groupBy("key", "gram").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    real = F.col("gram").isNotNull()
    total = lambda x: F.coalesce(F.sum(F.when(real, x)), F.lit(0)).cast("long")
    return counts.groupBy("key").agg(total(F.least("a", "b")).alias("match"), total(F.col("a")).alias("cand"), total(F.col("b")).alias("ref"))


def ngram_by_row(pairs: DataFrame, n: int = 1) -> DataFrame:
    """As ngram(), of pairs with a row a key: counted row by row, without a shuffle of n-grams."""
    if n < 1:
        raise ValueError(f"n must be 1 or more, not {n}")

    @F.pandas_udf("long")
    def match(cand: pd.Series, ref: pd.Series) -> pd.Series:
        bag = lambda x: Counter(zip(*(x[i:] for i in range(n))))
        return pd.Series([sum((bag(list(a)) & bag(list(b))).values()) for a, b in zip(cand, ref)], dtype="int64")

    size = lambda c: F.greatest(F.size(c) - (n - 1), F.lit(0)).cast("long")
    return pairs.select("key", match("cand", "ref").alias("match"), size("cand").alias("cand"), size("ref").alias("ref"))


def lcs(a: list, b: list) -> int:
    """Length of the longest common subsequence, bit-parallel over a."""
    masks: dict = {}
    for i, x in enumerate(a):
        masks[x] = masks.get(x, 0) | 1 << i
    full = row = (1 << len(a)) - 1
    for y in b:
        u = row & masks.get(y, 0)
        row = (row + u) | (row - u)
        row &= full
    return len(a) - row.bit_count()


def lcs_places(ref: list, cand: list) -> set[int]:
    """Places in ref of one longest common subsequence."""
    table = [[0] * (len(cand) + 1) for _ in range(len(ref) + 1)]
    for i, x in enumerate(ref):
        for j, y in enumerate(cand):
            table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
    out, i, j = set(), len(ref), len(cand)
    while i and j:
        if ref[i - 1] == cand[j - 1]:
            out.add(i - 1)
            i, j = i - 1, j - 1
        elif table[i - 1][j] >= table[i][j - 1]:
            i -= 1
        else:
            j -= 1
    return out


def union_lcs(refs: list[list], cands: list[list]) -> int:
    """Summary-level matches: for every reference sentence the union over candidate sentences, clipped by counts."""
    left_ref, left_cand, hits = Counter(w for s in refs for w in s), Counter(w for s in cands for w in s), 0
    for ref in refs:
        places: set[int] = set()
        for cand in cands:
            places |= lcs_places(ref, list(cand))
        for w in (ref[i] for i in sorted(places)):
            if left_ref[w] > 0 and left_cand[w] > 0:
                hits += 1
                left_ref[w] -= 1
                left_cand[w] -= 1
    return hits


def longest(pairs: DataFrame, level: str = "text") -> DataFrame:
    """(key, match, cand, ref) of pairs (key, cand, ref); arrays of tokens, or for level `summary` arrays of token arrays."""
    if level not in ("text", "summary"):
        raise ValueError(f"level must be text or summary, not {level}")

    @F.pandas_udf("long")
    def match(cand: pd.Series, ref: pd.Series) -> pd.Series:
        if level == "text":
            return pd.Series([lcs(list(a), list(b)) for a, b in zip(cand, ref)], dtype="int64")
        return pd.Series([union_lcs([list(s) for s in b], [list(s) for s in a]) for a, b in zip(cand, ref)], dtype="int64")

    size = (lambda c: F.size(c)) if level == "text" else (lambda c: F.size(F.flatten(c)))
    return pairs.select("key", match("cand", "ref").alias("match"), size("cand").cast("long").alias("cand"), size("ref").cast("long").alias("ref"))


def means(counts: DataFrame, measure: str) -> DataFrame:
    """(measure, n, p, r, f): means over keys."""
    rows = counts.select(scored(F.col("match"), F.col("cand"), F.col("ref")).alias("s")).select("s.*")
    return rows.agg(F.count("*").alias("n"), *[F.round(F.coalesce(F.avg(c), F.lit(0.0)), 6).alias(c) for c in ("p", "r", "f")]).withColumn("measure", F.lit(measure))


def pairs(outputs: DataFrame, references: DataFrame) -> DataFrame:
    """(key, cand, ref) token arrays of outputs and references (meeting_id, text); a meeting that lacks one has none there."""
    rows = outputs.select(F.col("meeting_id").alias("key"), words(F.col("text")).alias("cand")).join(references.select(F.col("meeting_id").alias("key"), words(F.col("text")).alias("ref")), "key", "full")
    none = F.array().cast("array<string>")
    return rows.select("key", F.coalesce("cand", none).alias("cand"), F.coalesce("ref", none).alias("ref"))


def sentence_pairs(outputs: DataFrame, references: DataFrame) -> DataFrame:
    """As pairs(), with an array of token arrays a side."""
    cut = lambda: F.transform(sentences(F.col("text")), lambda s: words(s))
    return outputs.select(F.col("meeting_id").alias("key"), cut().alias("cand")).join(references.select(F.col("meeting_id").alias("key"), cut().alias("ref")), "key")


def reference_texts(gold: DataFrame) -> DataFrame:
    """(meeting_id, text): the reference summary of each meeting, one sentence a line."""
    return gold.groupBy("meeting_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("sent_no", "text"))), lambda x: x["text"]), "\n").alias("text"))
