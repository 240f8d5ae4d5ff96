"""Mixing sources to target weights by pivotal dependent rounding.

A source's target fixes the copies x = target / source size that each of its documents should be taken; whole
copies are taken outright, the fractions are rounded dependently: two documents meet, and mass (in words) moves
from one to the other, at random but fair, until one of the fractions is 0 or 1. Moving words, not probability,
leaves the expected words of a source unchanged at every step, so what is taken differs from the target by less
than one document. Buckets of a source are reduced to one residual fraction each, then the residuals of many
buckets meet in the next level of the tree, and the last one of a source is drawn by itself.

Random numbers come from a seeded hash of the document, so reruns and retried tasks agree.

Defined results: null text is of size 0 and takes 0 words; a null source is a source of its own, after the
others; repeated rows are documents of their own; all sizes 0: all targets 0; empty table: no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import kept, small_or_plain, word_count

MOST = 3
FAN = 64
ROWS_A_BUCKET = 200_000
ROW = "row_key long, pivot_source string, size long, fraction double, draw double"


def targets(sizes: DataFrame, weights=(1, 2, 3), most: int = MOST) -> DataFrame:
    """(source, source_size, target) of a table (source, source_size), one row a source.

    Resharing the excess by weight until no source is above its limit ends at min(limit, level * weight) with one
    level for all; sorted by limit / weight, the level follows from running sums."""
    listed = Window.orderBy(F.asc_nulls_last("source"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(listed) - 1, F.lit(len(weights))) + 1).cast("int"))
    rows = sizes.select("source", F.col("source_size").cast("long").alias("source_size")).withColumn("weight", w).withColumn("limit", most * F.col("source_size").cast("double"))
    order = Window.orderBy(F.col("limit") / F.col("weight"), F.asc_nulls_last("source"))
    before, rest = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = rows.withColumn("total", F.sum("source_size").over(everything)) \
        .withColumn("level", (F.col("total") - F.coalesce(F.sum("limit").over(before), F.lit(0.0))) / F.sum("weight").over(rest))
    rows = rows.withColumn("level", F.max(F.when(F.col("level") * F.col("weight") <= F.col("limit"), F.col("level"))).over(everything))
    return rows.select("source", "source_size", F.least("limit", F.coalesce(F.col("level"), F.lit(0.0)) * F.col("weight")).alias("target"))


def pivot(sizes: np.ndarray, fractions: np.ndarray, draws: np.ndarray) -> tuple[np.ndarray, int]:
    """Rounds all fractions but one at most: (values, index of the residual or -1). sum(values * sizes) stays."""
    out, held = fractions.copy(), -1
    for i in range(len(out)):
        p = out[i]
        if p <= 1e-12 or p >= 1 - 1e-12:
            out[i] = round(p)
            continue
        if held < 0:
            held = i
            continue
        q, a, b = out[held], float(sizes[held]), float(sizes[i])
        up, down = min((1 - q) * a, p * b), min(q * a, (1 - p) * b)  # words that can move to the held one, and from it
        moved = up if draws[i] * (up + down) < down else -down
        q, p = q + moved / a, p - moved / b
        q, p = (round(x) if min(abs(x), abs(x - 1)) < 1e-9 else x for x in (q, p))
        out[held], out[i] = q, p
        held = held if 0 < q < 1 else i if 0 < p < 1 else -1
    return out, held


def _level(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Batches come sorted by group; the residual of a group that goes on in the next batch is carried over."""
    carry = None
    for batch in batches:
        rows = batch if carry is None else pd.concat([carry, batch], ignore_index=True)
        carry = None
        if not len(rows):
            continue
        group = rows["bucket_key"].to_numpy()
        edges = np.flatnonzero(np.r_[True, group[1:] != group[:-1], True])
        value, residual = rows["fraction"].to_numpy(dtype=float).copy(), []
        sizes, draws = rows["size"].to_numpy(dtype=float), rows["draw"].to_numpy(dtype=float)
        for a, b in zip(edges[:-1], edges[1:]):
            value[a:b], k = pivot(sizes[a:b], value[a:b], draws[a:b])
            if k >= 0:
                residual.append(a + k)
        rows = rows.assign(fraction=value)
        if residual and residual[-1] >= edges[-2]:  # may meet rows of the next batch
            carry = rows.iloc[[residual[-1]]]
            rows = rows.drop(index=rows.index[residual[-1]])
        yield rows.drop(columns="bucket_key")
    if carry is not None:
        yield carry.drop(columns="bucket_key")


def levels(n: int) -> list[int]:
    """Buckets of a source at each level of the tree over n rows: leaves of about ROWS_A_BUCKET rows at most, then FAN to one."""
    out = [1, FAN, FAN ** 2]
    while n > ROWS_A_BUCKET * out[-1]:
        out.append(FAN * out[-1])
    return out[::-1]


def rounded(rows: DataFrame, n: int) -> DataFrame:
    """(row_key, up 0/1) of n rows at most (row_key, pivot_source, size, fraction, draw) with fractions in (0, 1) and sizes over 0."""
    done, tree = None, levels(n)
    for buckets in tree:
        key = F.xxhash64("pivot_source", F.pmod(F.xxhash64(F.lit("level"), "row_key"), F.lit(tree[0])) % buckets)
        out = rows.withColumn("bucket_key", key).repartition("bucket_key").sortWithinPartitions("bucket_key", "row_key").mapInPandas(_level, ROW)
        out = kept(out)
        whole = out.where("fraction <= 0 or fraction >= 1").select("row_key", F.col("fraction").cast("int").alias("up"))
        done = whole if done is None else done.unionByName(whole)
        rows = out.where("fraction > 0 and fraction < 1")
    last = rows.select("row_key", (F.pmod(F.xxhash64(F.lit("last"), "row_key"), F.lit(1 << 30)) / float(1 << 30) < F.col("fraction")).cast("int").alias("up"))
    return done.unionByName(last)


def _content_key(seed: int):
    return F.xxhash64(F.lit(seed), "doc_id", "source", "text")


def mixed(documents: DataFrame, weights=(1, 2, 3), most: int = MOST, seed: int = 7) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken, content_key, repeat), one row a document."""
    docs = documents.select("doc_id", "source", word_count(F.col("text")).alias("size"), _content_key(seed).alias("content_key"))
    docs = docs.withColumn("repeat", F.row_number().over(Window.partitionBy("content_key").orderBy("doc_id")))
    docs = kept(docs.withColumn("row_key", F.xxhash64("content_key", "repeat")))
    goal = kept(targets(docs.groupBy("source").agg(F.sum("size").alias("source_size")), weights, most).withColumnRenamed("source", "goal_source"))
    docs = docs.join(small_or_plain(goal, 100_000), F.col("source").eqNullSafe(F.col("goal_source"))).drop("goal_source")
    copies = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    docs = docs.withColumn("whole", F.floor(copies)).withColumn("fraction", copies - F.floor(copies))
    open_ = docs.where("size > 0 and fraction > 0").select("row_key", F.coalesce(F.concat(F.lit("s"), "source"), F.lit("null")).alias("pivot_source"), "size", "fraction",
                                                          (F.pmod(F.xxhash64(F.lit("draw"), "row_key"), F.lit(1 << 30)) / float(1 << 30)).alias("draw"))
    docs = docs.join(rounded(open_, docs.count()), "row_key", "left")
    docs = docs.withColumn("copies", F.col("whole") + F.coalesce(F.col("up"), F.lit(0)))
    return docs.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), "content_key", "repeat")


def mixture(documents: DataFrame, seed: int = 7, **options) -> DataFrame:
    """The mix itself: every row of documents as often as it is taken; documents of size 0 are not taken."""
    keep = [F.col(f"`{c}`") for c in documents.columns]
    rows = documents.select(F.struct(*keep).alias("mix_row"), _content_key(seed).alias("mix_key"))
    rows = rows.withColumn("mix_repeat", F.row_number().over(Window.partitionBy("mix_key").orderBy(F.xxhash64("mix_row"))))
    taken = mixed(documents, seed=seed, **options).where("copies > 0 and size > 0").select(F.col("content_key").alias("mix_key"), F.col("repeat").alias("mix_repeat"), "copies")
    return rows.join(taken, ["mix_key", "mix_repeat"]).select("mix_row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select("mix_row.*")
