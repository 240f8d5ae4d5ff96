"""Exact top-k search by inner product over tiles of queries and shards.

Vectors are packed into dense tiles; every tile of queries meets every shard of candidates in one matrix
product, which keeps only the k best of each tile; per-query lists are merged in a tree of FAN_IN shards a node.

Defined results: a vector that is null, or holds a null or non-finite component, takes no part; vectors of
another length than the tile's have no common inner product and meet only vectors of their own length; ties
go to the smaller id; repeated rows are separate candidates, all rows with the query's own id are left out; of
several query rows with one id, the one with the least vector is the query; an empty table gives an empty result; further
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TILE_ROWS = 4096
QUERY_ROWS = 1024
FAN_IN = 8
TILE = "tile_shard long, dim int, ids binary, grid binary"


def quantised(vectors: DataFrame, scale: int = 64) -> DataFrame:
    """(vec_id, grid array<long>): floor(scale * component), whole vectors only."""
    x = F.col("embedding")
    whole = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) != float("inf")))
    return vectors.select("vec_id", x.alias("embedding")).where(x.isNotNull() & whole & F.col("vec_id").isNotNull()).select(
        F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale).cast("long")).alias("grid"))


KINDS = (np.int16, np.int32, np.int64)


def narrowed(grid: np.ndarray) -> np.ndarray:
    """In the narrowest of KINDS that holds all values."""
    low, high = int(grid.min(initial=0)), int(grid.max(initial=0))
    return grid.astype(next(k for k in KINDS if np.iinfo(k).min <= low and high <= np.iinfo(k).max))


def widened(data: bytes, rows: int, dim: int) -> np.ndarray:
    """What narrowed() wrote; the kind follows from the number of bytes."""
    kind = {np.dtype(k).itemsize: k for k in KINDS}[len(data) // max(1, rows * dim) or 8]
    return np.frombuffer(data, kind).reshape(rows, dim).astype(np.int64)


def _packer(most: int):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}

        def tile(key, rows):
            return pa.RecordBatch.from_pydict({
                "tile_shard": pa.array([key[0]], pa.int64()), "dim": pa.array([key[1]], pa.int32()),
                "ids": pa.array([np.concatenate([r[0] for r in rows]).tobytes()], pa.binary()),
                "grid": pa.array([narrowed(np.concatenate([r[1] for r in rows])).tobytes()], pa.binary())})

        for batch in batches:
            ids, shards = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("vec_id", "tile_shard"))
            grid = batch.column(batch.schema.get_field_index("grid"))
            sizes = np.diff(grid.offsets.to_numpy())
            flat, starts = grid.values.to_numpy(zero_copy_only=False), grid.offsets.to_numpy()
            for i in range(len(ids)):
                rows = held.setdefault((int(shards[i]), int(sizes[i])), [])
                rows.append((ids[i:i + 1].astype(np.int64), flat[starts[i]:starts[i + 1]].astype(np.int64)))
                if len(rows) >= most:
                    yield tile((int(shards[i]), int(sizes[i])), held.pop((int(shards[i]), int(sizes[i]))))
        for key, rows in held.items():
            yield tile(key, rows)

    return pack


def best_of_tile(q_ids, q, c_ids, c, k):
    """Per query the k best candidates of the tile: (query ids, candidate ids, scores), ties to smaller ids."""
    order = np.argsort(c_ids, kind="stable")
    c_ids, c = c_ids[order], c[order]
    most = float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) * max(1, q.shape[1])
    if most < 2 ** 24:
        scores = (q.astype(np.float32) @ c.astype(np.float32).T).astype(np.int64)
    elif most < 2 ** 53:
        scores = (q.astype(np.float64) @ c.astype(np.float64).T).astype(np.int64)
    else:
        scores = q @ c.T
    n = len(c_ids)
    take = min(n, k + int((q_ids[:, None] == c_ids[None, :]).sum(axis=1).max(initial=0)))
    if most < 2 ** 48:  # one number carries the score and, below it, the place: no ties are left
        keyed = scores * TILE_ROWS + (n - 1 - np.arange(n))[None, :]
        top = np.argpartition(keyed, n - take, axis=1)[:, n - take:]
    else:
        top = np.argsort(-scores, axis=1, kind="stable")[:, :take]
    rows = np.repeat(np.arange(len(q_ids)), take)
    cols = top.ravel()
    keep = q_ids[rows] != c_ids[cols]
    return q_ids[rows[keep]], c_ids[cols[keep]], scores[rows[keep], cols[keep]]


def _matcher(k: int):
    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                q_ids, c_ids = np.frombuffer(row["q_ids"], np.int64), np.frombuffer(row["ids"], np.int64)
                q, c = widened(row["q_grid"], len(q_ids), row["dim"]), widened(row["grid"], len(c_ids), row["dim"])
                a, b, s = best_of_tile(q_ids, q, c_ids, c, k)
                yield pa.RecordBatch.from_pydict({"query_id": a, "vec_id": b, "score": s, "tile_shard": np.full(len(a), row["tile_shard"])})

    return match


def top_k(queries: DataFrame, candidates: DataFrame, k: int = 20, rows_per_shard: int = 8192) -> DataFrame:
    """(query_id, rank, vec_id, score). queries and candidates: (vec_id long, grid array<long>)."""
    shards = max(1, -(-candidates.count() // rows_per_shard))
    tiles = candidates.select("vec_id", "grid", F.pmod(F.xxhash64("vec_id", "grid"), F.lit(shards)).cast("long").alias("tile_shard")) \
        .repartition("tile_shard").mapInArrow(_packer(TILE_ROWS), TILE)
    queries = queries.groupBy("vec_id").agg(F.min("grid").alias("grid"))
    asked = queries.select("vec_id", "grid", F.lit(0).cast("long").alias("tile_shard")).mapInArrow(_packer(QUERY_ROWS), TILE)
    asked = asked.select("dim", F.col("ids").alias("q_ids"), F.col("grid").alias("q_grid"),
                         F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))).alias("tile_shard"))
    pairs = tiles.join(asked, ["tile_shard", "dim"]).repartition(F.xxhash64("q_ids", "ids"))
    lists = pairs.mapInArrow(_matcher(k), "query_id long, vec_id long, score long, tile_shard long")

    def merged(df, *keys):
        best = Window.partitionBy(*keys).orderBy(F.desc("score"), "vec_id")
        return df.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)

    nodes = shards
    while nodes > FAN_IN:
        nodes = -(-nodes // FAN_IN)
        lists = merged(lists.withColumn("tile_shard", F.expr(f"tile_shard div {FAN_IN}")), "query_id", "tile_shard").drop("rank")
    return merged(lists, "query_id").select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
