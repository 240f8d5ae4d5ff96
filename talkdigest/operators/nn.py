"""The encoder-decoder architecture in numpy, run in Arrow batches; and its parts as column functions.

Weights are seeded or given: pre-trained ones are not available offline, so these are exact semantics, not quality.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

EPS = 1e-5


def layer_norm(x: np.ndarray, gain=1.0, bias=0.0) -> np.ndarray:
    n = x.shape[-1]  # plain sums: mean() and var() cost more than a short row's arithmetic
    d = x - np.add.reduce(x, -1, keepdims=True) / n
    return d / np.sqrt(np.add.reduce(d * d, -1, keepdims=True) / n + EPS) * gain + bias


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def causal(n: int) -> np.ndarray:
    return np.tril(np.ones((n, n), bool))


def banded(n: int, w: int) -> np.ndarray:
    """Attention to places at most w apart: linear cost for long inputs; w >= n is dense."""
    i = np.arange(n)
    return np.abs(i[:, None] - i[None, :]) <= w


def attention(q: np.ndarray, k: np.ndarray, v: np.ndarray, mask: np.ndarray | None = None) -> np.ndarray:
    scores = q @ k.T / np.sqrt(q.shape[-1])
    if mask is not None:
        scores = np.where(mask, scores, -1e30)
    return softmax(scores) @ v


@dataclass
class Heads:
    q: np.ndarray
    k: np.ndarray
    v: np.ndarray
    o: np.ndarray
    heads: int

    def __call__(self, x: np.ndarray, y: np.ndarray | None = None, mask: np.ndarray | None = None) -> np.ndarray:
        y = x if y is None else y
        cut = lambda z: np.split(z, self.heads, axis=1)
        parts = [attention(a, b, c, mask) for a, b, c in zip(cut(x @ self.q), cut(y @ self.k), cut(y @ self.v))]
        return np.concatenate(parts, axis=1) @ self.o


@dataclass
class FeedForward:
    a: np.ndarray
    b: np.ndarray

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(x @ self.a, 0) @ self.b


def make_heads(rng, d: int, heads: int, scale: float) -> Heads:
    return Heads(*(rng.normal(0, scale, (d, d)) for _ in range(4)), heads)


@dataclass
class EncoderLayer:
    heads: Heads
    forward: FeedForward

    def __call__(self, h: np.ndarray, mask=None) -> np.ndarray:
        h = layer_norm(h + self.heads(h, mask=mask))
        return layer_norm(h + self.forward(h))


@dataclass
class DecoderLayer:
    own: Heads
    cross: Heads
    forward: FeedForward

    def __call__(self, h: np.ndarray, encoded: np.ndarray) -> np.ndarray:
        h = layer_norm(h + self.own(h, mask=causal(len(h))))
        h = layer_norm(h + self.cross(h, encoded))
        return layer_norm(h + self.forward(h))


@dataclass
class Seq2Seq:
    """`layers` encoder and as many decoder layers over a shared embedding; token 0 opens, token 1 ends an output."""

    vocabulary: int
    d: int = 16
    heads: int = 2
    layers: int = 6
    seed: int = 0
    scale: float = 0.2
    embedding: np.ndarray = field(init=False)

    def __post_init__(self):
        rng = np.random.default_rng(self.seed)
        self.embedding = rng.normal(0, 1, (self.vocabulary, self.d))
        forward = lambda: FeedForward(rng.normal(0, self.scale, (self.d, 4 * self.d)), rng.normal(0, self.scale, (4 * self.d, self.d)))
        self.encoder = [EncoderLayer(make_heads(rng, self.d, self.heads, self.scale), forward()) for _ in range(self.layers)]
        self.decoder = [DecoderLayer(make_heads(rng, self.d, self.heads, self.scale), make_heads(rng, self.d, self.heads, self.scale), forward()) for _ in range(self.layers)]

    def placed(self, ids: list[int]) -> np.ndarray:
        at = np.arange(len(ids))[:, None] / 10000 ** (2 * (np.arange(self.d) // 2) / self.d)[None, :]
        return self.embedding[ids] + np.where(np.arange(self.d) % 2 == 0, np.sin(at), np.cos(at))

    def placed_at(self, token: int, place: int) -> np.ndarray:
        """placed() of one token."""
        at = place / 10000 ** (2 * (np.arange(self.d) // 2) / self.d)[None, :]
        return self.embedding[[token]] + np.where(np.arange(self.d) % 2 == 0, np.sin(at), np.cos(at))

    def encode(self, ids: list[int], mask=None) -> np.ndarray:
        h = self.placed(ids)
        for layer in self.encoder:
            h = layer(h, mask)
        return h

    def logits(self, out: list[int], encoded: np.ndarray) -> np.ndarray:
        h = self.placed(out)
        for layer in self.decoder:
            h = layer(h, encoded)
        return h @ self.embedding.T

    def reader(self, encoded: np.ndarray) -> Reader:
        return Reader(self, encoded)

    def decode(self, ids: list[int], most: int = 16, beam: int = 1) -> list[int]:
        """Left to right, token by token; beam 1 is greedy. Ties go to smaller ids."""
        encoded = self.encode(ids)
        open_, done = [(0.0, [0])], []
        for _ in range(most):
            grown = []
            for score, out in open_:
                p = np.log(softmax(self.logits(out, encoded)[-1]) + 1e-30)
                for t in np.argsort(-p, kind="stable")[:beam]:
                    grown.append((score + float(p[t]), out + [int(t)]))
            grown.sort(key=lambda x: (-x[0], x[1]))
            done += [x for x in grown[:beam] if x[1][-1] == 1]
            open_ = [x for x in grown[:beam] if x[1][-1] != 1]
            if not open_:
                break
        best = min(done + open_, key=lambda x: (-x[0], x[1]))[1][1:]
        return best[:-1] if best and best[-1] == 1 else best


class Reader:
    """Decoding token by token over one encoding: keys and values of the encoding and of earlier tokens are kept, and only the last
    token passes the layers. The same logits as Seq2Seq.logits() of all tokens, whose earlier places later ones do not change."""

    def __init__(self, model: Seq2Seq, encoded: np.ndarray, most: int = 8):
        self.model, self.size = model, 0
        split = lambda x, n: x.reshape(len(x), n, -1).transpose(1, 0, 2)  # noqa: E731  heads first
        self.split = split
        self.cross = [(split(encoded @ x.cross.k, x.cross.heads).transpose(0, 2, 1).copy(), split(encoded @ x.cross.v, x.cross.heads)) for x in model.decoder]
        self.own = [[np.zeros((x.own.heads, most, model.d // x.own.heads)) for _ in range(2)] for x in model.decoder]

    def attended(self, q: np.ndarray, keys: np.ndarray, values: np.ndarray) -> np.ndarray:
        """One query of each head over its keys (turned) and values."""
        return (softmax(q @ keys / np.sqrt(q.shape[-1])) @ values).transpose(1, 0, 2).reshape(1, -1)

    def logits(self, token: int) -> np.ndarray:
        """Scores of what follows the tokens so far and this one."""
        m, at = self.model, self.size
        h = m.placed_at(token, at)
        for layer, own, (keys, values) in zip(m.decoder, self.own, self.cross):
            if at == own[0].shape[1]:
                own[:] = [np.concatenate([x, np.zeros_like(x)], axis=1) for x in own]
            own[0][:, at:at + 1], own[1][:, at:at + 1] = self.split(h @ layer.own.k, layer.own.heads), self.split(h @ layer.own.v, layer.own.heads)
            mine = self.attended(self.split(h @ layer.own.q, layer.own.heads), own[0][:, :at + 1].transpose(0, 2, 1), own[1][:, :at + 1])
            h = layer_norm(h + mine @ layer.own.o)
            h = layer_norm(h + self.attended(self.split(h @ layer.cross.q, layer.cross.heads), keys, values) @ layer.cross.o)
            h = layer_norm(h + layer.forward(h))
        self.size += 1
        return (h @ m.embedding.T)[0]


def block_context(blocks: list[np.ndarray]) -> np.ndarray:
    """One vector of many blocks' encodings: mean of the blocks' means, for inputs longer than a window."""
    return np.mean([b.mean(0) for b in blocks], axis=0)


def encode_column(df: DataFrame, model: Seq2Seq, ids: str = "ids", window: int = 1024, band: int | None = None) -> DataFrame:
    """df (key, ids array<int>) with the mean encoding of each row; rows longer than a window are encoded block by block. band: how far
    attention reaches, all of the window by default."""
    mask = lambda n: None if band is None else banded(n, band)
    shared = df.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("array<double>")
    def run(column: pd.Series) -> pd.Series:
        return column.map(lambda x: block_context([shared.value.encode(part, mask(len(part))) for i in range(0, len(x), window) for part in (list(x[i:i + window]),)]).tolist() if len(x) else [])

    return df.withColumn("encoded", run(ids))


def decode_column(df: DataFrame, model: Seq2Seq, ids: str = "ids", window: int = 1024, most: int = 16, beam: int = 1) -> DataFrame:
    """df (key, ids array<int>) with `outputs`: the ids that the model writes of each window of a row, in order."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("array<array<int>>")
    def run(column: pd.Series) -> pd.Series:
        return column.map(lambda x: [shared.value.decode(list(x[i:i + window]), most, beam) for i in range(0, len(x), window)])

    return df.withColumn("outputs", run(ids))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def let(value: Column, body) -> Column:
    """body(value) with value computed once, not for each element that a lambda inside visits."""
    return F.element_at(F.transform(F.array(value), lambda x: body(x)), 1)


def norm_column(x: Column) -> Column:
    """Layer norm of an array column, without gain and bias."""
    mean = F.aggregate(x, F.lit(0.0), lambda s, y: s + y.cast("double")) / F.size(x)
    spread = lambda m: F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, y: s + (y.cast("double") - m) * (y.cast("double") - m)) / F.size(x) + EPS)
    return let(mean, lambda m: let(spread(m), lambda d: F.transform(x, lambda y: (y.cast("double") - m) / d)))


def attended(vectors: DataFrame, window: int = 32) -> DataFrame:
    """(vec_id, other_id, k, weight): single-head self-attention of (vec_id, embedding) inside windows of consecutive ids; k is the other's embedding."""
    place = F.floor(F.col("vec_id") / window)
    a, b = vectors.select(place.alias("win"), "vec_id", F.col("embedding").alias("q")), vectors.select(place.alias("win"), F.col("vec_id").alias("other_id"), F.col("embedding").alias("k"))
    scores = a.join(b, "win").select("vec_id", "other_id", "k", (dot(F.col("q"), F.col("k")) / F.sqrt(F.size("q").cast("double"))).alias("s"))
    w = Window.partitionBy("vec_id")
    rows = scores.withColumn("e", F.exp(F.col("s") - F.max("s").over(w)))
    return rows.select("vec_id", "other_id", "k", (F.col("e") / F.sum("e").over(w)).alias("weight"))


def attention_rows(vectors: DataFrame, window: int = 32) -> DataFrame:
    """(vec_id, other_id, weight): the weights alone."""
    return attended(vectors, window).drop("k")


def attention_output(vectors: DataFrame, window: int = 32) -> DataFrame:
    """(vec_id, place, value): the attention-weighted mean of the embeddings; summed where the weights are, without another shuffle."""
    cells = attended(vectors, window).select("vec_id", "weight", F.posexplode("k").alias("place", "x"))
    return cells.groupBy("vec_id", "place").agg(F.sum(F.col("weight") * F.col("x").cast("double")).alias("value"))


def window_encode(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """mapInPandas body: layer norm of each row's embedding, for plans that stay in Arrow."""
    for b in batches:
        yield b.assign(embedding=[layer_norm(np.asarray(x, float)).tolist() for x in b["embedding"]])
