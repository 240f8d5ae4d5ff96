"""Training: distributed AdamW for the boundary head, stride regression, policy gradient, choice of checkpoint."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .backbones import Sliding, bags, window_features
from .runs import arrays
from .windows import View, reach
from ..sources.layout import nest

WIDTH = 8


def boundary_blocks(utts: DataFrame, segments: DataFrame, block: int = 8) -> DataFrame:
    """(meeting_id, block): features of every utterance of each (noisy) segment, and y = 1 at gold_end, the last supporting one; as a block of adamw()."""
    segs = segments.groupBy("meeting_id").agg(F.collect_list(F.struct("seg_start", "seg_end", "gold_end")).alias("segs"))
    rows = arrays(nest(utts)).join(segs, "meeting_id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                sliding = Sliding(bags(list(r.text)), list(r.speaker), block)
                for s in r.segs:
                    left, hi = s["seg_start"], min(s["seg_end"], len(sliding.items) - 1)
                    out.append((r.meeting_id, block_of(sliding.features(left, hi), np.arange(left, hi + 1) == s["gold_end"])))
            yield pd.DataFrame(out, columns=["meeting_id", "block"])

    return rows.mapInPandas(run, "meeting_id string, block binary")


def stride_rows(utts: DataFrame, segments: DataFrame, k: int = 1024) -> DataFrame:
    """(meeting_id, x, y): features of the window at each gold segment's start, and the stride to behind its end in tokens."""
    segs = segments.groupBy("meeting_id").agg(F.collect_list(F.struct("seg_start", "gold_end")).alias("segs"))
    rows = arrays(nest(utts)).join(segs, "meeting_id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                n, start, end = (np.asarray(getattr(r, c), np.int64) for c in ("n_tok", "tok_start", "tok_end"))
                for s in r.segs:
                    left = int(s["seg_start"])
                    hi = reach(left, start, end, k)
                    x = window_features(View(r.meeting_id, np.asarray(r.utt_no), list(r.speaker), list(r.text), n, left, hi, k))
                    out.append((r.meeting_id, list(map(float, x)), float(min(int(end[min(int(s["gold_end"]), hi)]) - int(start[left]), k - 1))))
            yield pd.DataFrame(out, columns=["meeting_id", "x", "y"])

    return rows.mapInPandas(run, "meeting_id string, x array<double>, y double")


def logistic_gradient(w: np.ndarray, x: np.ndarray, y: np.ndarray, positive: float) -> tuple[np.ndarray, float, float]:
    """Sums over rows of gradient, loss and weight; positives weigh `positive`."""
    z = x @ w
    p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
    weight = np.where(y > 0, positive, 1.0)
    loss = -weight * (y * np.log(p + 1e-12) + (1 - y) * np.log(1 - p + 1e-12))
    return x.T @ (weight * (p - y)), float(loss.sum()), float(weight.sum())


def block_of(x: np.ndarray, y: np.ndarray) -> bytes:
    """Rows of features and their y as doubles: one value for many rows, which passes to Python without a conversion of each."""
    return np.column_stack([x, y]).astype("<f8").tobytes()


def packed(rows: DataFrame) -> DataFrame:
    """(block) of rows (x array<double>, y double)."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield pd.DataFrame({"block": [block_of(np.stack(b["x"].to_numpy()), b["y"].to_numpy(dtype=float))]})

    return rows.select("x", "y").mapInPandas(run, "block binary")


def adamw(rows: DataFrame, lr: float = 2e-5, epochs: int = 20, weight_decay: float = 0.01, steps_per_epoch: int = 1, positive: float = 1.0, width: int | None = None) -> DataFrame | list:
    """[(epoch, weights, loss)] of a logistic head on rows (x, y), or on blocks of them of `width` features. Each step is one pass: partial
    gradients per task, one small sum.

    Bias-corrected moments, decay apart from the gradient; betas 0.9 and 0.999, epsilon 1e-8."""
    own = None
    if "block" not in rows.columns:
        width = width or len(rows.first()["x"])
        rows = own = packed(rows).persist()
    if width is None:
        raise ValueError("blocks need a width")
    w, m, v, t, out = np.zeros(width), np.zeros(width), np.zeros(width), 0, []
    spark = rows.sparkSession
    for epoch in range(1, epochs + 1):
        for _ in range(steps_per_epoch):
            shared = spark.sparkContext.broadcast(w)

            def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
                total, loss, weight = np.zeros(width), 0.0, 0.0
                for b in batches:
                    if len(b):
                        x = np.frombuffer(b"".join(b["block"]), "<f8").reshape(-1, width + 1)
                        g, l, n = logistic_gradient(shared.value, x[:, :-1], x[:, -1], positive)
                        total, loss, weight = total + g, loss + l, weight + n
                yield pd.DataFrame({"g": [total.tolist()], "loss": [loss], "weight": [weight]})

            parts = rows.select("block").mapInPandas(run, "g array<double>, loss double, weight double")
            sums = parts.agg(*[F.sum(F.col("g")[i]).alias(f"g{i}") for i in range(width)], F.sum("loss").alias("loss"), F.sum("weight").alias("weight")).first()
            n = max(sums["weight"] or 0.0, 1e-12)
            g, t = np.array([sums[f"g{i}"] or 0.0 for i in range(width)]) / n, t + 1
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            w = w - lr * (m / (1 - 0.9 ** t) / (np.sqrt(v / (1 - 0.999 ** t)) + 1e-8) + weight_decay * w)
            shared.unpersist()
        out.append((epoch, w.tolist(), (sums["loss"] or 0.0) / n))
    if own is not None:
        own.unpersist()
    return out


def best_checkpoint(history: DataFrame, score: str = "val_r2") -> DataFrame:
    """The row of history (epoch, score, ...) with the best score, the earliest of equals."""
    return history.groupBy().agg(F.max_by(F.struct(*history.columns), F.struct(F.col(score), -F.col("epoch"))).alias("best")).select("best.*")


def direct_stride(rows: DataFrame, ridge: float = 1e-3) -> list[float]:
    """Least squares of stride on window features: normal equations summed on the cluster, solved once."""
    width = len(rows.first()["x"])
    cells = [F.sum(F.col("x")[i] * F.col("x")[j]).alias(f"a{i}_{j}") for i in range(width) for j in range(i + 1)] + [F.sum(F.col("x")[i] * F.col("y")).alias(f"b{i}") for i in range(width)]
    s = rows.agg(*cells).first()
    a = np.array([[s[f"a{max(i, j)}_{min(i, j)}"] for j in range(width)] for i in range(width)])
    return solved(np.concatenate([a.ravel(), [s[f"b{i}"] for i in range(width)]]), ridge)


def equations(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The normal equations of least squares as one array: x'x by rows, then x'y."""
    return np.concatenate([(x.T @ x).ravel(), x.T @ y])


def summed(rows: DataFrame, column: str) -> np.ndarray:
    """The sum of an array column, place by place: in each task first."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = sum((np.asarray(x, float) for b in batches for x in b[column]), np.zeros(1))
        if total.size > 1:
            yield pd.DataFrame({"x": [total.tolist()]})

    places = rows.select(column).mapInPandas(run, "x array<double>").select(F.posexplode("x").alias("place", "x"))
    return np.array([r.x for r in places.groupBy("place").agg(F.sum("x").alias("x")).orderBy("place").collect()])


def solved(sums: np.ndarray, ridge: float = 1e-3) -> list[float]:
    """Least squares from normal equations, as direct_stride() has it."""
    width = int(np.sqrt(len(sums)))
    a, b = sums[:width * width].reshape(width, width), sums[width * width:]
    return np.linalg.solve(a + ridge * np.trace(a) / width * np.eye(width), b).tolist()


def policy_gradient(reward: Callable[[list[float], int], tuple[int, float, np.ndarray, np.ndarray]], actions: int = 4, episodes: int = 5, lr: float = 0.5) -> list[tuple[int, list[float], float]]:
    """[(episode, logits after its update, mean reward of the episode)]. reward(logits, episode) runs one episode and gives sums over
    its meetings: their number, rewards r, counts c of the actions taken, and r * c.

    The gradient of a softmax policy is the sum of (one-hot - p) over steps, times reward less the running mean; it follows from the sums."""
    logits, mean, out = np.zeros(actions), None, []
    for e in range(episodes):
        n, total, taken, paid = reward(logits.tolist(), e)
        p = np.exp(logits - logits.max())
        p /= p.sum()
        got = total / n if n else 0.0
        mean = got if mean is None else 0.9 * mean + 0.1 * got
        if n:
            gain = paid - mean * taken
            logits = logits + lr * (gain - p * gain.sum()) / n
        out.append((e, logits.tolist(), got))
    return out
