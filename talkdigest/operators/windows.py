"""Windows over transcripts and the rules that move them."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import positive


def count_windows(n, size: int, stride: int):
    """Windows at 0, stride, 2 * stride, .. until n tokens are covered; one for an empty transcript."""
    return F.greatest(F.lit(1).cast("long"), F.ceil((n - size) / stride).cast("long") + 1)


def fixed(utts: DataFrame, size: int = 1024, stride: int | None = None) -> DataFrame:
    """utts with window, win_from, win_to: the tokens of an utterance that lie in each window, as places in the utterance.

    The windows of an utterance follow from its positions by division: no range join. An utterance without tokens
    belongs to the windows that hold its position."""
    stride = stride or size
    positive(size=size, stride=stride)
    n = F.max("tok_end").over(Window.partitionBy("meeting_id"))
    rows = utts.withColumn("n_windows", count_windows(n, size, stride))
    at, to = F.col("tok_start"), F.greatest(F.col("tok_end"), F.col("tok_start") + 1)
    last = F.col("n_windows") - 1
    lo = F.least(last, F.greatest(F.lit(0).cast("long"), F.floor((at - size) / stride).cast("long") + 1))
    hi = F.least(last, F.floor((to - 1) / stride).cast("long"))
    rows = rows.withColumn("window", F.explode(F.sequence(lo, F.greatest(lo, hi))))
    begin = F.col("window") * stride
    return rows.withColumn("win_from", F.greatest(F.lit(0).cast("long"), begin - at)).withColumn("win_to", F.greatest(F.lit(0).cast("long"), F.least(F.col("n_tok"), begin + size - at))).drop("n_windows")


@dataclass
class View:
    """What a backbone sees: utterances left..hi of a meeting; numbers are places in the meeting's arrays."""

    meeting_id: str
    utt_nos: np.ndarray
    speakers: list
    texts: list
    n_tok: np.ndarray
    left: int
    hi: int
    k: int

    def __len__(self):
        return self.hi - self.left + 1


def reach(left: int, tok_start: np.ndarray, tok_end: np.ndarray, k: int) -> int:
    """Last utterance of a window of k tokens from `left`: whole utterances only, at least one."""
    return max(left, int(np.searchsorted(tok_end, tok_start[left] + k, "right")) - 1)


def advance(left: int, boundary: int | None, hi: int, resume: str = "after") -> tuple[int, int]:
    """(boundary, next left). The boundary is held inside the window; without one the window is used up. Always moves on."""
    b = hi if boundary is None else min(max(boundary, left), hi)
    return b, b + 1 if resume == "after" else max(b, left + 1)
