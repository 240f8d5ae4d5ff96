"""Where a boundary utterance given as text stands in a window, and how far boundaries are from gold."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

WORD = re.compile(r"[^\W_]+")


def normal(text: str) -> str:
    return " ".join((text or "").lower().split())


def token_f1(a: str, b: str) -> float:
    x, y = Counter(WORD.findall(a.lower())), Counter(WORD.findall(b.lower()))
    both = sum((x & y).values())
    return 2 * both / (sum(x.values()) + sum(y.values())) if both else 0.0


def locate(texts: list[str], text: str, least: float = 0.5) -> int | None:
    """Place in texts: the first equal one after normalising, else the earliest of the best token F1, else None."""
    want = normal(text)
    for i, t in enumerate(texts):
        if normal(t) == want:
            return i
    scores = [token_f1(t or "", text or "") for t in texts]
    best = max(scores, default=0.0)
    return scores.index(best) if best >= least else None


def locate_exact(asked: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, left_utt, hi_utt, text, found): the exact rule as a join on normalised text."""
    from ..functions.text import normal as norm

    rows = asked.withColumn("norm", norm(F.col("text"))).join(utts.select("meeting_id", "utt_no", norm(F.col("text")).alias("norm")), ["meeting_id", "norm"], "left")
    inside = F.when(F.col("utt_no").between(F.col("left_utt"), F.col("hi_utt")), F.col("utt_no"))
    return rows.groupBy("meeting_id", "left_utt", "hi_utt", "text").agg(F.min(inside).alias("found"))


def distance(pred: DataFrame, gold: DataFrame, utts: DataFrame, align: str = "teacher", also: tuple[str, ...] = ()) -> DataFrame:
    """(*also, meeting_id, snip_no, pred_utt, gold_utt, utterances, characters) of each prediction.

    teacher: pred and gold share (meeting_id, snip_no); free: a prediction is held against the nearest gold boundary,
    found by as-of windows from both sides. pred: pred_utt; gold: gold_utt. also: further columns of pred (teacher)."""
    if align not in ("teacher", "free"):
        raise ValueError(f"align must be teacher or free, not {align}")
    if align == "teacher":
        rows = pred.join(gold, ["meeting_id", "snip_no"])
    else:
        both = gold.select("meeting_id", F.col("gold_utt").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("snip_no")).unionByName(pred.select("meeting_id", F.col("pred_utt").alias("at"), F.lit(1).alias("kind"), "snip_no"))
        is_gold = F.when(F.col("kind") == 0, F.col("at"))
        order = Window.partitionBy("meeting_id").orderBy("at", "kind")
        down = F.last(is_gold, True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))
        up = F.first(is_gold, True).over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
        rows = both.withColumn("down", down).withColumn("up", up).where("kind = 1")
        near = F.when(F.col("up").isNull() | (F.col("at") - F.col("down") <= F.col("up") - F.col("at")), F.col("down")).otherwise(F.col("up"))
        rows = rows.select("meeting_id", "snip_no", F.col("at").alias("pred_utt"), near.alias("gold_utt")).where("gold_utt is not null")
    ends = utts.select("meeting_id", "utt_no", "char_end")
    rows = rows.join(ends.select("meeting_id", F.col("utt_no").alias("pred_utt"), F.col("char_end").alias("pred_char")), ["meeting_id", "pred_utt"]).join(ends.select("meeting_id", F.col("utt_no").alias("gold_utt"), F.col("char_end").alias("gold_char")), ["meeting_id", "gold_utt"])
    return rows.select(*also, "meeting_id", "snip_no", "pred_utt", "gold_utt", F.abs(F.col("pred_utt") - F.col("gold_utt")).alias("utterances"), F.abs(F.col("pred_char") - F.col("gold_char")).alias("characters"))


def summary(distances: DataFrame, within: int = 3, by: tuple[str, ...] = ()) -> DataFrame:
    """(*by, n, utterances, characters, hit_rate): means and the share of predictions at most `within` utterances off."""
    return distances.groupBy(*by).agg(F.count("*").alias("n"), F.round(F.avg("utterances"), 6).alias("utterances"), F.round(F.avg("characters"), 6).alias("characters"), F.round(F.avg((F.col("utterances") <= within).cast("double")), 6).alias("hit_rate"))
