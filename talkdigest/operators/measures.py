"""Measures beside ROUGE: factual support, segmentation quality, cost of a run, support recall."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import grams, words


def consistency(outputs: DataFrame, utts: DataFrame, n: int = 2) -> DataFrame:
    """(meeting_id, grams, supported) of outputs (meeting_id, text): distinct n-grams, and those that occur inside an utterance of the source."""
    mine = outputs.select("meeting_id", F.explode(F.transform(F.transform(F.split("text", r"[.!?\n]+"), lambda s: words(s)), lambda t: grams(t, n))).alias("g")).select("meeting_id", F.explode("g").alias("gram")).distinct()
    source = utts.select("meeting_id", F.explode(grams(F.col("tokens"), n)).alias("gram")).distinct().withColumn("hit", F.lit(1))
    return mine.join(source, ["meeting_id", "gram"], "left").groupBy("meeting_id").agg(F.count("*").alias("grams"), F.count("hit").alias("supported"))


def window_consistency(steps: DataFrame, utts: DataFrame, n: int = 2) -> DataFrame:
    """(meeting_id, step, grams, supported): each snippet against its own window only. Utterances left_utt..hi_utt."""
    mine = steps.select("meeting_id", "step", F.explode(F.array_distinct(F.flatten(F.transform(F.transform(F.split("snippet", r"[.!?\n]+"), lambda s: words(s)), lambda t: grams(t, n))))).alias("gram"))
    flat = steps.select("meeting_id", "step", F.explode(F.sequence("left_utt", "hi_utt")).alias("utt_no")).join(utts.select("meeting_id", "utt_no", "tokens"), ["meeting_id", "utt_no"])
    source = flat.select("meeting_id", "step", F.explode(grams(F.col("tokens"), n)).alias("gram")).distinct().withColumn("hit", F.lit(1))
    return mine.join(source, ["meeting_id", "step", "gram"], "left").groupBy("meeting_id", "step").agg(F.count("*").alias("grams"), F.count("hit").alias("supported"))


def own_window_consistency(steps: DataFrame, n: int = 2) -> DataFrame:
    """As window_consistency(), of steps that carry their source (runs.dynamic_with_source): row by row, without a shuffle."""
    of_lines = lambda lines, tokens: F.array_distinct(F.flatten(F.transform(F.transform(lines, tokens), lambda t: grams(t, n))))  # noqa: E731  a line is cut once
    mine = of_lines(F.split("snippet", r"[.!?\n]+"), lambda s: words(s))
    rows = steps.select("meeting_id", "step", mine.alias("mine"), of_lines(F.split("source", "\n"), lambda s: F.array_remove(F.split(s, " "), "")).alias("theirs"))
    rows = rows.select("meeting_id", "step", F.size("mine").cast("long").alias("grams"), F.size(F.array_intersect("mine", "theirs")).cast("long").alias("supported"))
    return rows.where("grams > 0")


def consistency_by_row(outputs: DataFrame, utts: DataFrame, n: int = 2) -> DataFrame:
    """As consistency(), of outputs with a row a meeting: a meeting's utterances meet its output, and n-grams are no rows of a shuffle."""
    source = utts.groupBy("meeting_id").agg(F.array_join(F.collect_list(F.array_join("tokens", " ")), "\n").alias("source"))
    rows = outputs.join(source, "meeting_id", "left").select("meeting_id", F.lit(0).alias("step"), F.col("text").alias("snippet"), F.coalesce("source", F.lit("")).alias("source"))
    return own_window_consistency(rows, n).drop("step")


def mention_support(outputs: DataFrame, utts: DataFrame, pattern: str) -> DataFrame:
    """(meeting_id, mentions, supported): distinct matches of pattern (names, numbers) in the output that the source has too."""
    mine = outputs.select("meeting_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(f"({pattern})"), F.lit(1))).alias("m")).distinct()
    source = utts.select("meeting_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(f"({pattern})"), F.lit(1))).alias("m")).distinct().withColumn("hit", F.lit(1))
    return mine.join(source, ["meeting_id", "m"], "left").groupBy("meeting_id").agg(F.count("*").alias("mentions"), F.count("hit").alias("supported"))


def support_recall(steps: DataFrame, links: DataFrame) -> DataFrame:
    """(supported, seen, recall): share of supporting utterances that lie in what the snippets were made of (left_utt..boundary_utt)."""
    flat = links.where("support is not null").select("meeting_id", F.explode("support").alias("utt_no")).distinct()
    seen = steps.select("meeting_id", F.explode(F.sequence("left_utt", "boundary_utt")).alias("utt_no")).distinct().withColumn("hit", F.lit(1))
    return flat.join(seen, ["meeting_id", "utt_no"], "left").agg(F.count("*").alias("supported"), F.count("hit").alias("seen"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def cost(steps: DataFrame) -> DataFrame:
    """(steps, tokens, again, attention): windows, tokens encoded, tokens encoded more than once, sum of squared lengths."""
    length = F.col("i_right") - F.col("i_left")
    rows = steps.groupBy("meeting_id").agg(F.count("*").alias("steps"), F.sum(length).alias("tokens"), (F.max("i_right") - F.min("i_left")).alias("reach"), F.sum(length * length).alias("attention"))
    return rows.agg(F.sum("steps").alias("steps"), F.sum("tokens").alias("tokens"), F.sum(F.greatest(F.lit(0), F.col("tokens") - F.col("reach"))).alias("again"), F.sum("attention").alias("attention"))


def pk(ref: np.ndarray, hyp: np.ndarray, width: int) -> float:
    """Share of places where the two segmentations disagree on whether i and i + width lie in one segment; arrays of 0/1 cuts after each unit."""
    if len(ref) <= width:
        return 0.0
    a, b = np.r_[0, np.cumsum(ref)], np.r_[0, np.cumsum(hyp)]
    return float(np.mean((a[width:-1] == a[:-1 - width]) != (b[width:-1] == b[:-1 - width])))


def window_diff(ref: np.ndarray, hyp: np.ndarray, width: int) -> float:
    """As pk, on whether the numbers of cuts differ."""
    if len(ref) <= width:
        return 0.0
    a, b = np.r_[0, np.cumsum(ref)], np.r_[0, np.cumsum(hyp)]
    return float(np.mean((a[width:-1] - a[:-1 - width]) != (b[width:-1] - b[:-1 - width])))


def segmentation(gold: DataFrame, pred: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, pk, window_diff) of cuts (meeting_id, utt_no), a cut after the utterance; the width is half the mean gold segment."""
    n = utts.groupBy("meeting_id").agg(F.max("utt_no").alias("last_utt"))
    side = lambda df, name: df.groupBy("meeting_id").agg(F.collect_set("utt_no").alias(name))
    rows = n.join(side(gold, "gold"), "meeting_id", "left").join(side(pred, "pred"), "meeting_id", "left")

    @F.pandas_udf("pk double, window_diff double")
    def score(last: pd.Series, g: pd.Series, p: pd.Series) -> pd.DataFrame:
        out = []
        for n_, a, b in zip(last, g, p):
            x, y = np.zeros(n_ + 1, int), np.zeros(n_ + 1, int)
            x[[i for i in (a if a is not None else []) if i < n_]] = 1
            y[[i for i in (b if b is not None else []) if i < n_]] = 1
            width = max(1, round((n_ + 1) / (x.sum() + 1) / 2))
            out.append((pk(x, y, width), window_diff(x, y, width)))
        return pd.DataFrame(out, columns=["pk", "window_diff"])

    return rows.select("meeting_id", score("last_utt", "gold", "pred").alias("s")).select("meeting_id", "s.*")
