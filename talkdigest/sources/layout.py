"""Flat and nested layouts of meetings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FIELDS = ["utt_no", "speaker", "text", "n_tok", "tok_start", "tok_end", "char_end"]


def nest(utts: DataFrame, also: tuple[str, ...] = ()) -> DataFrame:
    """One row a meeting: (meeting_id, n_tok, utterances), utterances in order, with further fields. A meeting must fit a task's memory."""
    rows = utts.groupBy("meeting_id").agg(F.sum("n_tok").alias("n_tok"), F.sort_array(F.collect_list(F.struct(*FIELDS, *also))).alias("utterances"))
    return rows.select("meeting_id", "n_tok", "utterances")


def unnest(meetings: DataFrame) -> DataFrame:
    return meetings.select("meeting_id", F.inline("utterances"))


def spans_of(rows: DataFrame, utts: DataFrame, fields: list[str], also: list[str]) -> DataFrame:
    """(meeting_id, *also, u): rows (meeting_id, seg_start, seg_end, *also), with u the utterances (utt_no and fields) from seg_start to
    seg_end in order. Both sides meet by meeting, so an utterance travels once, however many rows hold it."""
    whole = utts.groupBy("meeting_id").agg(F.sort_array(F.collect_list(F.struct("utt_no", *fields))).alias("all"))
    asked = rows.groupBy("meeting_id").agg(F.collect_list(F.struct("seg_start", "seg_end", *also)).alias("asked"))
    first, last = F.col("all")[0]["utt_no"], F.element_at("all", -1)["utt_no"]
    dense = last - first + 1 == F.size("all")  # no gaps or repeated numbers: a span is a slice

    def span(s):
        lo, hi = F.greatest(s["seg_start"], first), F.least(s["seg_end"], last)
        cut = F.slice("all", (lo - first + 1).cast("int"), F.greatest(hi - lo + 1, F.lit(0)).cast("int"))
        return F.when(dense, cut).otherwise(F.filter("all", lambda u: u["utt_no"].between(s["seg_start"], s["seg_end"])))

    out = whole.join(asked, "meeting_id").select("meeting_id", F.inline(F.transform("asked", lambda s: F.struct(*[s[c].alias(c) for c in also], span(s).alias("u")))))
    return out.where(F.size("u") > 0)
