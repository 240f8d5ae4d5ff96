"""Summary conversion: sentences with support become snippets, samples and training targets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import positive
from ..sources.layout import spans_of
from .analysis import by_occurrence

SEP = "[SEP]"


def grouped(spans: DataFrame, min_overlap: int = 1, chain: bool = True) -> DataFrame:
    """spans with snip_no: neighbours in order of occurrence share one if their segments overlap enough.

    chain: compare with the furthest end so far, else with the predecessor's end only. One shuffle, no pairs."""
    positive(min_overlap=min_overlap)
    order = by_occurrence()
    so_far = F.max("seg_end").over(order.rowsBetween(Window.unboundedPreceding, -1)) if chain else F.lag("seg_end").over(order)
    rows = spans.withColumn("reach", so_far)
    shared = F.least("reach", "seg_end") - F.col("seg_start") + 1
    fresh = F.col("reach").isNull() | (shared < F.least(F.lit(min_overlap), F.col("seg_end") - F.col("seg_start") + 1))
    return rows.withColumn("fresh", fresh.cast("long")).withColumn("snip_no", F.sum("fresh").over(order) - 1).drop("reach", "fresh")


def merge(spans: DataFrame, min_overlap: int = 1, chain: bool = True) -> DataFrame:
    """(meeting_id, snip_no, seg_start, seg_end, sent_nos), sentences in order of occurrence."""
    rows = grouped(spans, min_overlap, chain)
    return rows.groupBy("meeting_id", "snip_no").agg(F.min("seg_start").alias("seg_start"), F.max("seg_end").alias("seg_end"),
                                                     F.transform(F.sort_array(F.collect_list(F.struct("seg_start", "seg_end", "sent_no"))), lambda x: x["sent_no"]).alias("sent_nos"))


def snippet_words(snippets: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, snip_no, words): the distinct words of each snippet's segment."""
    rows = spans_of(snippets, utts, ["tokens"], ["snip_no"])
    return rows.select("meeting_id", "snip_no", F.array_distinct(F.flatten(F.transform("u", lambda x: x["tokens"]))).alias("words"))


def place_orphans(gold: DataFrame, spans_grouped: DataFrame, snippets: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, sent_no, snip_no, overlap) of unannotated sentences.

    The snippet whose segment shares most distinct words, the earliest of equals; without any shared word, the snippet of
    the annotated sentence before it, else the first."""
    orphans = gold.where("support is null").groupBy("meeting_id").agg(F.collect_list(F.struct("sent_no", "tokens")).alias("orphans"))
    # a snippet's words meet the meeting's orphans as sets, row by row: no word is a row of its own
    shared = snippet_words(snippets, utts).join(orphans, "meeting_id")
    shared = shared.select("meeting_id", "snip_no", F.inline(F.transform("orphans", lambda o: F.struct(o["sent_no"].alias("sent_no"), F.size(F.array_intersect(o["tokens"], "words")).cast("long").alias("overlap"))))).where("overlap > 0")
    best = shared.groupBy("meeting_id", "sent_no").agg(F.max(F.struct("overlap", (-F.col("snip_no")).alias("back"))).alias("best"))
    order = Window.partitionBy("meeting_id").orderBy("sent_no").rowsBetween(Window.unboundedPreceding, -1)
    before = gold.select("meeting_id", "sent_no", F.col("support").isNull().alias("orphan")).join(spans_grouped.select("meeting_id", "sent_no", F.col("snip_no").alias("own")), ["meeting_id", "sent_no"], "left").withColumn("previous", F.last("own", True).over(order)).where("orphan")
    rows = before.join(best, ["meeting_id", "sent_no"], "left")
    return rows.select("meeting_id", "sent_no", F.coalesce(-F.col("best.back"), "previous", F.lit(0)).cast("long").alias("snip_no"), F.coalesce("best.overlap", F.lit(0)).cast("long").alias("overlap"))


def membership(spans_grouped: DataFrame, orphans: DataFrame) -> DataFrame:
    """(meeting_id, sent_no, snip_no, place): annotated sentences by occurrence, then orphans by number."""
    placed = spans_grouped.withColumn("place", F.row_number().over(by_occurrence()).cast("long"))
    return placed.select("meeting_id", "sent_no", "snip_no", "place").unionByName(orphans.select("meeting_id", "sent_no", "snip_no", (F.col("sent_no") + 1_000_000).alias("place")))


def assembled(gold: DataFrame, members: DataFrame, snippets: DataFrame) -> DataFrame:
    """(meeting_id, snip_no, sent_nos, text, seg_start, seg_end): snippets with the texts of all their sentences."""
    rows = members.join(gold.select("meeting_id", "sent_no", "text"), ["meeting_id", "sent_no"])
    rows = rows.groupBy("meeting_id", "snip_no").agg(F.sort_array(F.collect_list(F.struct("place", "sent_no", "text"))).alias("s"))
    rows = rows.select("meeting_id", "snip_no", F.transform("s", lambda x: x["sent_no"]).alias("sent_nos"), F.array_join(F.transform("s", lambda x: x["text"]), " ").alias("text"))
    return rows.join(snippets.select("meeting_id", "snip_no", "seg_start", "seg_end"), ["meeting_id", "snip_no"], "left")


def converted(utts: DataFrame, gold: DataFrame, spans: DataFrame, min_overlap: int = 1, chain: bool = True) -> DataFrame:
    """All conversion steps up to snippets with text."""
    marked = grouped(spans, min_overlap, chain)
    snippets = merge(spans, min_overlap, chain)
    return assembled(gold, membership(marked, place_orphans(gold, marked, snippets, utts)), snippets)


def span_text(rows: DataFrame, utts: DataFrame, keys: list[str]) -> DataFrame:
    """rows with `source`: the texts of utterances seg_start..seg_end."""
    spans = spans_of(rows, utts, ["text"], [k for k in keys if k != "meeting_id"])
    text = spans.select(*keys, F.array_join(F.transform("u", lambda x: x["text"]), " ").alias("source"))
    return rows.join(text, keys, "left")


def add_noise(snippets: DataFrame, utts: DataFrame, splits: DataFrame, lo: int = 6, hi: int = 14, side: str = "both", seed: int = 0) -> DataFrame:
    """snippets with meeting_no, split, noise and widened seg_start/seg_end in the training split, clipped to the transcript."""
    positive(lo=lo, hi=hi)
    if side not in ("both", "left", "right"):
        raise ValueError(f"side must be both, left or right, not {side}")
    last = utts.groupBy("meeting_id").agg(F.max("utt_no").alias("last_utt"))
    count = (F.col("meeting_no") * 7919 + F.col("snip_no") * 104729 + seed) % (hi - lo + 1) + lo
    rows = snippets.join(splits, "meeting_id").join(last, "meeting_id").withColumn("noise", F.when(F.col("split") == "train", count).otherwise(F.lit(0)).cast("long"))
    left = {"both": F.floor(F.col("noise") / 2), "left": F.col("noise"), "right": F.lit(0)}[side]
    return rows.withColumn("gold_start", F.col("seg_start")).withColumn("gold_end", F.col("seg_end")).withColumn("seg_start", F.greatest(F.lit(0).cast("long"), F.col("gold_start") - left)).withColumn("seg_end", F.least("last_utt", F.col("gold_end") + F.col("noise") - left)).drop("last_utt")


def samples(snippets: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, snip_no, source, target): a snippet's segment, and its text with the last supporting utterance after the separator.

    snippets may carry gold_end (after add_noise); else seg_end is the last supporting utterance."""
    end = "gold_end" if "gold_end" in snippets.columns else "seg_end"
    rows = span_text(snippets.where("seg_start is not null"), utts, ["meeting_id", "snip_no"])
    last = utts.select("meeting_id", F.col("utt_no").alias(end), F.col("text").alias("last_text"))
    return target(rows.join(last, ["meeting_id", end]))


def target(rows: DataFrame, sep: str = SEP) -> DataFrame:
    return rows.withColumn("target", F.concat_ws(f" {sep} ", "text", "last_text"))


def parse_target(column, sep: str = SEP):
    """(snippet, utterance) split at the last separator."""
    parts = F.split(column, rf" {sep.replace('[', chr(92) + '[').replace(']', chr(92) + ']')} ")
    head = F.array_join(F.slice(parts, 1, F.greatest(F.size(parts) - 1, F.lit(1))), f" {sep} ")
    return head, F.when(F.size(parts) > 1, F.element_at(parts, -1))
