"""Corpus analyses: sizes, order agreement, coverage, where support lies and what truncation loses."""

from __future__ import annotations

from bisect import bisect_right

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import grams
from ..schema import positive


def corpus_stats(utts: DataFrame, summary: DataFrame, corpus: str) -> DataFrame:
    """(corpus, meetings, source_sentences, source_words, summary_sentences, summary_words): means over meetings."""
    source = utts.groupBy("meeting_id").agg(F.count("*").alias("s"), F.sum("n_tok").alias("w")).agg(F.count("*").alias("meetings"), F.round(F.avg("s"), 6).alias("source_sentences"), F.round(F.avg("w"), 6).alias("source_words"))
    target = summary.groupBy("meeting_id").agg(F.count("*").alias("s"), F.sum(F.size("tokens")).alias("w")).agg(F.round(F.avg("s"), 6).alias("summary_sentences"), F.round(F.avg("w"), 6).alias("summary_words"))
    return source.crossJoin(target).withColumn("corpus", F.lit(corpus))  # one row each


def role_stats(utts: DataFrame) -> DataFrame:
    return utts.groupBy("speaker").agg(F.count("*").alias("turns"), F.sum("n_tok").alias("words"), F.countDistinct("meeting_id").alias("meetings"))


def support_spans(links: DataFrame) -> DataFrame:
    """(meeting_id, sent_no, seg_start, seg_end, n_support) of annotated sentences; narrow."""
    return links.where("support is not null and size(support) > 0").select("meeting_id", "sent_no", F.array_min("support").alias("seg_start"), F.array_max("support").alias("seg_end"), F.size("support").cast("long").alias("n_support"))


def by_occurrence():
    return Window.partitionBy("meeting_id").orderBy("seg_start", "seg_end", "sent_no")


def occurrence_order(spans: DataFrame) -> DataFrame:
    """spans with occ_rank and sum_rank, both dense from 0 over annotated sentences."""
    return spans.withColumn("occ_rank", F.row_number().over(by_occurrence()) - 1).withColumn("sum_rank", F.row_number().over(Window.partitionBy("meeting_id").orderBy("sent_no")) - 1)


def longest_in_order(starts) -> int:
    tails: list[int] = []
    for x in starts:
        at = bisect_right(tails, x)
        tails[at:at + 1] = [x]
    return len(tails)


def pairs_in_order(starts) -> int:
    """Pairs whose later member does not start earlier, without visiting each pair."""
    seen: list[int] = []
    hits = 0
    for x in starts:
        at = bisect_right(seen, x)
        hits += at
        seen.insert(at, x)
    return hits


def starts_in_order(spans: DataFrame) -> DataFrame:
    """(meeting_id, starts): a meeting's segment starts in the order of its summary."""
    return spans.groupBy("meeting_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("sent_no", "seg_start"))), lambda x: x["seg_start"]).alias("starts"))


def agreement_by_meeting(spans: DataFrame, measure: str = "rank") -> DataFrame:
    """(meeting_id, hits, total) of a measure: rank, adjacent, lis or kendall."""
    if measure == "rank":
        return occurrence_order(spans).groupBy("meeting_id").agg(F.sum((F.col("occ_rank") == F.col("sum_rank")).cast("long")).alias("hits"), F.count("*").alias("total"))
    if measure == "adjacent":
        before = F.lag("seg_start").over(Window.partitionBy("meeting_id").orderBy("sent_no"))
        return spans.withColumn("before", before).where("before is not null").groupBy("meeting_id").agg(F.sum((F.col("before") <= F.col("seg_start")).cast("long")).alias("hits"), F.count("*").alias("total"))
    if measure == "lis":
        @F.pandas_udf("long")
        def longest(starts: pd.Series) -> pd.Series:
            return starts.map(longest_in_order)

        return starts_in_order(spans).select("meeting_id", longest("starts").alias("hits"), F.size("starts").cast("long").alias("total"))
    if measure == "kendall":
        @F.pandas_udf("long")
        def concordant(starts: pd.Series) -> pd.Series:
            return starts.map(pairs_in_order)

        n = F.size("starts").cast("long")
        return starts_in_order(spans).where(n > 1).select("meeting_id", concordant("starts").alias("hits"), (n * (n - 1) / 2).cast("long").alias("total"))
    raise ValueError(f"measure must be rank, adjacent, lis or kendall, not {measure}")


def order_agreement(spans: DataFrame, measure: str = "rank") -> DataFrame:
    """(measure, hits, total, micro, macro) over all meetings."""
    rows = agreement_by_meeting(spans, measure)
    return rows.agg(F.sum("hits").alias("hits"), F.sum("total").alias("total"), F.round(F.sum("hits") / F.sum("total"), 6).alias("micro"), F.round(F.avg(F.col("hits") / F.col("total")), 6).alias("macro")).withColumn("measure", F.lit(measure))


def segments(utts: DataFrame, links: DataFrame, mode: str = "span") -> DataFrame:
    """(meeting_id, sent_no, utterance columns) of each segment: the whole span, or the marked utterances only."""
    if mode not in ("span", "support"):
        raise ValueError(f"mode must be span or support, not {mode}")
    spans = support_spans(links) if mode == "span" else None
    flat = spans.select("meeting_id", "sent_no", F.explode(F.sequence("seg_start", "seg_end")).alias("utt_no")) if mode == "span" else links.where("support is not null").select("meeting_id", "sent_no", F.explode("support").alias("utt_no"))
    return flat.join(utts, ["meeting_id", "utt_no"])


def _counts(rows: DataFrame, name: str, n: int = 1) -> DataFrame:
    tokens = F.col("tokens") if n == 1 else grams(F.col("tokens"), n)
    return rows.select("meeting_id", "sent_no", F.explode(tokens).alias("word")).groupBy("meeting_id", "sent_no", "word").agg(F.count("*").alias(name))


def coverage_by_sentence(gold: DataFrame, segs: DataFrame, count: str = "multiset", n: int = 1) -> DataFrame:
    """(meeting_id, sent_no, matched, total) of annotated sentences; count: multiset or set; n: n-grams."""
    if count not in ("multiset", "set"):
        raise ValueError(f"count must be multiset or set, not {count}")
    mine, theirs = _counts(gold.where("support is not null"), "c", n), _counts(segs, "d", n)
    if count == "set":
        mine, theirs = mine.withColumn("c", F.lit(1).cast("long")), theirs.withColumn("d", F.lit(1).cast("long"))
    rows = mine.join(theirs, ["meeting_id", "sent_no", "word"], "left")
    return rows.groupBy("meeting_id", "sent_no").agg(F.sum(F.least("c", F.coalesce("d", F.lit(0)))).alias("matched"), F.sum("c").alias("total"))


def coverage(gold: DataFrame, segs: DataFrame, count: str = "multiset", avg: str = "micro") -> DataFrame:
    """(matched, total, coverage): recall of summary words in their segments."""
    rows = coverage_by_sentence(gold, segs, count)
    value = F.sum("matched") / F.sum("total") if avg == "micro" else F.avg(F.col("matched") / F.col("total"))
    return rows.agg(F.sum("matched").alias("matched"), F.sum("total").alias("total"), F.round(value, 6).alias("coverage"))


def novelty(gold: DataFrame, segs: DataFrame, n: int = 1) -> DataFrame:
    """(novelty): share of summary n-grams that their segment lacks."""
    rows = coverage_by_sentence(gold, segs, "multiset", n)
    return rows.agg(F.round(1 - F.sum("matched") / F.sum("total"), 6).alias("novelty"))


def support_utterances(utts: DataFrame, links: DataFrame) -> DataFrame:
    """Distinct supporting utterances with the meeting's length n."""
    n = utts.groupBy("meeting_id").agg(F.max("tok_end").alias("n"))
    flat = links.where("support is not null").select("meeting_id", F.explode("support").alias("utt_no")).distinct()
    return flat.join(utts.select("meeting_id", "utt_no", "n_tok", "tok_start", "tok_end"), ["meeting_id", "utt_no"]).join(n, "meeting_id")


def lead_bias(utts: DataFrame, links: DataFrame, deciles: int = 10) -> DataFrame:
    """(decile, utterances, words, share): where in the transcript the supporting words stand."""
    rows = support_utterances(utts, links).where("n > 0").withColumn("decile", F.least(F.lit(deciles - 1), F.floor(deciles * F.col("tok_start") / F.col("n"))).cast("int"))
    rows = rows.groupBy("decile").agg(F.count("*").alias("utterances"), F.sum("n_tok").alias("words"))
    return rows.withColumn("share", F.round(F.col("words") / F.sum("words").over(Window.partitionBy(F.lit(0))), 6))  # one row a decile


def truncation_loss(utts: DataFrame, links: DataFrame, k: int = 1024) -> DataFrame:
    """(k, utterances, lost_utterances, words, lost_words, meetings, cut_meetings): support that ends beyond the first k tokens."""
    positive(k=k)
    lost = (F.col("tok_end") > k).cast("long")
    return support_utterances(utts, links).agg(F.count("*").alias("utterances"), F.sum(lost).alias("lost_utterances"), F.sum("n_tok").alias("words"), F.sum(lost * F.col("n_tok")).alias("lost_words"),
                                               F.countDistinct("meeting_id").alias("meetings"), F.countDistinct(F.when(F.col("n") > k, F.col("meeting_id"))).alias("cut_meetings")).withColumn("k", F.lit(k).cast("long"))
