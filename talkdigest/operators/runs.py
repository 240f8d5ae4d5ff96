"""Runs of a backbone over meetings: truncated, fixed windows, gold segments, and dynamically sliding windows.

The dynamic loop of a meeting is sequential, so it stays inside one task; meetings are the unit of parallelism and
one shuffle (nesting) is all. Two more executions give the same steps: a frontier that moves all meetings one step at
a time (for generators that serve large batches), and, for the lead backbone, a jump table with pointer doubling.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import normal, sentences, words
from ..schema import STEPS, positive
from ..sources.layout import nest, spans_of
from .boundary import locate
from .iteration import cut
from .windows import View, advance, fixed, reach

ARRAYS = ("utt_no", "speaker", "text", "n_tok", "tok_start", "tok_end")


def arrays(nested: DataFrame) -> DataFrame:
    return nested.select("meeting_id", *[F.col(f"utterances.{c}").alias(c) for c in ARRAYS])


def step(row, left: int, backbone, k: int, resume: str):
    """(hi, i_left, i_right, snippet, boundary, next left) of one window."""
    hi = reach(left, row.tok_start, row.tok_end, k)
    snippet, b = backbone.generate(View(row.meeting_id, row.utt_no, row.speaker, row.text, row.n_tok, left, hi, k))
    if isinstance(b, str):
        place = locate(row.text[left:hi + 1], b)
        b = None if place is None else left + place
    b, nxt = advance(left, b, hi, resume)
    i_left = int(row.tok_start[left])
    return hi, i_left, min(int(row.tok_end[hi]), i_left + k) if hi == left else int(row.tok_end[hi]), snippet, b, nxt


class Meeting:
    __slots__ = ("meeting_id", "utt_no", "speaker", "text", "n_tok", "tok_start", "tok_end")

    def __init__(self, record):
        self.meeting_id, self.speaker, self.text = record.meeting_id, list(record.speaker), list(record.text)
        self.utt_no, self.n_tok, self.tok_start, self.tok_end = (np.asarray(getattr(record, c), np.int64) for c in ("utt_no", "n_tok", "tok_start", "tok_end"))


def steps_of(meeting: Meeting, backbone, k: int, resume: str, stop: str) -> Iterator[tuple]:
    """All steps of one meeting; left strictly grows, so there are at most as many as utterances."""
    left, last, number, backbone = 0, len(meeting.utt_no) - 1, 0, backbone.of(meeting)
    while left <= last:
        hi, i_left, i_right, snippet, b, nxt = step(meeting, left, backbone, k, resume)
        over = b >= last or (stop == "window" and hi >= last)
        stride = int(meeting.tok_start[nxt] if nxt <= last else meeting.tok_end[last]) - i_left
        yield (meeting.meeting_id, number, int(meeting.utt_no[left]), int(meeting.utt_no[hi]), i_left, i_right, snippet, int(meeting.utt_no[b]), stride)
        if over:
            return
        left, number = nxt, number + 1


NAMES = [c.split()[0] for c in STEPS.split(", ")]


def _check(k, resume, stop):
    positive(k=k)
    if resume not in ("after", "at"):
        raise ValueError(f"resume must be after or at, not {resume}")
    if stop not in ("boundary", "window"):
        raise ValueError(f"stop must be boundary or window, not {stop}")


def dynamic(utts: DataFrame, backbone, k: int = 1024, resume: str = "after", stop: str = "boundary") -> DataFrame:
    """The steps table (see schema.STEPS): each window starts where the boundary of the one before says."""
    _check(k, resume, stop)
    shared = utts.sparkSession.sparkContext.broadcast(backbone)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = [s for record in batch.itertuples(index=False) for s in steps_of(Meeting(record), shared.value, k, resume, stop)]
            yield pd.DataFrame(rows, columns=NAMES)

    return arrays(nest(utts)).mapInPandas(run, STEPS)


def dynamic_with_source(utts: DataFrame, backbone, k: int = 1024, resume: str = "after", stop: str = "boundary") -> DataFrame:
    """As dynamic(), with `source`: the tokens of each window, an utterance a line; no join brings a window's utterances back."""
    _check(k, resume, stop)
    shared = utts.sparkSession.sparkContext.broadcast(backbone)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for record in batch.itertuples(index=False):
                m, line, rows = Meeting(record), list(record.line), []
                for s in steps_of(m, shared.value, k, resume, stop):
                    left, hi = np.searchsorted(m.utt_no, (s[2], s[3]))
                    rows.append((*s, "\n".join(line[left:hi + 1])))
                yield pd.DataFrame(rows, columns=[*NAMES, "source"])

    nested = nest(utts.withColumn("line", F.array_join("tokens", " ")), ("line",))
    return nested.select("meeting_id", *[F.col(f"utterances.{c}").alias(c) for c in (*ARRAYS, "line")]).mapInPandas(run, f"{STEPS}, source string")


def frontier(utts: DataFrame, backbone, k: int = 1024, resume: str = "after", stop: str = "boundary", keep=None) -> DataFrame:
    """The same steps, one distributed pass a step: every open meeting moves one window on. keep(df) cuts the lineage of each pass."""
    _check(k, resume, stop)
    keep = keep or cut
    meetings = arrays(nest(utts)).persist()
    shared = utts.sparkSession.sparkContext.broadcast(backbone)
    schema = STEPS + ", next_left bigint, open boolean"

    def one(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for record in batch.itertuples(index=False):
                m, left = Meeting(record), int(record.left)
                last = len(m.utt_no) - 1
                hi, i_left, i_right, snippet, b, nxt = step(m, left, shared.value, k, resume)
                stride = int(m.tok_start[nxt] if nxt <= last else m.tok_end[last]) - i_left
                rows.append((m.meeting_id, int(record.step), int(m.utt_no[left]), int(m.utt_no[hi]), i_left, i_right, snippet, int(m.utt_no[b]), stride, nxt, not (b >= last or (stop == "window" and hi >= last))))
            yield pd.DataFrame(rows, columns=[*NAMES, "next_left", "open"])

    at, done = meetings.select("meeting_id", F.lit(0).cast("long").alias("left"), F.lit(0).cast("long").alias("step")), None
    while True:
        moved = keep(meetings.join(at, "meeting_id").mapInPandas(one, schema))
        done = moved.select(*NAMES) if done is None else done.unionByName(moved.select(*NAMES))
        if not moved.where("open").limit(1).count():
            return done
        at = moved.where("open").select("meeting_id", F.col("next_left").alias("left"), (F.col("step") + 1).alias("step"))


def reaches(utts: DataFrame, k: int) -> DataFrame:
    """(meeting_id, utt_no, hi): the last utterance that a window from each utterance holds; one shuffle, no range join."""
    ends = utts.select("meeting_id", F.col("tok_end").alias("at"), F.lit(0).alias("kind"), "utt_no")
    asks = utts.select("meeting_id", (F.col("tok_start") + k).alias("at"), F.lit(1).alias("kind"), "utt_no")
    order = Window.partitionBy("meeting_id").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = ends.unionByName(asks).withColumn("hi", F.max(F.when(F.col("kind") == 0, F.col("utt_no"))).over(order))
    return rows.where("kind = 1").select("meeting_id", "utt_no", F.greatest("utt_no", F.coalesce("hi", "utt_no")).alias("hi"))


def jump_table(utts: DataFrame, k: int, q: int, resume: str = "after") -> DataFrame:
    """(meeting_id, utt_no, hi, boundary, next) of the lead backbone; next is null at the end. Utterance numbers have no gaps."""
    rows = reaches(utts, k).join(utts.groupBy("meeting_id").agg(F.max("utt_no").alias("last_utt")), "meeting_id")
    rows = rows.withColumn("boundary", F.least(F.col("utt_no") + q - 1, "hi"))
    nxt = F.col("boundary") + 1 if resume == "after" else F.greatest(F.col("boundary"), F.col("utt_no") + 1)
    return rows.select("meeting_id", "utt_no", "hi", "boundary", F.when(F.col("boundary") < F.col("last_utt"), nxt).alias("next"))


def jump(utts: DataFrame, k: int, q: int, resume: str = "after", keep=None) -> DataFrame:
    """(meeting_id, step, left_utt, hi_utt, boundary_utt) of the lead run by pointer doubling: log2(steps) joins."""
    keep = keep or cut
    table = keep(jump_table(utts, k, q, resume))
    hops = table.where("next is not null").select("meeting_id", F.col("utt_no").alias("a"), F.col("next").alias("b"))
    found = table.groupBy("meeting_id").agg(F.min("utt_no").alias("a"), F.lit(0).cast("long").alias("step"))
    size = 1
    while hops.limit(1).count():
        ahead = found.join(hops, ["meeting_id", "a"]).select("meeting_id", F.col("b").alias("a"), (F.col("step") + size).alias("step"))
        found = keep(found.unionByName(ahead))
        on = hops.select("meeting_id", F.col("a").alias("b"), F.col("b").alias("c"))
        hops, size = keep(hops.join(on, ["meeting_id", "b"]).select("meeting_id", "a", F.col("c").alias("b"))), 2 * size
    return found.join(table.withColumnRenamed("utt_no", "a"), ["meeting_id", "a"]).select("meeting_id", "step", F.col("a").alias("left_utt"), F.col("hi").alias("hi_utt"), F.col("boundary").alias("boundary_utt"))


def windowed(parts: DataFrame, backbone, k: int, group: str) -> DataFrame:
    """(meeting_id, step, snippet, i_left, i_right): every group of utterance parts is one independent window.

    parts: meeting_id, group, utt_no, speaker, n_tok, tok_start, tok_end, part (the text inside the window), part_tok."""
    rows = parts.groupBy("meeting_id", group).agg(F.sort_array(F.collect_list(F.struct("utt_no", "speaker", "part", "part_tok", "from_tok"))).alias("p"))
    rows = rows.select("meeting_id", F.col(group).cast("long").alias("step"), *[F.col(f"p.{c}").alias(c) for c in ("utt_no", "speaker", "part", "part_tok", "from_tok")])
    return _generated(rows, backbone, k)


def _generated(rows: DataFrame, backbone, k: int) -> DataFrame:
    """As windowed(), of rows (meeting_id, step, and arrays utt_no, speaker, part, part_tok, from_tok)."""
    shared = rows.sparkSession.sparkContext.broadcast(backbone)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                n = np.asarray(r.part_tok, np.int64)
                snippet, _ = shared.value.generate(View(r.meeting_id, np.asarray(r.utt_no), list(r.speaker), list(r.part), n, 0, len(n) - 1, k))
                out.append((r.meeting_id, r.step, snippet, int(r.from_tok[0]), int(r.from_tok[0]) + int(n.sum())))
            yield pd.DataFrame(out, columns=["meeting_id", "step", "snippet", "i_left", "i_right"])

    return rows.mapInPandas(run, "meeting_id string, step long, snippet string, i_left long, i_right long")


def _parts(rows: DataFrame) -> DataFrame:
    """Exactly the tokens inside the window, also in mid-utterance."""
    whole = (F.col("win_from") == 0) & (F.col("win_to") == F.col("n_tok"))
    part = F.when(whole, F.col("text")).otherwise(F.array_join(F.slice("tokens", (F.col("win_from") + 1).cast("int"), F.greatest(F.col("win_to") - F.col("win_from"), F.lit(0)).cast("int")), " "))
    return rows.withColumn("part", part).withColumn("part_tok", F.greatest(F.col("win_to") - F.col("win_from"), F.lit(0))).withColumn("from_tok", F.col("tok_start") + F.col("win_from"))


def fixed_run(utts: DataFrame, backbone, k: int = 1024, stride: int | None = None) -> DataFrame:
    """Windows have no dependence on each other, so each is a row of its own."""
    return windowed(_parts(fixed(utts, k, stride)), backbone, k, "window")


def truncate_run(utts: DataFrame, backbone, k: int = 1024) -> DataFrame:
    """One call on the first k tokens."""
    positive(k=k)
    rows = utts.where(F.col("tok_start") < k).withColumn("window", F.lit(0).cast("long")).withColumn("win_from", F.lit(0).cast("long")).withColumn("win_to", F.least("n_tok", k - F.col("tok_start")))
    return windowed(_parts(rows), backbone, k, "window")


def gold_run(utts: DataFrame, segments: DataFrame, backbone, k: int = 1024) -> DataFrame:
    """Each gold segment (meeting_id, snip_no, seg_start, seg_end), cut to k tokens, is one input."""
    positive(k=k)
    spans = spans_of(segments, utts, ["speaker", "text", "n_tok", "tok_start"], ["snip_no"])
    rows = spans.select("meeting_id", "snip_no", F.array_min(F.transform("u", lambda x: x["tok_start"])).alias("first"), "u")

    def part(x):
        """An utterance of the segment as far as the first k tokens reach."""
        size = F.least(x["n_tok"], k - (x["tok_start"] - F.col("first")))
        text = F.when(size == x["n_tok"], x["text"]).otherwise(F.array_join(F.slice(words(x["text"]), 1, F.greatest(size, F.lit(0)).cast("int")), " "))
        return F.struct(x["utt_no"].alias("utt_no"), x["speaker"].alias("speaker"), text.alias("part"), F.greatest(size, F.lit(0).cast("long")).alias("part_tok"), x["tok_start"].alias("from_tok"))

    rows = rows.withColumn("p", F.transform(F.filter("u", lambda x: x["tok_start"] - F.col("first") < k), part))
    return _generated(rows.select("meeting_id", F.col("snip_no").cast("long").alias("step"), *[F.col(f"p.{c}").alias(c) for c in ("utt_no", "speaker", "part", "part_tok", "from_tok")]), backbone, k)


def assemble(steps: DataFrame) -> DataFrame:
    """(meeting_id, text): snippets in order of their steps."""
    return steps.groupBy("meeting_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("step", "snippet"))), lambda x: x["snippet"]), "\n").alias("text"))


def first_places(items: pd.Series) -> pd.Series:
    """Places of an array's elements that did not occur before."""
    def places(x):
        seen: dict = {}
        for i, item in enumerate(x):
            seen.setdefault(item, i)
        return list(seen.values())

    return items.map(places)


def dedup_sentences(outputs: DataFrame) -> DataFrame:
    """(meeting_id, text, sentences, repeated): outputs (meeting_id, text), a row a meeting, without sentences that occurred before, compared in
    lower case and single spaces. Row by row: sentences are no rows of a shuffle."""
    rows = outputs.select("meeting_id", sentences(F.col("text")).alias("all")).where(F.size("all") > 0)
    rows = rows.withColumn("firsts", F.pandas_udf(first_places, "array<int>")(F.transform("all", lambda s: normal(s))))
    text = F.array_join(F.transform("firsts", lambda i: F.get("all", i)), ". ")
    return rows.select("meeting_id", text.alias("text"), F.size("all").cast("long").alias("sentences"), (F.size("all") - F.size("firsts")).cast("long").alias("repeated"))


def redundancy(outputs: DataFrame) -> DataFrame:
    """(sentences, repeated, share) over all outputs."""
    return dedup_sentences(outputs).agg(F.sum("sentences").alias("sentences"), F.sum("repeated").alias("repeated"), F.round(F.sum("repeated") / F.sum("sentences"), 6).alias("share"))


def overlap_votes(utts: DataFrame, k: int, stride: int, q: int) -> DataFrame:
    """(meeting_id, utt_no, windows, votes): in how many overlapping windows an utterance stands, and among the first q of how many."""
    rows = fixed(utts, k, stride)
    nth = F.row_number().over(Window.partitionBy("meeting_id", "window").orderBy("utt_no"))
    return rows.withColumn("nth", nth).groupBy("meeting_id", "utt_no").agg(F.count("*").alias("windows"), F.sum((F.col("nth") <= q).cast("long")).alias("votes"))
