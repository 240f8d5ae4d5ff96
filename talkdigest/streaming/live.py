"""Live meetings: windows slide while utterances arrive, and event windows, joins and de-duplication around them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.runs import NAMES, Meeting, step
from ..schema import STEPS, positive

STATE = "utt_no array<bigint>, n_tok array<bigint>, text array<string>, next_utt bigint, step bigint, offset bigint"


class Buffer:
    """The utterances of a meeting from the left edge on; the same steps as a batch run would make."""

    def __init__(self, meeting: str, backbone, k: int):
        self.meeting, self.backbone, self.k = meeting, backbone, k
        self.utts, self.toks, self.texts, self.next, self.step, self.offset = [], [], [], 0, 0, 0

    def load(self, state: tuple) -> None:
        self.utts, self.toks, self.texts, self.next, self.step, self.offset = (list(x) if i < 3 else x for i, x in enumerate(state))

    def state(self) -> tuple:
        return self.utts, self.toks, self.texts, self.next, self.step, self.offset

    def add(self, n_tok: int, text: str) -> None:
        self.utts.append(self.next)
        self.toks.append(int(n_tok))
        self.texts.append(text)
        self.next += 1

    def move(self, final: bool) -> Iterator[tuple]:
        """A step needs one utterance beyond the window, or the end of the meeting."""
        while self.utts:
            ends = np.cumsum(self.toks)
            if not final and ends[-1] <= self.k:
                return
            record = type("Record", (), {"meeting_id": self.meeting, "speaker": [None] * len(self.utts), "text": self.texts, "utt_no": self.utts, "n_tok": self.toks, "tok_start": ends - self.toks + self.offset, "tok_end": ends + self.offset})
            m = Meeting(record)
            hi, i_left, i_right, snippet, b, nxt = step(m, 0, self.backbone, self.k, "after")
            last = len(self.utts) - 1
            stride = int(m.tok_start[nxt] if nxt <= last else m.tok_end[last]) - i_left
            yield (self.meeting, self.step, self.utts[0], self.utts[hi], i_left, i_right, snippet, self.utts[b], stride)
            self.offset += int(sum(self.toks[:nxt]))
            self.utts, self.toks, self.texts, self.step = self.utts[nxt:], self.toks[nxt:], self.texts[nxt:], self.step + 1


def dynamic(stream: DataFrame, backbone, k: int = 1024, gap: str = "1 day") -> DataFrame:
    """Steps of a stream (meeting_id, ts timestamp, seq, n_tok, text): emitted as soon as a window is full, the rest when no
    utterance has come for `gap` of event time. State is one window a meeting. Rows of a batch are put in order by (ts, seq)."""
    positive(k=k)
    gap_ms = int(pd.Timedelta(gap).total_seconds() * 1000)

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        buffer = Buffer(key[0], backbone, k)
        if state.exists:
            buffer.load(state.get)
        if state.hasTimedOut:
            out = list(buffer.move(True))
            state.remove()
            yield pd.DataFrame(out, columns=NAMES)
            return
        rows = pd.concat(list(batches)).sort_values(["ts", "seq"])
        for r in rows.itertuples(index=False):
            buffer.add(r.n_tok, r.text)
        out = list(buffer.move(False))
        state.update(buffer.state())
        state.setTimeoutTimestamp(int(max(pd.Timestamp(rows["ts"].max()).timestamp() * 1000, state.getCurrentWatermarkMs())) + gap_ms)
        yield pd.DataFrame(out, columns=NAMES)

    marked = stream.withWatermark("ts", "1 second").select("meeting_id", "ts", "seq", "n_tok", "text")
    return marked.groupBy("meeting_id").applyInPandasWithState(run, STEPS, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def from_events(events: DataFrame) -> DataFrame:
    """Utterances of a user's events: (meeting_id, ts, seq, n_tok, text)."""
    return events.select(F.col("user_id").cast("string").alias("meeting_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("seq"), (1 + F.floor("value") % 20).cast("long").alias("n_tok"), F.concat_ws(" ", "event_type", F.col("event_id").cast("string")).alias("text"))


def read_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A file stream of the events table."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{folder}/[{name[0]}]{name[1:]}")  # a pattern, as the table may be one file


def stamped(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, kind: str = "tumbling", late: str = "1 hour") -> DataFrame:
    """(start, end, event_type, n, total) of tumbling (1 day), sliding (2 days by 1) or session (gap 1 day, by user) windows."""
    rows = stamped(events).withWatermark("ts", late)
    agg = (F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))
    if kind == "session":
        out = rows.groupBy(F.session_window("ts", "1 day").alias("w"), F.col("user_id").cast("string").alias("key")).agg(*agg)
    elif kind in ("tumbling", "sliding"):
        w = F.window("ts", "1 day") if kind == "tumbling" else F.window("ts", "2 days", "1 day")
        out = rows.groupBy(w.alias("w"), F.col("event_type").alias("key")).agg(*agg)
    else:
        raise ValueError(f"kind must be tumbling, sliding or session, not {kind}")
    return out.select(F.col("w.start").alias("win_start"), F.col("w.end").alias("win_end"), "key", "n", "total")


def dedup(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once, however often it is replayed within the watermark."""
    return stamped(events).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def join_static(events: DataFrame, users: DataFrame) -> DataFrame:
    """A stream of events with the customer of the same number."""
    return stamped(events).join(users.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "user_id", "event_type", "c_mktsegment")


def join_streams(clicks: DataFrame, errors: DataFrame, within: str = "1 hour") -> DataFrame:
    """(click_id, error_id): errors of a user that follow a click within a time; both sides are watermarked, so state is bounded."""
    a = stamped(clicks).where("event_type = 'click'").select(F.col("user_id").alias("a_user"), F.col("event_id").alias("click_id"), F.col("ts").alias("a_ts")).withWatermark("a_ts", "1 hour")
    b = stamped(errors).where("event_type = 'error'").select(F.col("user_id").alias("b_user"), F.col("event_id").alias("error_id"), F.col("ts").alias("b_ts")).withWatermark("b_ts", "1 hour")
    return a.join(b, F.expr(f"a_user = b_user and b_ts >= a_ts and b_ts <= a_ts + interval {within}")).select("click_id", "error_id")


def drained(stream: DataFrame, name: str, folder: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, into Parquet files of the folder (append) or a memory table, and read it."""
    spark = stream.sparkSession
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/{name}-state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").start(f"{folder}/{name}")
    else:
        query = writer.format("memory").queryName(name).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/{name}") if mode == "append" else spark.table(name)
