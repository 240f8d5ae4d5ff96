"""Streams: equal to batch, late and repeated rows."""

import datetime as dt

from pyspark.sql import functions as F

from talkdigest.operators import runs
from talkdigest.operators.backbones import LeadBackbone
from talkdigest.operators.positions import attach
from talkdigest.streaming import live

SCHEMA = "meeting_id string, ts timestamp, seq long, n_tok long, text string"


def rows_of(n, meetings=("a", "b")):
    start = dt.datetime(2024, 1, 1)
    return [(m, start + dt.timedelta(minutes=i), i, 1 + (i * 7 + j) % 11, f"{m}{i}") for j, m in enumerate(meetings) for i in range(n)]


def test_live_run_equals_batch(spark, tmp_path):
    rows = rows_of(60)
    for part in range(4):
        spark.createDataFrame([r for r in rows if r[2] // 15 == part], SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    spark.createDataFrame([("end", dt.datetime(2024, 3, 1), 0, 1, "")], SCHEMA).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = live.drained(live.dynamic(stream, LeadBackbone(3), 30, "1 day"), "live", str(tmp_path)).where("meeting_id <> 'end'")
    utts = attach(spark.createDataFrame(rows, SCHEMA).select("meeting_id", F.col("seq").alias("utt_no"), "n_tok", "text", F.lit("PM").alias("speaker")))
    want = runs.dynamic(utts, LeadBackbone(3), 30)
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def test_repeated_events_are_kept_once(spark, tmp_path):
    rows = [(i % 5, dt.datetime(2024, 1, 1, 0, i % 5)) for i in range(10)]
    spark.createDataFrame(rows, "event_id long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("event_id long, ts timestamp").parquet(str(tmp_path / "in"))
    assert live.drained(live.dedup(stream), "dedup", str(tmp_path)).count() == 5


def test_late_rows_are_dropped(spark, tmp_path):
    at = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double"
    for i, rows in enumerate([[(1, at(0), 1, "a", 1.0)], [(2, at(200), 1, "a", 1.0)], [(3, at(1), 1, "a", 1.0)], [(4, at(500), 1, "a", 1.0)]]):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(schema).parquet(str(tmp_path / "in"))
        live.windowed(stream).writeStream.outputMode("append").format("parquet").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start(str(tmp_path / "out")).awaitTermination()
    out = spark.read.parquet(str(tmp_path / "out"))
    assert out.agg(F.sum("n")).first()[0] == 2  # the row of hour 1 came after the watermark had passed its day
