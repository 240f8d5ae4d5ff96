"""Deterministic train, validation and test sets in the ratio 97 : 20 : 20."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ranking import positions, text_bucket

TRAIN, VALIDATION, TEST, STEP = 97, 20, 20, 53


def assign(meetings: DataFrame, key: str = "meeting_id") -> DataFrame:
    """(key, meeting_no, split) of the distinct keys; a step prime to 137 spreads small sets over all three."""
    rows = positions(meetings.select(key).distinct(), text_bucket(F.col(key).cast("string")), [key], [], "meeting_no")
    place = F.pmod(F.lit(STEP) * F.col("meeting_no"), F.lit(TRAIN + VALIDATION + TEST))
    return rows.withColumn("split", F.when(place < TRAIN, "train").when(place < TRAIN + VALIDATION, "validation").otherwise("test"))


def assign_exact(meetings: DataFrame, train: int, validation: int, key: str = "meeting_id") -> DataFrame:
    """The first `train` keys, the next `validation` ones, and the rest."""
    rows = positions(meetings.select(key).distinct(), text_bucket(F.col(key).cast("string")), [key], [], "meeting_no")
    return rows.withColumn("split", F.when(F.col("meeting_no") < train, "train").when(F.col("meeting_no") < train + validation, "validation").otherwise("test"))
