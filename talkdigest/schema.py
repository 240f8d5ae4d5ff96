"""Declared schemas and the checks that inputs pass before a plan is built."""

from __future__ import annotations

from pyspark.sql import DataFrame

UTTERANCES = "meeting_id string, agenda_no int, utt_no bigint, speaker string, text string, tokens array<string>, n_tok bigint, tok_start bigint, tok_end bigint, char_start bigint, char_end bigint"
STEPS = "meeting_id string, step bigint, left_utt bigint, hi_utt bigint, i_left bigint, i_right bigint, snippet string, boundary_utt bigint, stride_tok bigint"

#: Speaker roles and their full names (fixed values).
ROLES = {"PM": "project manager", "ME": "marketing expert", "ID": "industrial designer", "UI": "user interface designer"}


def require(df: DataFrame, columns: str) -> DataFrame:
    """df, if it has all named columns with the named types (`name type, ...`); ValueError otherwise. `any` fits every type."""
    have = dict(df.dtypes)
    for part in columns.split(", "):
        name, kind = part.split(" ", 1)
        if name not in have:
            raise ValueError(f"missing column {name}")
        if kind != "any" and have[name] != kind:
            raise ValueError(f"column {name} is {have[name]}, not {kind}")
    return df


def positive(**values: int) -> None:
    for name, value in values.items():
        if value < 1:
            raise ValueError(f"{name} must be 1 or more, not {value}")


def check_utterances(df: DataFrame) -> DataFrame:
    """Runs one job: ValueError for a null meeting_id or a repeated (meeting_id, utt_no)."""
    require(df, "meeting_id string, utt_no any")
    if df.where("meeting_id is null").limit(1).count():
        raise ValueError("null in column meeting_id")
    if df.groupBy("meeting_id", "utt_no").count().where("count > 1").limit(1).count():
        raise ValueError("repeated key in columns meeting_id, utt_no")
    return df


def check_support(links: DataFrame, utts: DataFrame) -> DataFrame:
    """Runs one job: ValueError if a supporting utterance does not exist."""
    from pyspark.sql import functions as F

    flat = links.select("meeting_id", F.explode("support").alias("utt_no"))
    if flat.join(utts.select("meeting_id", "utt_no"), ["meeting_id", "utt_no"], "left_anti").limit(1).count():
        raise ValueError("index out of range in column support")
    return links
