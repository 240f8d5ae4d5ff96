"""SQL registration: words, longest common subsequence, and a sliding-window table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType
from pyspark.sql.udtf import UserDefinedTableFunction

from ..operators.rouge import lcs


def lcs_udf():
    def lcs_length(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([lcs(list(x), list(y)) if x is not None and y is not None else 0 for x, y in zip(a, b)], dtype="int64")

    return F.pandas_udf(lcs_length, LongType())


class Slide:
    """slide(TABLE(utts) PARTITION BY (meeting_id) ORDER BY (utt_no), k): windows of whole utterances of up to k tokens."""

    def __init__(self):
        self.meeting, self.first, self.last, self.tokens, self.window, self.k = None, None, None, 0, 0, 0

    def eval(self, row, k):
        n, self.k = row["n_tok"], k
        if self.first is not None and self.tokens + n > k:
            yield self.meeting, self.window, self.first, self.last, self.tokens
            self.first, self.tokens, self.window = None, 0, self.window + 1
        self.meeting, self.last, self.tokens = row["meeting_id"], row["utt_no"], self.tokens + n
        if self.first is None:
            self.first = row["utt_no"]

    def terminate(self):
        if self.first is not None:
            yield self.meeting, self.window, self.first, self.last, self.tokens


def slide_udtf() -> UserDefinedTableFunction:
    return F.udtf(Slide, returnType="meeting_id string, win long, first_utt long, last_utt long, tokens long", useArrow=True)


def register(spark: SparkSession) -> None:
    spark.udf.register("lcs_length", lcs_udf())
    spark.udtf.register("slide", slide_udtf())
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION words(t STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(lower(t), '([\\p{L}\\p{N}]+)', 1)")
