"""Relational operators around the method: containment, interval and as-of joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import words


def containment(items: DataFrame, documents: DataFrame) -> DataFrame:
    """(item_id, doc_id, doc_chars): documents that hold an item's text verbatim.

    An item's rarest inner word (among the documents) is the join key, so only documents with that word are compared; words
    at its edges may be parts of longer ones there. Items of fewer than three words meet the documents that hold their first three
    characters (an empty text stands in all)."""
    inner = F.slice(words(F.col("text"), False), 2, F.greatest(F.size(words(F.col("text"), False)) - 2, F.lit(0)))
    keys = items.select("item_id", F.col("text").alias("passage"), F.explode(inner).alias("word"))
    cells = documents.select("doc_id", F.explode(F.array_distinct(words(F.col("text"), False))).alias("word"))
    df = cells.join(keys.select("word").distinct(), "word", "left_semi").groupBy("word").count()
    rare = keys.join(df, "word", "left").groupBy("item_id", "passage").agg(F.min_by("word", F.struct(F.coalesce("count", F.lit(0)), "word")).alias("word"))
    found = cells.join(rare.select("item_id", "passage", "word"), "word").join(documents.select("doc_id", "text"), "doc_id").where(F.contains("text", "passage"))
    short = items.where(F.size(words(F.col("text"), False)) < 3).select("item_id", F.col("text").alias("passage"))
    sized = lambda df: df.select("item_id", "doc_id", F.length("text").cast("long").alias("doc_chars"))
    if short.isEmpty():
        return sized(found)
    keyed = short.withColumn("start", F.substring("passage", 1, 3))
    starts = documents.select("doc_id", F.explode(grams("text")).alias("start")).join(keyed.select("start").distinct(), "start", "left_semi")
    rest = starts.join(keyed, "start").join(documents.select("doc_id", "text"), "doc_id").where(F.contains("text", "passage"))
    return sized(found).unionByName(sized(rest))


def grams(text: str, n: int = 3) -> Column:
    """Distinct character strings of up to n of a column, the empty one included."""
    chars = F.split(text, "")
    at = lambda i, k: F.coalesce(F.get(chars, i + k), F.lit(""))

    def of(m: int) -> Column:
        return F.transform(chars, lambda c, i: F.concat(*[at(i, k) for k in range(m)]))

    return F.array_distinct(F.concat(F.array(F.lit("")), *[of(m) for m in range(1, n + 1)]))


def interval_expanded(points: DataFrame, spans: DataFrame) -> DataFrame:
    """points (meeting_id, utt_no, ...) joined with spans (meeting_id, seg_start, seg_end, ...) that hold them, as an equi-join on expanded positions."""
    return spans.withColumn("utt_no", F.explode(F.sequence("seg_start", "seg_end"))).join(points, ["meeting_id", "utt_no"])


def interval_theta(points: DataFrame, spans: DataFrame) -> DataFrame:
    """The same join with the range as a condition beside the meeting's equality."""
    s = spans.withColumnRenamed("meeting_id", "of_meeting")
    return points.join(s, (F.col("meeting_id") == F.col("of_meeting")) & F.col("utt_no").between(F.col("seg_start"), F.col("seg_end"))).drop("of_meeting")


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str, name: str) -> DataFrame:
    """left with `name`: the value of the latest right row of the same `by` at or before `at`; one shuffle, no range join."""
    a = left.withColumn("right_value", F.lit(None).cast(right.schema[value].dataType)).withColumn("side", F.lit(1))
    b = right.select(by, at, F.col(value).alias("right_value")).withColumn("side", F.lit(0))
    rows = a.unionByName(b, allowMissingColumns=True)
    order = Window.partitionBy(by).orderBy(at, "side", "right_value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return rows.withColumn(name, F.last("right_value", True).over(order)).where("side = 1").drop("side", "right_value")


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An inner join with hot keys of the large side spread over `salts` tasks; the small side is repeated that often."""
    a = large.withColumn("salt", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    b = small.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "salt"]).drop("salt")
