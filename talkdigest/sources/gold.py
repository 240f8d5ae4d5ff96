"""Planted reference summaries with their supporting utterances, for bundles of documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import ROLES


def planted(utts: DataFrame) -> DataFrame:
    """(meeting_id, sent_no, text, tokens, support, first_speaker).

    Every agenda item has a sentence on its first and last utterance; every odd item one more on the seam with the item
    before it. Each tenth pair of neighbours trades places; every fourth token is new; a ninth has no annotation."""
    at = lambda f: f(F.struct("utt_no", "speaker", "tokens"), "utt_no")
    items = utts.groupBy("meeting_id", "agenda_no").agg(at(F.min_by).alias("a"), at(F.max_by).alias("z"))
    order = Window.partitionBy("meeting_id").orderBy("agenda_no")
    items = items.withColumn("seam", F.when((F.col("agenda_no") % 2 == 1) & (F.lag("agenda_no").over(order) == F.col("agenda_no") - 1), F.lag("z").over(order)))
    # only the first and last utterances of items travel, with their tokens: no join with all utterances
    sentence = lambda first, last, key: F.struct(F.col(f"{first}.utt_no").alias("start"), F.col(f"{last}.utt_no").alias("end"), key.alias("key"), F.col(f"{first}.speaker").alias("first_speaker"), F.col(f"{first}.tokens").alias("first_tokens"), F.col(f"{last}.tokens").alias("last_tokens"))
    own, seam = sentence("a", "z", 2 * F.col("agenda_no")), sentence("seam", "a", 2 * F.col("agenda_no") - 1)
    rows = items.select("meeting_id", F.inline(F.when(F.col("seam").isNull(), F.array(own)).otherwise(F.array(own, seam))))
    occ = F.row_number().over(Window.partitionBy("meeting_id").orderBy("start", "end", "key")) - 1
    rows = rows.withColumn("occ", occ).withColumn("n", F.count("*").over(Window.partitionBy("meeting_id")))
    sent = F.when((F.col("occ") % 10 == 0) & (F.col("occ") + 1 < F.col("n")), F.col("occ") + 1).when(F.col("occ") % 10 == 1, F.col("occ") - 1).otherwise(F.col("occ"))
    rows = rows.withColumn("sent_no", sent.cast("long"))
    both = F.when(F.col("start") == F.col("end"), F.col("first_tokens")).otherwise(F.concat("first_tokens", "last_tokens"))
    tokens = F.transform(both, lambda t, i: F.when((i + 1) % 4 == 0, F.concat(F.lit("novel"), (i + 1).cast("string"))).otherwise(t))
    bundle = F.substring_index("meeting_id", "-", -1).cast("long")
    support = F.when((5 * bundle + F.col("sent_no")) % 9 != 4, F.array_distinct(F.array("start", "end")))
    rows = rows.withColumn("tokens", tokens)
    return rows.select("meeting_id", "sent_no", F.array_join("tokens", " ").alias("text"), "tokens", support.alias("support"), "first_speaker")


def with_speakers(gold: DataFrame) -> DataFrame:
    """The pronoun fixture: sentences open with the role of their first speaker, each sixth with `they`."""
    role = F.create_map(*[F.lit(x) for pair in ROLES.items() for x in pair])[F.col("first_speaker")]
    opening = F.when(F.col("sent_no") % 6 == 5, F.lit("they")).otherwise(F.concat(F.lit("the "), role))
    rows = gold.withColumn("referent", F.concat(F.lit("the "), role)).withColumn("text", F.concat_ws(" ", opening, "text"))
    return rows.withColumn("tokens", F.split("text", " "))


def chains(gold: DataFrame) -> DataFrame:
    """(meeting_id, sent_no, mention, referent) of the pronoun fixture."""
    return with_speakers(gold).where("sent_no % 6 = 5").select("meeting_id", "sent_no", F.lit("they").alias("mention"), "referent")
