"""Pronoun openings of snippets are replaced by the person they refer to."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Personal pronouns of four languages (fixed values).
PRONOUNS = {
    "en": ("i", "you", "he", "she", "it", "we", "they"),
    "de": ("ich", "du", "er", "sie", "es", "wir", "ihr"),
    "fr": ("je", "tu", "il", "elle", "on", "nous", "vous", "ils", "elles"),
    "es": ("yo", "tú", "él", "ella", "nosotros", "vosotros", "ellos", "ellas"),
}
#: Pronouns of more than one person (fixed values).
PLURAL = ("we", "they", "wir", "nous", "ils", "elles", "nosotros", "ellos", "ellas")


def lexicon(langs=tuple(PRONOUNS)) -> list[str]:
    return sorted({p for lang in langs for p in PRONOUNS[lang]})


def first_word(text):
    return F.lower(F.regexp_extract(text, r"^\s*([\p{L}\p{N}]+)", 1))


def resolve_openings(snippets: DataFrame, chains: DataFrame, pronouns: list[str] | None = None) -> DataFrame:
    """snippets with `text` repaired and `repaired boolean`. Chains are those of the summary's original order; the one of
    a snippet's first sentence counts. Without a chain the text stays."""
    rows = snippets.withColumn("sent_no", F.element_at("sent_nos", 1))
    rows = rows.join(chains.select("meeting_id", "sent_no", "mention", "referent"), ["meeting_id", "sent_no"], "left")
    hit = first_word(F.col("text")).isin(pronouns or lexicon()) & (first_word(F.col("text")) == F.lower("mention"))
    hit = F.coalesce(hit, F.lit(False))
    rest = F.regexp_replace("text", r"^\s*[\p{L}\p{N}]+", "")
    return rows.withColumn("repaired", hit).withColumn("text", F.when(hit, F.concat("referent", rest)).otherwise(F.col("text"))).drop("sent_no", "mention", "referent")


def heuristic_chains(summary: DataFrame, persons: list[str], pronouns: list[str] | None = None) -> DataFrame:
    """(meeting_id, sent_no, mention, referent): a pronoun opening refers to the nearest person named in an earlier sentence.

    persons: names in lower case; a name with a plural `s` at its end agrees with plural pronouns, when known."""
    names = "|".join(sorted(persons, key=lambda p: (-len(p), p)))
    found = F.regexp_extract_all(F.lower("text"), F.lit(rf"({names})"), F.lit(1))
    order = Window.partitionBy("meeting_id").orderBy("sent_no").rowsBetween(Window.unboundedPreceding, -1)
    rows = summary.select("meeting_id", "sent_no", first_word(F.col("text")).alias("mention"), F.when(F.size(found) > 0, F.element_at(found, -1)).alias("named"))
    rows = rows.withColumn("referent", F.last("named", True).over(order))
    return rows.where(F.col("mention").isin(pronouns or lexicon()) & F.col("referent").isNotNull()).select("meeting_id", "sent_no", "mention", "referent")
