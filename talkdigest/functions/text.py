"""Tokens, sentences and HTML text as built-in column functions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}]+"
SENTENCE_END = r"[.!?\n]+"
#: HTML parts without running text (fixed values).
NOISE = ("script", "style", "nav", "footer")
#: Entities and their characters (fixed values).
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&"))


def words(text: Column, lower: bool = True) -> Column:
    """Runs of letters or digits; an empty array for null."""
    text = F.coalesce(text, F.lit(""))
    return F.regexp_extract_all(F.lower(text) if lower else text, F.lit(f"({WORD})"), F.lit(1))


def sentences(text: Column) -> Column:
    """Trimmed, non-blank pieces between sentence ends."""
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), SENTENCE_END), lambda x: F.trim(x)), lambda x: x != "")


def grams(tokens: Column, n: int) -> Column:
    """Adjacent n-grams, joined by a space."""
    starts = F.when(F.size(tokens) >= n, F.sequence(F.lit(1), F.size(tokens) - (n - 1))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: F.array_join(F.slice(tokens, i, n), " "))


def normal(text: Column) -> Column:
    """Lower case, single spaces."""
    return F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))


def without_noise(html: Column) -> Column:
    html = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?s)<!--.*?-->", "")
    for tag in NOISE:
        html = F.regexp_replace(html, rf"(?s)<{tag}[ >].*?</{tag}>", "")
    return html


def plain(html: Column) -> Column:
    """Text of a fragment: tags removed, entities decoded, trimmed."""
    out = F.regexp_replace(html, r"<[^>]*>", "")
    for entity, char in ENTITIES:
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(out)


def headline(html: Column) -> Column:
    return plain(F.regexp_extract(without_noise(html), r"(?s)<h1[^>]*>(.*?)</h1>", 1))


def paragraphs(html: Column) -> Column:
    """Non-blank texts of the <p> pieces, closed or not."""
    pieces = F.split(without_noise(html), r"<p>|<p [^>]*>")
    pieces = F.slice(pieces, 2, F.greatest(F.size(pieces) - 1, F.lit(0)))
    return F.filter(F.transform(pieces, lambda x: plain(F.regexp_replace(x, r"(?s)</p>.*", ""))), lambda x: x != "")
