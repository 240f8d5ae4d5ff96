"""URL filter: a blocked Bloom filter of listed canonical URLs, then an exact hash join, then host rules.

Every listed URL hashes to one 64-bit block and sets up to six bits there; the filter is a table (block, bits) of
about PER_BLOCK URLs a block, so it grows with the list. A page whose block lacks one of its bits is surely unlisted;
possible hits go to an exact join on the canonical URL, which removes false positives. Rules on host and path prefix
override the list, the longest first. Filter and hits are broadcast where they are small, else joined by shuffles.
All of it is built-in functions.

Defined results: a null URL or one without `://` has an empty host and path, is never listed and is allowed;
repeated URLs are judged alike, repeated or null entries of the list change nothing; an empty list blocks nothing; an
empty table gives no rows; further columns, of whatever name, are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_or_plain, written

#: (verdict, host, path)
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: What the bundled list is made of: hosts, their prefixes and zones, languages, and places of pages (fixed values).
LISTED_LABELS = ("ads-track", "spam-farm", "casino-win", "adult-x", "cheap-pills", "free-bets")
LISTED_PREFIXES = ("", "m.", "blog.")
LISTED_ZONES = ("com", "net", "org")
LISTED_LANGS = ("en", "de", "fr", "es")
LISTED_ENDS = ("", ".html")
LISTED_PAGES, UNLISTED_FIFTH = 1000, 3
PER_BLOCK = 5
BITS = 6
MOST = 1 << 20  # rows of a filter (16 MB) or of hits up to which they are broadcast
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER)
    tail = F.substring(rest, F.length(host) + 1, F.length(rest))
    return host, F.regexp_extract(tail, r"^[^?#]*", 0)


def canonical(host: Column, path: Column) -> Column:
    """Host without a leading www. plus path without an ending slash; null for URLs without a host."""
    return F.when(host != "", F.concat(F.regexp_replace(host, r"^www\.", ""), F.regexp_replace(path, r"/+$", "")))


def _bits(name: str) -> Column:
    """BITS places of 64, six bits of one hash each."""
    h = f"xxhash64('bits', {name})"
    return F.expr(" | ".join(f"shiftleft(1L, cast(shiftrightunsigned({h}, {6 * i}) & 63 as int))" for i in range(BITS)))


def _block(key: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(F.lit("block"), key), F.lit(blocks))


def bloom(listed: DataFrame, blocks: int) -> DataFrame:
    """(block, bits) of a table (canonical); at most `blocks` rows."""
    return listed.where("canonical is not null").groupBy(_block(F.col("canonical"), blocks).alias("block")).agg(F.bit_or(_bits("canonical")).alias("bits"))


def blocks_for(n: int) -> int:
    """A power of two of blocks for n listed URLs."""
    return 1 << (max(1, -(-n // PER_BLOCK)) - 1).bit_length()


def matched(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, else nulls."""
    rule = verdict = None
    for kind, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r)):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule = F.when(fits, F.lit(h + p)) if rule is None else rule.when(fits, F.lit(h + p))
        verdict = F.when(fits, F.lit(kind)) if verdict is None else verdict.when(fits, F.lit(kind))
    return (rule, verdict) if rules else (F.lit(None).cast("string"),) * 2


def judged(pages: DataFrame, listed: DataFrame, rules=RULES, blocks: int | None = None) -> DataFrame:
    """(page_id, host, path, rule, verdict, listed). listed: (canonical); blocks: of the filter, by default from the list's length."""
    host, path = host_and_path(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    rows = rows.withColumn("canonical", canonical(F.col("host"), F.col("path")))
    names = written(listed.select("canonical").where("canonical is not null").distinct(), "listed")
    blocks = blocks or blocks_for(names.count())
    keys = rows.select("canonical").where("canonical is not null").distinct().withColumn("block", _block(F.col("canonical"), blocks)).withColumn("own", _bits("canonical"))
    bits = bloom(names, blocks)
    possible = keys.join(F.broadcast(bits) if blocks <= MOST else bits, "block").where("(bits & own) = own").select("canonical")
    hits = written(possible.join(names, "canonical", "left_semi").select(F.col("canonical").alias("hit")), "hits")
    # URLs without a host get keys of their own, so that they don't meet in one task; no canonical URL begins like these
    key = F.coalesce("canonical", F.concat(F.lit("?"), F.coalesce(F.col("page_id").cast("string"), F.lit(""))))
    rule, verdict = matched(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("key", key).join(small_or_plain(hits, MOST), F.col("key") == F.col("hit"), "left").withColumn("listed", F.col("hit").isNotNull())
    return rows.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(verdict, F.when(F.col("listed"), "block").otherwise("allow")).alias("verdict"), "listed")


def bundled_list(spark: SparkSession) -> DataFrame:
    """(canonical): the list that the query judges by, from the fixed values above and no table: most of its URLs are no pages, and
    a fifth of the places of a listed host are not on it."""
    rows = spark.range(LISTED_PAGES).where(F.col("id") % 5 != UNLISTED_FIFTH)
    for name, values in (("prefix", LISTED_PREFIXES), ("label", LISTED_LABELS), ("zone", LISTED_ZONES), ("lang", LISTED_LANGS), ("end", LISTED_ENDS)):
        rows = rows.withColumn(name, F.explode(F.array(*map(F.lit, values))))
    return rows.select(F.concat("prefix", "label", F.lit(".example."), "zone", F.lit("/"), "lang", F.lit("/"), F.col("id").cast("string"), "end").alias("canonical"))
