"""Line deduplication by a fixed-depth log-template tree.

A line goes down the tree by its token count and its first DEPTH tokens; tokens with a digit are variable fields
(`<*>`) from the start. In a leaf, the tokens that more than half of its distinct lines have at a place are the
template's, the other places are variable; a line whose remaining tokens agree with the template at SIMILAR of
the places or more belongs to it, any other line is a template of its own. A template that min_docs documents or
more hold is recurring: its first line (least doc_id, then line) stays, all others are dropped.

Everything is counted over all lines; leaves are pre-aggregated to distinct lines before tokens are counted, so a
line that a third of the documents hold is one row there.

Lines of fewer than min_tokens tokens have no template: with `short`, such lines are recurring if min_docs documents
hold the same tokens, digits included; without it they are never dropped.

Defined results: null text stays null, with 0 lines; blank lines are never dropped; rows with the same doc_id and text are one
document, and a doc_id counts once however many texts it has; a null doc_id is never dropped from; documents whose lines all
recur keep their row with an empty text; empty table: no rows; further columns stay, but for deduplicated() those named
n_lines or n_dropped, which give way to its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SIEVE, few_or_shuffled, matching, written

DEPTH = 3
SIMILAR = 0.6
FIELD = "<*>"
MOST = 50_000  # rows of keys up to which a side is broadcast: a few MB of the driver, whatever the input


def _lines(text):
    return F.split(text, "\n", -1)


def _masked(tokens):
    return F.transform(tokens, lambda t: F.when(t.rlike("[0-9]"), FIELD).otherwise(t))


def _tokens(text):
    """An array of tokens for each line; white space becomes spaces first, as a plain split is far faster than a pattern."""
    for space in "\t\x0b\x0c\r":
        text = F.replace(text, F.lit(space), F.lit(" "))
    return F.transform(F.split(text, "\n", -1), lambda line: F.array_remove(F.split(line, " ", -1), ""))


def placed_in_leaves(documents: DataFrame, min_tokens: int = 3, depth: int = DEPTH, short: bool = False) -> DataFrame:
    """(doc_id, text_key, line_no, tokens, leaf) of the lines that can be dropped; a short line's leaf is that of its very tokens."""
    rows = documents.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("text_key"), F.posexplode(_tokens(F.col("text"))).alias("line_no", "tokens"))
    leaf = F.xxhash64(F.size("tokens"), _masked(F.slice("tokens", 1, depth)))
    leaf = F.when(F.size("tokens") < min_tokens, F.xxhash64(F.lit("short"), "tokens")).otherwise(leaf)
    return rows.where(F.size("tokens") >= (1 if short else min_tokens)).withColumn("leaf", leaf)


def parsed(rows: DataFrame) -> DataFrame:
    """(doc_id, text_key, line_no, leaf, tokens, line_key) of rows of placed_in_leaves() and `uniform`, variable fields masked; a
    leaf of one line only needs no tokens."""
    rows = rows.select("doc_id", "text_key", "line_no", "leaf", F.when(~F.col("uniform"), _masked(F.col("tokens"))).alias("tokens"))
    return rows.withColumn("line_key", F.when(F.col("tokens").isNull(), F.col("leaf")).otherwise(F.xxhash64("leaf", "tokens")))


def generalised(distinct: DataFrame, depth: int = DEPTH, similar: float = SIMILAR) -> DataFrame:
    """(line_key, template) of distinct lines (leaf, line_key, tokens)."""
    tail = distinct.select("leaf", F.posexplode(F.expr(f"slice(tokens, {depth + 1}, greatest(size(tokens) - {depth}, 0))")).alias("place", "token"))
    counts = tail.groupBy("leaf", "place", "token").agg(F.count("*").alias("n"))
    common = counts.groupBy("leaf", "place").agg(F.max_by("token", F.struct("n", "token")).alias("token"), F.max("n").alias("most"), F.sum("n").alias("n"))
    common = common.select("leaf", F.struct("place", F.when(F.col("most") * 2 > F.col("n"), F.col("token")).otherwise(FIELD).alias("token")).alias("fixed"))
    templates = common.groupBy("leaf").agg(F.transform(F.sort_array(F.collect_list("fixed")), lambda x: x["token"]).alias("template_tail"))
    # templates are long and as many as the leaves: never broadcast
    rows = distinct.join(written(templates, "templates").hint("merge"), "leaf", "left").withColumn("tail", F.expr(f"slice(tokens, {depth + 1}, greatest(size(tokens) - {depth}, 0))"))
    same = F.aggregate(F.arrays_zip("tail", "template_tail"), F.lit(0), lambda a, x: a + F.when(x["tail"] == x["template_tail"], 1).otherwise(0))
    fits = (F.size("tail") == 0) | (F.coalesce(same, F.lit(0)) >= similar * F.size("tail"))
    return rows.select("line_key", F.when(fits, F.xxhash64(F.lit("leaf"), "leaf")).otherwise(F.xxhash64(F.lit("line"), "line_key")).alias("template"))


def _sieved(lines: DataFrame, leaves: DataFrame) -> DataFrame:
    """lines joined with leaves (leaf, uniform)."""
    return matching(lines, leaves, "leaf", MOST, F.col("leaf"), SIEVE)


def recurring(documents: DataFrame, min_docs: int = 3, min_tokens: int = 3, short: bool = False) -> DataFrame:
    """(doc_id, text_key, drops array<int>): the line numbers that a document loses, ascending.

    Leaves, keys and first places are tables of their own, broadcast where they are few; else the joins are shuffled, and a line
    or template that a third of all rows have is split at run time."""
    lines = placed_in_leaves(documents, min_tokens, short=short)
    # a leaf of fewer rows than min_docs, or of one document, holds no recurring template
    key = F.xxhash64("tokens")
    leaves = lines.groupBy("leaf").agg(F.count("*").alias("n"), F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), (F.min(key) == F.max(key)).alias("uniform"))
    leaves = written(leaves.where((F.col("n") >= min_docs) & (F.col("a") < F.col("b"))).select("leaf", "uniform"), "leaves")
    held = written(parsed(_sieved(lines, leaves)), "lines")
    varied = held.where("tokens is not null")
    distinct = varied.groupBy("leaf", "line_key").agg(F.first("tokens").alias("tokens"))
    keys = written(generalised(distinct), "line-keys")
    place = ("doc_id", "text_key", "line_no")
    placed = varied.select(*place, "line_key").join(few_or_shuffled(keys, MOST), "line_key").select(*place, "template")
    placed = placed.unionByName(held.where("tokens is null").select(*place, F.xxhash64(F.lit("leaf"), "leaf").alias("template")))
    first = placed.groupBy("template", "doc_id").agg(F.min(F.struct("text_key", "line_no")).alias("at")).groupBy("template").agg(F.count("*").alias("docs"), F.min(F.struct("doc_id", "at.text_key", "at.line_no")).alias("first"))
    first = written(first.where(F.col("docs") >= min_docs).select("template", "first"), "firsts")
    again = placed.join(few_or_shuffled(first, MOST), "template").where(F.struct(*place) != F.col("first"))
    return again.groupBy("doc_id", "text_key").agg(F.sort_array(F.collect_set("line_no")).alias("drops"))


def _without(text: Column, drops: Column) -> Column:
    """text without the lines at `drops` (ascending, all within): the runs of lines between them, each one slice."""
    def runs(lines):
        start = lambda i: F.when(i == 0, F.lit(0)).otherwise(drops[i - 1] + 1)
        end = lambda i: F.when(i == F.size(drops), F.size(lines)).otherwise(drops[i])
        return F.flatten(F.transform(F.sequence(F.lit(0), F.size(drops)), lambda i: F.slice(lines, start(i) + 1, end(i) - start(i))))

    # the lines are cut once: inside a lambda over them, not for each run
    return F.array_join(F.element_at(F.transform(F.array(_lines(text)), runs), 1), "\n")


def _joined(documents: DataFrame, min_docs: int, min_tokens: int, short: bool) -> DataFrame:
    """(doc, cleaned, drops)."""
    drops = recurring(documents.select("doc_id", "text"), min_docs, min_tokens, short).select(F.col("doc_id").alias("drop_id"), F.col("text_key").alias("drop_key"), "drops")
    rows = documents.select(F.struct(*[F.col(f"`{c}`") for c in documents.columns]).alias("doc"))
    rows = rows.join(drops, (F.col("doc.doc_id") == F.col("drop_id")) & (F.xxhash64("doc.text") == F.col("drop_key")), "left")
    text = F.col("doc.text")
    return rows.withColumn("cleaned", F.when(F.col("drops").isNull(), text).otherwise(_without(text, F.col("drops"))))


def cleaned(documents: DataFrame, min_docs: int = 3, min_tokens: int = 3, short: bool = False) -> DataFrame:
    """documents, all columns as they are, with `text` without recurring lines."""
    rows = _joined(documents, min_docs, min_tokens, short)
    return rows.select(*[F.col("cleaned").alias("text") if c == "text" else F.col(f"doc.`{c}`") for c in documents.columns])


def deduplicated(documents: DataFrame, min_docs: int = 3, min_tokens: int = 3, short: bool = False) -> DataFrame:
    """documents with `text` without recurring lines, and n_lines, n_dropped; further columns stay."""
    rows = _joined(documents, min_docs, min_tokens, short)
    names, text = [c for c in documents.columns if c not in ("n_lines", "n_dropped")], F.col("doc.text")
    return rows.select(*[F.col("cleaned").alias("text") if c == "text" else F.col(f"doc.`{c}`") for c in names],
                       F.when(text.isNull(), 0).otherwise(F.size(_lines(text))).alias("n_lines"), F.coalesce(F.size("drops"), F.lit(0)).alias("n_dropped"))
