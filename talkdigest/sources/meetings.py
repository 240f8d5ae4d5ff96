"""Transcripts as flat utterance rows, from documents, conversations or pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators.positions import attach
from ..operators.ranking import positions
from ..schema import ROLES, positive, require

COLUMNS = ["meeting_id", "agenda_no", "utt_no", "speaker", "text", "tokens", "n_tok", "tok_start", "tok_end", "char_start", "char_end"]
ID_BUCKET, ID_BUCKETS = 1024, 1 << 16  # neighbouring document ids a rank bucket at least, and buckets at most


def finished(rows: DataFrame) -> DataFrame:
    """Tokens, counts and positions for (meeting_id, agenda_no, utt_no, speaker, text)."""
    rows = rows.withColumn("tokens", T.words(F.col("text"))).withColumn("n_tok", F.size("tokens").cast("long")).withColumn("utt_no", F.col("utt_no").cast("long"))
    return attach(rows).select(*COLUMNS)


def retokenized(rows: DataFrame) -> DataFrame:
    """Utterances that were kept without their tokens, with them."""
    return rows.withColumn("tokens", T.words(F.col("text"))).select(*COLUMNS)


def from_documents(documents: DataFrame, per: int = 12) -> DataFrame:
    """Bundles of `per` consecutive documents of a language; a document is an agenda item, a sentence an utterance."""
    positive(per=per)
    require(documents, "doc_id any, lang string, text string")
    docs = documents.select("doc_id", F.coalesce("lang", F.lit("und")).alias("lang"), "text")
    low, high = docs.agg(F.min("doc_id"), F.max("doc_id")).first()
    width = max(ID_BUCKET, -(-((high or 0) - (low or 0) + 1) // ID_BUCKETS))  # so that the counts before a bucket fit one task
    docs = positions(docs, F.floor(F.col("doc_id") / width), ["doc_id"], ["lang"], "place")
    meeting = F.concat_ws("-", "lang", F.expr(f"place div {per}").cast("string"))
    rows = docs.select(meeting.alias("meeting_id"), F.pmod("place", F.lit(per)).cast("int").alias("agenda_no"), F.posexplode(T.sentences(F.col("text"))).alias("piece", "text"))
    utt = F.row_number().over(Window.partitionBy("meeting_id").orderBy("agenda_no", "piece")) - 1
    rows = rows.withColumn("utt_no", utt)
    speaker = F.element_at(F.array(*[F.lit(x) for x in ROLES]), (F.pmod("utt_no", F.lit(4)) + 1).cast("int"))
    return finished(rows.withColumn("speaker", speaker))


def from_conversations(conversations: DataFrame, grain: str = "turn") -> DataFrame:
    """A conversation is a meeting, a turn (or each sentence of it) an utterance, an exchange of two turns an agenda item."""
    rows = conversations.where("conv_id is not null").select(F.col("conv_id").cast("string").alias("meeting_id"), F.expr("turn div 2").cast("int").alias("agenda_no"), "turn", F.col("role").alias("speaker"), "text")
    if grain == "turn":
        return finished(rows.withColumn("utt_no", F.col("turn")))
    if grain != "sentence":
        raise ValueError(f"grain must be turn or sentence, not {grain}")
    rows = rows.select("meeting_id", "agenda_no", "turn", "speaker", F.posexplode(T.sentences(F.col("text"))).alias("piece", "text"))
    return finished(rows.withColumn("utt_no", F.row_number().over(Window.partitionBy("meeting_id").orderBy("turn", "piece")) - 1))


def from_pages(pages: DataFrame) -> DataFrame:
    """News-like transcripts: paragraphs are utterances; `headline` is the reference."""
    rows = pages.select(F.col("page_id").cast("string").alias("meeting_id"), T.headline(F.col("html")).alias("headline"), F.posexplode(T.paragraphs(F.col("html"))).alias("utt_no", "text"))
    return rows.withColumn("tokens", T.words(F.col("text"))).withColumn("n_tok", F.size("tokens").cast("long")).withColumn("utt_no", F.col("utt_no").cast("long"))
