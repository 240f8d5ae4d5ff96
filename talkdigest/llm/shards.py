"""Sharding by proportional stratified interleaving.

Rows are shuffled by a seeded hash inside their source and ranked; a row of rank r among n gets the fractional
rank (2r + 1) / 2n. Sorting all rows by it interleaves the sources in proportion, so equal cuts of that order
hold the sources' mixture each, within one row a source. Counts of the shards differ by one at most.

Both global ranks come from counts of hash (or rank) buckets plus a row number inside a bucket, so a source
that holds a third of all rows is spread over many tasks and no row count reaches a single task.

Defined results: a null source is a source of its own, after the others; null text counts as empty; null,
repeated or tied ids are ordered by their content; repeated rows take a place each; empty table: no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import kept, small_or_plain

ROWS_A_BUCKET = 1_000_000


def hex_digits(n: int) -> int:
    """Of the seeded hash: as many as give buckets of up to about ROWS_A_BUCKET rows, 4,096 buckets at least."""
    digits = 3
    while n > ROWS_A_BUCKET * 16 ** digits:
        digits += 1
    return digits


def ranked(df: DataFrame, bucket: str, order: list, *by: str) -> DataFrame:
    """df with `place`, the 0-based rank in (bucket, *order) inside the groups `by`, without a task for each group."""
    keys = [*by, bucket]
    counts = df.groupBy(*keys).agg(F.count("*").alias("bucket_rows"))
    before = Window.partitionBy(*by).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("before", F.coalesce(F.sum("bucket_rows").over(before), F.lit(0)))
    inside = df.withColumn("inside", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)) - 1)
    counts = counts.select(*[F.col(c).alias(f"of_{c}") for c in keys], "before")
    on = F.lit(True)
    for c in keys:
        on = on & F.col(c).eqNullSafe(F.col(f"of_{c}"))
    return inside.join(counts, on).select(*df.columns, (F.col("before") + F.col("inside")).alias("place"))


def interleaved(documents: DataFrame, shards: int = 16, seed: int = 1) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) of the `rows` law."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = documents.select("doc_id", F.col("source").alias("stratum"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"),
                            F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary")).alias("shuffled"))
    rows = kept(rows)  # numbers and a hash; read by both ranks and their counts
    n = rows.count()
    digits = hex_digits(n)
    rows = rows.withColumn("hash_bucket", F.substring("shuffled", 1, digits))
    rows = ranked(rows, "hash_bucket", ["shuffled", F.asc_nulls_last("doc_id"), "size", "text_crc32"], "stratum").withColumnRenamed("place", "stratum_rank")
    totals = rows.groupBy(F.col("stratum").alias("of_stratum")).agg(F.count("*").alias("stratum_rows"))
    rows = rows.join(small_or_plain(totals, 100_000), F.col("stratum").eqNullSafe(F.col("of_stratum")))
    rows = rows.withColumn("fraction", (2 * F.col("stratum_rank") + 1) / (2.0 * F.col("stratum_rows")))
    rows = rows.withColumn("cut", F.floor(F.col("fraction") * 16 ** digits)).withColumn("all_rows", F.lit("all"))
    rows = ranked(rows, "cut", ["fraction", F.asc_nulls_last("stratum"), "shuffled", F.asc_nulls_last("doc_id"), "size", "text_crc32"], "all_rows")
    shard = F.expr(f"cast((place * {shards}) div {max(1, n)} as int)")
    first = F.expr(f"(shard * {max(1, n)}L + {shards - 1}) div {shards}")
    return rows.withColumn("shard", shard).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", (F.col("place") - first).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), F.col("stratum").alias("source"))
