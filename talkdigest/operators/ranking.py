"""Global 0-based positions without a global sort: counts of ordered buckets plus row numbers inside a bucket."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def positions(df: DataFrame, bucket: Column, order: list[str], by: list[str], name: str) -> DataFrame:
    """df with `name`: the place in (bucket, *order) within `by`. bucket must grow with order, so that one hot group spreads over tasks."""
    rows = df.withColumn("rank_bucket", bucket)
    keys = [*by, "rank_bucket"]
    before = Window.partitionBy(*[f"of_{c}" for c in by]).orderBy("of_rank_bucket").rowsBetween(Window.unboundedPreceding, -1)
    counts = rows.groupBy(*[F.col(c).alias(f"of_{c}") for c in keys]).agg(F.count("*").alias("bucket_rows"))
    counts = counts.withColumn("before_bucket", F.coalesce(F.sum("bucket_rows").over(before), F.lit(0))).drop("bucket_rows")
    rows = rows.withColumn("in_bucket", F.row_number().over(Window.partitionBy(*keys).orderBy(*order)) - 1)
    on = F.lit(True)
    for c in keys:
        on = on & F.col(c).eqNullSafe(F.col(f"of_{c}"))
    return rows.join(counts, on).select(*df.columns, (F.col("before_bucket") + F.col("in_bucket")).cast("long").alias(name))


def text_bucket(column: Column, n_bytes: int = 8) -> Column:
    """An order-preserving bucket of a string: its first bytes."""
    return F.substring(F.hex(column.cast("binary")), 1, 2 * n_bytes)
