"""Reading and writing of meetings with declared schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..schema import require

FORMATS = ("parquet", "orc", "json", "csv", "text")


def read_meetings(spark: SparkSession, path: str, columns: list[str] | None = None, where: str | None = None, schema: str | None = None, fmt: str = "parquet") -> DataFrame:
    """A scan with pruned columns and a pushed filter; text formats need a schema (none is inferred)."""
    if fmt not in FORMATS:
        raise ValueError(f"fmt must be one of {', '.join(FORMATS)}, not {fmt}")
    reader = spark.read.format(fmt)
    if fmt in ("json", "csv"):
        if not schema:
            raise ValueError(f"{fmt} needs a schema")
        reader = reader.schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    df = reader.load(path)
    if schema and fmt in ("parquet", "orc"):
        require(df, schema)
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def write(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "errorifexists") -> None:
    """One folder of files; `by` partitions them for pruning. Text takes one string column."""
    if fmt not in FORMATS:
        raise ValueError(f"fmt must be one of {', '.join(FORMATS)}, not {fmt}")
    writer = df.write.format(fmt).mode(mode)
    if fmt == "csv":
        writer = writer.option("header", True).option("escape", '"')
    (writer.partitionBy(*by) if by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int = 256, key: str = "meeting_id") -> None:
    """A table clustered by meeting: later groupings and joins by meeting need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
