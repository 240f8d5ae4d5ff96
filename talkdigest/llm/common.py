"""What the operators share: table access and written intermediate tables."""

from __future__ import annotations

import tempfile
import uuid

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
#: Blocks of 64 bits that keys leave a mark in, if they are too many to be broadcast: 5 MB at most.
SIEVE = 1 << 17


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Paths of tables written and frames kept, in order.
_written: list[str] = []
_kept: list[DataFrame] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share. Where the session names none, a local one is made if driver and executors are one
    process (tests); on a cluster that is an error."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = f"file://{tempfile.mkdtemp(prefix='talkdigest-')}"
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def written(df: DataFrame, name: str, light: bool = False) -> DataFrame:
    """Write df as Parquet into the shared folder and read it again: cuts lineage, survives lost executors.

    light: rows of a few numbers, far smaller than texts; they are put into a sixteenth as many files as a shuffle has partitions."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    if light:
        df = df.coalesce(max(4, int(spark.conf.get("spark.sql.shuffle.partitions")) // 16))
    df.write.parquet(path)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def kept(df: DataFrame) -> DataFrame:
    """df, kept on the executors' disks once it has been computed, for use by several jobs; what is lost with an executor is computed again."""
    _kept.append(df.persist(StorageLevel.DISK_ONLY))
    return _kept[-1]


def mark() -> tuple[int, int]:
    """Where release() shall begin."""
    return len(_written), len(_kept)


def release(spark: SparkSession, since: tuple[int, int], spare: int = 0) -> None:
    """Drop what was kept and delete what was written since a mark(), but for the last `spare` tables.

    For callers that have consumed, or written, all that the operators gave them since then."""
    hadoop, conf = spark.sparkContext._jvm.org.apache.hadoop.fs, spark.sparkContext._jsc.hadoopConfiguration()
    for path in (gone := _written[since[0]:len(_written) - spare]):
        where = hadoop.Path(path)
        where.getFileSystem(conf).delete(where, True)
    del _written[since[0]:since[0] + len(gone)]
    for frame in _kept[since[1]:]:
        frame.unpersist()
    del _kept[since[1]:]


def word_count(text):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def small_or_plain(df: DataFrame, most_rows: int) -> DataFrame:
    """df with a broadcast hint if it has at most most_rows rows, else as it is (a shuffled join follows)."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


def possible(rows: DataFrame, keys: DataFrame, on: str, code: Column | None = None, blocks: int = SIEVE) -> DataFrame:
    """All rows whose `on` is among that of keys, and some others: only the keys' marks are broadcast, in a table of fixed size.

    code: a hash of `on`."""
    code = F.xxhash64(on) if code is None else code
    block = F.pmod(code, F.lit(blocks).cast("long"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.call_function("shiftrightunsigned", code, F.lit(58)).cast("int"))
    marks = keys.groupBy(block.alias("sieve_block")).agg(F.bit_or(bit).alias("sieve_marks"))
    found = rows.withColumn("sieve_block", block).join(F.broadcast(marks), "sieve_block").where(F.col("sieve_marks").bitwiseAND(bit) != 0)
    return found.drop("sieve_block", "sieve_marks")


def matching(rows: DataFrame, keys: DataFrame, on: str, most_rows: int, code: Column | None = None, blocks: int = SIEVE) -> DataFrame:
    """rows joined with keys, which hold each `on` once. Of more than most_rows keys only the marks are broadcast; most rows without
    a key fall through before the shuffle that the exact join takes."""
    if keys.count() <= most_rows:
        return rows.join(F.broadcast(keys), on)
    return possible(rows, keys, on, code, blocks).join(keys.hint("merge"), on)


def few_or_shuffled(keys: DataFrame, most_rows: int) -> DataFrame:
    """A written table of keys as a side of a join: broadcast if it has few rows, else always shuffled."""
    return F.broadcast(keys) if keys.count() <= most_rows else keys.hint("merge")
