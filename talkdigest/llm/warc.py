"""WARC: records from pages, and a Merkle audit of replicas.

Pages become WARC resource records in numbered volumes; a record's place in its volume and its byte offset follow
from the order of page ids. Leaves of a volume's tree are the SHA-256 of its records with their offset ranges, in
order; FAN ordered nodes make one node of the next level, up to a root a volume; those are the leaves of a tree over
ranges of volume numbers, up to one root over all. Every level is a table, written once. An audit compares the replicas'
roots first and goes down only from nodes that differ, so it reads hashes along damaged branches only. Leaves stand at ordinals, so a lost or additional record makes all later leaves of its volume differ; the records
of differing leaves are therefore matched by content and by page id before they are judged.

Defined results: null url or html are empty strings; repeated page ids are records of their own; a record that one
replica lacks is `missing` (or `extra`); one with the same bytes at another ordinal or offset is `moved`; one with the
same page id and other bytes is `damaged`, as is one whose id can't be read where a master's record is lacking; null page ids go to NULL_VOLUMES volumes
of negative numbers, by content; equal replicas and empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import written

FAN = 16  # four bits of a node's number
NULL_VOLUMES = 1024
#: Pages carry no time of capture, and equal pages must give equal records; a parameter of record().
DATE = "2020-01-01T00:00:00Z"
CRLF = "\r\n"


def record(url: Column, html: Column, page_id: Column, date: str = DATE) -> Column:
    body = F.coalesce(html, F.lit(""))
    head = [("WARC-Type", F.lit("resource")), ("WARC-Date", F.lit(date)), ("WARC-Record-ID", F.concat(F.lit("<urn:page:"), F.coalesce(page_id.cast("string"), F.lit("")), F.lit(">"))), ("WARC-Target-URI", F.coalesce(url, F.lit(""))),
            ("Content-Type", F.lit("text/html; charset=utf-8")), ("Content-Length", F.octet_length(body).cast("string"))]
    parts = [F.lit(f"WARC/1.0{CRLF}")] + [x for name, value in head for x in (F.lit(f"{name}: "), value, F.lit(CRLF))]
    return F.concat(*parts, F.lit(CRLF), body, F.lit(CRLF * 2))


def in_volumes(pages: DataFrame, volume_pages: int) -> DataFrame:
    """(volume, page_id, record, digest): volume_pages neighbouring page ids a volume."""
    rows = pages.select("page_id", record(F.col("url"), F.col("html"), F.col("page_id")).alias("record"))
    rows = rows.withColumn("digest", F.sha2(F.col("record").cast("binary"), 256))
    return rows.withColumn("volume", F.coalesce(F.floor(F.col("page_id") / volume_pages), -1 - F.pmod(F.xxhash64("digest"), F.lit(NULL_VOLUMES))).cast("long"))


def volumes(pages: DataFrame, volume_pages: int = 1000) -> DataFrame:
    """(volume, page_id, length, digest, record_no, at) of the records of pages."""
    rows = in_volumes(pages, volume_pages).select("volume", "page_id", F.octet_length("record").cast("long").alias("length"), "digest")
    order = Window.partitionBy("volume").orderBy("page_id", "digest")
    return rows.withColumn("record_no", F.row_number().over(order) - 1).withColumn("at", F.coalesce(F.sum("length").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))


def write_volumes(pages: DataFrame, path: str, volume_pages: int = 1000) -> None:
    """One WARC file a volume under path/volume=N; its bytes are the records in order, at the offsets that volumes() gives. The
    files' names end in .txt, as those of Spark's text writer do."""
    rows = in_volumes(pages, volume_pages).repartition("volume").sortWithinPartitions("volume", "page_id", "digest")
    # the writer ends each row by the line break that ends a record
    rows.select("volume", F.expr("substring(record, 1, length(record) - 2)").alias("value")).write.partitionBy("volume").option("lineSep", CRLF).text(path)


def parse(data: bytes) -> Iterator[tuple[int, int, str | None, bytes]]:
    """(offset, length, record id, record) of each record; one with a damaged head reaches to the next record's head."""
    at, size = 0, len(data)
    while at < size:
        head = data.find(b"\r\n\r\n", at)
        fields = dict(x.split(b": ", 1) for x in data[at:head].split(b"\r\n")[1:] if b": " in x) if head >= 0 and data.startswith(b"WARC/", at) else {}
        try:
            end = head + 8 + int(fields[b"Content-Length"])
        except (KeyError, ValueError):
            end = data.find(b"\r\n\r\nWARC/1.0\r\n", at) + 4
            end = end if end > at + 4 else size
        end = min(end, size)
        yield at, end - at, fields.get(b"WARC-Record-ID", b"").decode("utf-8", "replace") or None, data[at:end]
        at = end


def read_volumes(spark: SparkSession, path: str) -> DataFrame:
    """(volume, record_no, page_id, at, length, digest) of WARC files as write_volumes() lays them out; a file must fit a task's memory."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file in batch.to_pylist():
                rows = [(file["volume"], i, int(id_.rpartition(":")[2][:-1]) if id_ and re.fullmatch(r"<urn:page:-?\d+>", id_) else None, at, n, hashlib.sha256(data).hexdigest()) for i, (at, n, id_, data) in enumerate(parse(file["content"]))]
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [()] * 6, kinds)], names=["volume", "record_no", "page_id", "at", "length", "digest"])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.txt").option("recursiveFileLookup", True).load(path)
    files = files.select(F.regexp_extract("path", r"volume=(-?\d+)", 1).cast("long").alias("volume"), "content")
    return files.mapInArrow(run, "volume long, record_no long, page_id long, at long, length long, digest string")


def leaves(records: DataFrame) -> DataFrame:
    """(volume, node, hash) at level 0: a record's digest together with its offset range."""
    return records.select("volume", F.col("record_no").cast("long").alias("node"), F.sha2(F.concat_ws(":", "at", "length", "digest").cast("binary"), 256).alias("hash"))


def parents(level: DataFrame) -> DataFrame:
    kids = level.groupBy("volume", F.shiftright("node", 4).alias("node")).agg(F.sort_array(F.collect_list(F.struct("node", "hash"))).alias("kids"))
    return kids.select("volume", "node", F.sha2(F.array_join(F.transform("kids", lambda x: F.concat_ws(":", x["node"], x["hash"])), " ").cast("binary"), 256).alias("hash"))


def levels_for(*replicas: DataFrame) -> tuple[int, int]:
    """Levels above the leaves of a volume and above the volumes, enough for all replicas to end in one node each."""
    inside, above = 1, 1
    for records in replicas:
        most, low, high = records.agg(F.max("record_no"), F.min("volume"), F.max("volume")).first()
        inside = max(inside, -(-int(most or 0).bit_length() // 4))
        # the root's number is 0 for volumes from 0 on, and shifted negative numbers end at -1
        above = max(above, -(-max(int(x or 0).bit_length() for x in (low, high)) // 4))
    return inside, above


def tree(records: DataFrame, inside: int, above: int) -> list[DataFrame]:
    """Levels (volume, node, hash) from the leaves to one node a volume, then (volume 0, node, hash) from the volumes to the root
    (two if there are volumes of negative numbers); a node has at most FAN children. Each is a table, made from the one below."""
    out = [written(leaves(records), "leaves", True)]
    for _ in range(inside):
        out.append(written(parents(out[-1]), "level", True))
    for step in range(above):
        below = out[-1] if step else out[-1].select(F.lit(0).cast("long").alias("volume"), F.col("volume").alias("node"), "hash")
        out.append(written(parents(below), "level", True))
    return out


def root_hash(levels: list[DataFrame]) -> str:
    """One hash over all of tree(); that of no text for no records."""
    return hashlib.sha256("".join(f"{r['node']}:{r['hash']} " for r in sorted(levels[-1].collect(), key=lambda r: r["node"])).encode()).hexdigest()  # two rows at most


def differing(mine: list[DataFrame], other: list[DataFrame], above: int) -> DataFrame:
    """(volume, node) of the leaves under branches that differ or exist in one replica only."""
    found = None
    for depth, (a, b) in enumerate(zip(reversed(mine), reversed(other))):
        a = a.select("volume", "node", F.col("hash").alias("hash_a"))
        b = b.select("volume", "node", F.col("hash").alias("hash_b"))
        if found is not None:
            up = found.select(F.col("volume").alias("up_volume"), F.col("node").alias("up"))
            # the roots of volumes are the children of the lowest nodes over volumes
            own = (F.lit(0).cast("long"), F.shiftright("volume", 4)) if depth == above else (F.col("volume"), F.shiftright("node", 4))
            a, b = (x.join(up, (own[0] == F.col("up_volume")) & (own[1] == F.col("up")), "left_semi") for x in (a, b))
        # written at each level, as both replicas go down from it
        found = written(a.join(b, ["volume", "node"], "full").where(~F.col("hash_a").eqNullSafe(F.col("hash_b"))).select("volume", "node"), "branches", True)
    return found


def matched(rows: DataFrame, *keys: str) -> DataFrame:
    """(volume, keys, a, b) of rows (volume, run, record_no, page_id, at, length, digest, mine): the n-th record of the master with
    the n-th of the replica that has the same keys; either may be null."""
    rank = F.row_number().over(Window.partitionBy("volume", *keys, "mine").orderBy("record_no"))
    whole = F.struct("record_no", "page_id", "at", "length", "digest", "run")
    return rows.withColumn("rank", rank).groupBy("volume", *keys, "rank").agg(F.max(F.when(F.col("mine"), whole)).alias("a"), F.max(F.when(~F.col("mine"), whole)).alias("b"))


def single(pairs: DataFrame) -> DataFrame:
    """The rows of matched() that found no partner, as it takes them."""
    rows = pairs.where("a is null or b is null")
    return rows.select("volume", F.coalesce("a", "b").alias("x"), F.col("a").isNotNull().alias("mine")).select("volume", "x.*", "mine")


def aligned(rows: DataFrame) -> DataFrame:
    """(volume, a, b): rows as matched() takes them; by bytes, then by page id, then a record without a readable id with what is
    lacking in the same gap between records that have a partner."""
    whole = matched(rows, "digest")
    named = matched(single(whole), "page_id")
    both = whole.select("volume", "a", "b").unionByName(named.select("volume", "a", "b")).where("a is not null and b is not null")
    rest = single(named).withColumn("mate", F.lit(None).cast("long"))
    marks = [both.select("volume", f"{x}.*", F.lit(x == "a").alias("mine"), F.col("a.record_no").alias("mate")) for x in "ab"]
    order = Window.partitionBy("volume", "run", "mine").orderBy("record_no")
    gaps = rest.unionByName(marks[0]).unionByName(marks[1]).withColumn("gap", F.last("mate", True).over(order)).where("mate is null")
    # an id that can be read and has no partner is a record of its own
    gaps = gaps.withColumn("other", F.when(~F.col("mine"), F.col("page_id")))
    return both.unionByName(matched(gaps, "run", "gap", "other").select("volume", "a", "b"))


def audit(master: DataFrame, replica: DataFrame) -> DataFrame:
    """(volume, record_no, page_id, at, length, status, expected, found) of records that differ. Both: as volumes() gives."""
    master, replica = written(master, "records"), written(replica, "records")  # digests and offsets only
    inside, above = levels_for(master, replica)
    mine, other = tree(master, inside, above), tree(replica, inside, above)
    bad = differing(mine, other, above) if root_hash(mine) != root_hash(other) else mine[0].limit(0)
    bad = bad.select("volume", F.col("node").alias("record_no"))
    # neighbouring ordinals are a run; records move inside runs only
    bad = written(bad.withColumn("run", F.col("record_no") - F.row_number().over(Window.partitionBy("volume").orderBy("record_no"))), "differing")
    sides = [x.join(bad, ["volume", "record_no"]).select("volume", "run", F.col("record_no").cast("long").alias("record_no"), "page_id", "at", "length", "digest", F.lit(mine).alias("mine")) for x, mine in ((master, True), (replica, False))]
    rows = aligned(sides[0].unionByName(sides[1]))
    status = F.when(F.col("b").isNull(), "missing").when(F.col("a").isNull(), "extra").when(F.col("a.digest") != F.col("b.digest"), "damaged").otherwise("moved")
    return rows.select("volume", *[F.coalesce(f"a.{c}", f"b.{c}").alias(c) for c in ("record_no", "page_id", "at", "length")], status.alias("status"), F.col("a.digest").alias("expected"), F.col("b.digest").alias("found"))


def damaged_replica(pages: DataFrame) -> DataFrame:
    """The pages of a replica with planted faults: one character changed in some; the ends of some volumes lost; in others three
    pages lost in the middle and one that stands twice, so that all records behind them move."""
    at, volume = F.col("page_id") % 1000, F.floor(F.col("page_id") / 1000) % 7
    html = F.when(F.col("page_id") % 97 == 5, F.concat(F.lit("#"), F.expr("substring(html, 2)"))).otherwise(F.col("html"))
    lost = ((volume == 3) & (at >= 990)) | ((volume == 0) & at.between(230, 232))
    times = F.when(F.coalesce(lost, F.lit(False)), 0).when((volume == 0) & (at == 240), 2).otherwise(1)
    copies = F.explode(F.array_repeat(F.lit(1), times)).alias("copy")
    return pages.select("page_id", "url", html.alias("html"), copies).drop("copy")
