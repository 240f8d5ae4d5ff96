"""MinHash near-duplicates by an LSH forest, confirmed on full shingle sets.

Each set of shingles has one signature of TREES * DEPTH minima. Tree t orders all signatures by their minima from
place DEPTH * t on, so sets that are alike stand next to each other in some orders, with a long common prefix. A region
is a run of equal prefixes of DEPTH minima; inside it, the order of the deeper minima puts the longest common prefixes
side by side, so that the depth adapts to how dense a region is.

Equal sets are one class first. Candidates come in two passes over the forest, so that a dense region costs no squares.
First each set meets the one before it in the order and the region's head; confirmed links are joined to components. Then
only regions that still hold several components matter: in one of up to SMALL sets all pairs are compared, by one matrix
product. The sets of larger ones, of all trees together, go through an exact set join: items are ordered from rare to
common, and two sets at the wanted similarity share one of the first items of both (of each set's n items, the first
n - ceil(0.8 n) + 1). Sets that share such an item are a group; a group of more than TILE sets is compared tile by tile. No
pair of a region is left out, whatever its size. Candidates are confirmed by the exact Jaccard of their whole sets (64-bit
hashes of shingles). Components come from alternating large-star and small-star steps over written tables.

A link between components that no other link joins is missed only if its sets share no region in any tree: with probability
(1 - 0.8^4)^TREES, 3e-6, at similarity 0.8, and far more rarely if they are more alike. Regions of more than HEAVY rows are
dealt to several tasks in the first pass, where chains then break; the second pass compares all the same.

Defined results: null, empty or word-less text: no shingles, a class of its own, kept; texts with fewer words than a
shingle: the whole sequence as one; equal sets are linked; repeated rows with one doc_id share class and decision; a
null doc_id takes no part in links, has no component and is kept; empty table: no rows; further columns, of whatever name,
are ignored by clustered() and kept by deduplicated().
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import few_or_shuffled, kept, matching, possible, written

TREES, DEPTH, DEEPER = 24, 4, 8
SMALL = 128  # sets of a region up to which all its pairs are compared at once
TILE = 256  # sets of a tile of a larger group
CELLS = 1 << 20  # counts by which items are ordered from rare to common; any order gives all pairs
HEAVY = 50_000  # rows of a region from which on several tasks chain it
MOST = 50_000  # rows of keys up to which a side is broadcast: a few MB of the driver, whatever the input
BLOCK = 2048
MULTIPLIERS = np.array([xxhash.xxh3_64_intdigest(b"minimum %d" % i) | 1 for i in range(TREES * DEPTH)], np.uint64)
MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)]


def shingles(text: str | None, words: int = 4) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a text, A-Z lower-cased."""
    found = (text or "").encode().lower().split()  # bytes: ASCII white space and letters only
    n = len(found)
    if not n:
        return np.empty(0, np.uint64)
    codes = np.fromiter(map(xxhash.xxh3_64_intdigest, found), np.uint64, n)
    width = min(words, n)
    out = np.full(n - width + 1, width * 0x9E3779B1, np.uint64)
    for i in range(width):
        out = (out ^ codes[i:n - width + 1 + i]) * MIX[0]
        out ^= out >> np.uint64(31)
    return np.unique(out * MIX[1])


def signature(items: np.ndarray) -> np.ndarray:
    least = np.full(len(MULTIPLIERS), 0xFFFFFFFF, np.uint64)
    for i in range(0, len(items), BLOCK):
        least = np.minimum(least, (MULTIPLIERS[:, None] * items[None, i:i + BLOCK] >> np.uint64(32)).min(axis=1))
    return least.astype(np.uint32)


def _signer(words: int):
    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, keys, signatures = [], [], []
            for text in batch.column(1):
                items = shingles(text.as_py(), words)
                counts.append(len(items))
                keys.append(xxhash.xxh3_128_digest(items.tobytes()) if len(items) else None)
                signatures.append(signature(items).astype(">u4").tobytes() if len(items) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(keys, pa.binary()), pa.array(signatures, pa.binary())], names=["doc_id", "n_shingles", "set_key", "signature"])

    return sign


def _brancher(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each set and tree: id, region (hash of tree and first DEPTH minima), the start of the minima after."""
    for batch in batches:
        for at in range(0, batch.num_rows, 1024):
            part = batch.slice(at, 1024)
            ids = part.column(0).to_numpy()
            minima = np.frombuffer(b"".join(part.column(1).to_pylist()), ">u4").astype(np.uint64).reshape(len(ids), -1)
            for tree in range(TREES):
                order = np.roll(minima, -DEPTH * tree, axis=1)
                region = np.full(len(ids), (tree + 1) * int(MIX[2]) % 2 ** 64, np.uint64)
                for i in range(DEPTH):
                    region = (region ^ order[:, i]) * MIX[0]
                    region ^= region >> np.uint64(29)
                deeper = ((order[:, DEPTH:DEPTH + DEEPER] * MIX[1]) >> np.uint64(56)).astype(np.uint8)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(region.view(np.int64)), pa.array([x.tobytes() for x in deeper], pa.binary())], names=["id", "region", "deeper"])


def _shared(regions: np.ndarray) -> np.ndarray:
    """Places of rows in a region with another row of the batch, or perhaps with one of the batches beside it."""
    same = np.zeros(len(regions), bool)
    same[1:] = regions[1:] == regions[:-1]
    same[:-1] |= same[1:]
    same[0] = same[-1] = True
    return np.flatnonzero(same)


def _pairs(a: list[int], b: list[int]) -> pa.RecordBatch:
    x, y = np.array(a, np.int64), np.array(b, np.int64)
    pairs = np.unique(np.stack([np.minimum(x, y), np.maximum(x, y)], 1), axis=0)
    pairs = pairs[pairs[:, 0] < pairs[:, 1]]
    return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])


def _chained(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by region, deeper minima, id: each with the row before and with the region's head."""
    last = head = before = None
    for batch in batches:
        regions, ids, a, b = batch.column(0).to_numpy(), batch.column(1).to_numpy(), [], []
        for i in _shared(regions) if len(regions) else ():
            id_ = int(ids[i])
            if regions[i] != last:
                last, head = regions[i], id_
            else:
                a += (head, before)
                b += (id_, id_)
            before = id_
        if a:
            yield _pairs(a, b)


def shared_items(sets: list[np.ndarray], cells: int = 1 << 23) -> np.ndarray:
    """Sizes of all pairwise intersections, by matrix products over the items that two sets or more hold."""
    columns = max(1, cells // len(sets))
    n, rows = len(sets), np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    _, place, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    number = np.cumsum(counts > 1) - 1
    some = counts[place] > 1
    rows, place = rows[some], number[place[some]]
    out = np.zeros((n, n), np.float32)
    for at in range(0, int(number[-1]) + 1 if len(number) else 0, columns):
        inside = (place >= at) & (place < at + columns)
        grid = np.zeros((n, min(columns, int(number[-1]) + 1 - at)), np.float32)
        grid[rows[inside], place[inside] - at] = 1
        out += grid @ grid.T
    return out.astype(np.int64)


def _joining(percent: int):
    def links(ids: list[int], owners: list[int], sets: list[np.ndarray]) -> Iterator[tuple[int, int]]:
        """Confirmed pairs that join components of a block, each once."""
        sizes = np.array([len(x) for x in sets])
        shared = shared_items(sets)
        alike = np.triu(100 * shared >= percent * (sizes[:, None] + sizes[None, :] - shared), 1)
        parent = {c: c for c in owners}

        def find(c):
            while parent[c] != c:
                parent[c] = c = parent[parent[c]]
            return c

        for i, j in zip(*np.nonzero(alike)):
            x, y = find(owners[i]), find(owners[j])
            if x != y:
                parent[x] = y
                yield min(ids[i], ids[j]), max(ids[i], ids[j])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by block; a block has about 2 * TILE rows at most (more only where an id has several sets)."""
        last, ids, owners, sets = None, [], [], []
        for batch in batches:
            found = []
            for block, id_, owner, items in zip(*(batch.column(c) for c in range(4))):
                block = block.as_py()
                if block != last:
                    if len(sets) > 1:
                        found += links(ids, owners, sets)
                    last, ids, owners, sets = block, [], [], []
                ids.append(id_.as_py())
                owners.append(owner.as_py())
                sets.append(np.frombuffer(items.as_py(), np.uint64))
            if found:
                yield _pairs(*map(list, zip(*found)))
        if len(sets) > 1 and (found := list(links(ids, owners, sets))):
            yield _pairs(*map(list, zip(*found)))

    return run


def forest(sets: DataFrame) -> DataFrame:
    """(id, region, deeper) of (id, signature), TREES rows a set."""
    return sets.select("id", "signature").mapInArrow(_brancher, "id long, region long, deeper binary")


def candidates(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct (a, b), a < b, of (id, signature): chains and heads of regions; and (id) of all sets that share a region with another.

    A region is in one task, one of more than HEAVY rows in several, where it is chained in parts."""
    rows = forest(sets)
    heavy = kept(rows.groupBy("region").count().where(F.col("count") > HEAVY).select("region", F.ceil(F.col("count") / HEAVY).alias("parts")))
    some = heavy.limit(1).count() > 0
    dealt = rows
    if some:
        dealt = rows.join(F.broadcast(heavy), "region", "left")  # of a share 1 / HEAVY of the rows at most
        dealt = dealt.withColumn("region", F.when(F.col("parts").isNull(), F.col("region")).otherwise(F.xxhash64("region", F.pmod(F.xxhash64("id"), F.col("parts")))))
    dealt = dealt.repartition("region").sortWithinPartitions("region", "deeper", "id")
    pairs = kept(dealt.select("region", "id").mapInArrow(_chained, "a long, b long").distinct())
    ends = pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id")))
    if some:
        ends = ends.unionByName(rows.join(F.broadcast(heavy.select("region")), "region", "left_semi").select("id"))
    return pairs, kept(ends.distinct())


def _cell_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(cell, n): how many items of a task's sets fall into each of CELLS cells."""
    counts = np.zeros(CELLS, np.int64)
    for batch in batches:
        for items in batch.column(0):
            np.add.at(counts, np.frombuffer(items.as_py(), np.uint64).view(np.int64) & (CELLS - 1), 1)
    cells = np.flatnonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(cells, pa.int64()), pa.array(counts[cells], pa.int64())], names=["cell", "n"])


def _first_items(counts, percent: int):
    """(item, id, component) of (id, component, items): of each set's n items the first n - ceil(percent * n / 100) + 1, those of the
    least counts first; two sets at the similarity share one of these."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for id_, component, items in zip(*batch.columns):
                item = np.frombuffer(items.as_py(), np.uint64).view(np.int64)
                keep = len(item) + -percent * len(item) // 100 + 1
                first = item[np.lexsort((item, counts.value[item & (CELLS - 1)]))[:keep]]
                same = lambda x: pa.array(np.full(len(first), x.as_py(), np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(first), same(id_), same(component)], names=["item", "id", "component"])

    return run


def sharing(members: DataFrame, items: DataFrame, percent: int) -> DataFrame:
    """(block, id, component): blocks in which all pairs of members (id, component) of different components meet that can have a
    Jaccard of percent / 100; an exact set join by first items."""
    sets = members.join(items, "id").select("id", "component", "items")
    counts = np.zeros(CELLS, np.int64)
    found = sets.select("items").mapInArrow(_cell_counts, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()  # CELLS rows at most
    counts[found["cell"].to_numpy()] = found["n"].to_numpy()
    order = members.sparkSession.sparkContext.broadcast(counts)
    first = written(sets.mapInArrow(_first_items(order, percent), "item long, id long, component long").distinct(), "first-items", True)
    return tiled(first).select("block", "id", "component")


def tiled(first: DataFrame) -> DataFrame:
    """(item, block, id, component) of (item, id, component): the sets of an item, if of several components, so dealt to blocks of up to
    about 2 * TILE sets that all pairs across components meet. As pairs within a component need not meet, the item's most
    frequent component is cut into tiles that meet the tiles of all others, and only those meet each other."""
    counts = first.groupBy("item", "component").agg(F.count("*").alias("n"))
    groups = counts.groupBy("item").agg(F.sum("n").alias("size"), F.max(F.struct("n", "component")).alias("main")).where(F.col("main.n") < F.col("size"))
    groups = written(groups.select("item", F.col("main.component").alias("main"), F.ceil(F.col("main.n") / TILE).alias("tiles"), F.ceil((F.col("size") - F.col("main.n")) / TILE).alias("others")), "groups", True)
    is_main = F.col("component") == F.col("main")
    own = F.pmod(F.xxhash64("id"), F.when(is_main, F.col("tiles")).otherwise(F.col("others")))
    upto = lambda n: F.sequence(F.lit(0).cast("long"), F.col(n) - 1)
    met = F.transform(upto("others"), lambda u: F.struct(F.lit(0).alias("kind"), own.alias("x"), u.alias("y")))
    meets = F.transform(upto("tiles"), lambda t: F.struct(F.lit(0).alias("kind"), t.alias("x"), own.alias("y")))
    beside = F.transform(F.filter(upto("others"), lambda u: u != own), lambda u: F.struct(F.lit(1).alias("kind"), F.least(u, own).alias("x"), F.greatest(u, own).alias("y")))
    rows = matching(first, groups, "item", MOST).withColumn("at", F.explode(F.when(is_main, met).otherwise(F.concat(meets, beside))))
    return rows.select("item", F.xxhash64("item", "at.kind", "at.x", "at.y").alias("block"), "id", "component")


def crossing(sets: DataFrame, joined: DataFrame, items: DataFrame, percent: int) -> DataFrame:
    """(a, b): confirmed links between components (id, component), from all pairs of each region; sets: (id, signature), items: (id, items).

    A set's items go to each of its blocks once, and pairs are formed inside a block only."""
    rows = written(forest(sets).select("region", "id").join(joined, "id", "left").select("region", "id", F.coalesce("component", "id").alias("component")), "forest", True)
    mixed = rows.groupBy("region").agg(F.count("*").alias("size"), F.min("component").alias("low"), F.max("component").alias("high"), F.bit_xor(F.xxhash64("id")).alias("members"))
    mixed = written(mixed.where("low < high").select("region", "size", "members"), "mixed", True)
    inside = matching(rows, mixed, "region", MOST)
    # regions of the same sets in several trees are one block
    blocks = inside.where(F.col("size") <= SMALL).select(F.xxhash64("members", "size").alias("block"), "id", "component")
    large = inside.where(F.col("size") > SMALL)
    if large.limit(1).count():
        members = written(large.select("id", "component").distinct(), "dense", True)
        blocks = blocks.unionByName(sharing(members, items, percent))
    blocks = blocks.distinct().join(items, "id")
    return blocks.repartition("block").sortWithinPartitions("block", "id").select("block", "id", "component", "items").mapInArrow(_joining(percent), "a long, b long")


def _sets(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingles(t.as_py(), words).tobytes() for t in batch.column(1)], pa.binary())], names=["id", "items"])

    return run


def _alike(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
                small, large = min(len(x), len(y)), max(len(x), len(y))
                if 100 * small < percent * large:
                    keep.append(False)
                    continue
                both = np.concatenate([x, y])
                both.sort()
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(100 * shared >= percent * (len(x) + len(y) - shared))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], names=["a", "b"])

    return run


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs whose sets have a Jaccard of percent / 100 or more."""
    rows = pairs.join(sets.select(F.col("id").alias("a"), F.col("items").alias("x")), "a").join(sets.select(F.col("id").alias("b"), F.col("items").alias("y")), "b")
    return rows.select("a", "b", "x", "y").mapInArrow(_alike(percent), "a long, b long")


def between(pairs: DataFrame, joined: DataFrame) -> DataFrame:
    """The pairs whose ends are in different components; joined: (id, component), others are alone."""
    rows = pairs.join(joined.select(F.col("id").alias("a"), F.col("component").alias("ca")), "a", "left").join(joined.select(F.col("id").alias("b"), F.col("component").alias("cb")), "b", "left")
    return rows.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b")


def components(edges: DataFrame) -> DataFrame:
    """(id, component): the least id reachable over edges (a, b), for the ids that have an edge."""
    edges = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "edges", True)
    mark = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u > v").distinct()
        edges = written(small, "edges", True)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if now == mark:
            break
        mark = now
    low = edges.select(F.col("v").alias("id")).distinct().select("id", F.col("id").alias("component"))
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(low)


def clustered(documents: DataFrame, words: int = 4, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept), one row a document; doc_id is a whole number."""
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    signed = kept(texts.mapInArrow(_signer(words), "doc_id long, n_shingles long, set_key binary, signature binary"))
    usable = signed.where("set_key is not null and doc_id is not null")
    # equal sets have equal signatures; a doc_id that stands for two sets (repeated ids) gets both, and its links join
    sets = kept(usable.groupBy("set_key").agg(F.min("doc_id").alias("id"), F.first("signature").alias("signature"), F.count("*").alias("copies")))
    pairs, ends = candidates(sets)
    owners = ends.withColumnRenamed("id", "doc_id")
    # texts are not shuffled for this: of many ids only marks are broadcast, and sets of other texts that pass meet no pair
    wanted = texts.join(F.broadcast(owners), "doc_id", "left_semi") if ends.count() <= MOST else possible(texts, owners, "doc_id")
    # dealt by id once: the joins with it need no further shuffle of whole sets
    parts = int(documents.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    items = kept(wanted.mapInArrow(_sets(words), "id long, items binary").repartition(parts, "id"))
    star = pairs.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")
    links = written(confirmed(star, items, percent).distinct(), "links", True)
    links = links.unionByName(written(confirmed(between(pairs, components(links)), items, percent).distinct(), "links", True))
    mixed = matching(sets, ends, "id", MOST)
    found = components(links.unionByName(crossing(mixed, components(links), items, percent)))
    # documents whose set nobody else has, and that no link reaches, need no row here
    known = sets.join(found, "id", "left").select("set_key", F.coalesce("component", "id").alias("class_component"), "id", "copies").where("copies > 1 or class_component <> id")
    known = few_or_shuffled(written(known.select("set_key", "class_component"), "classes", True), MOST)
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("class_component", "doc_id"))
    out = signed.join(known, "set_key", "left").select("doc_id", "n_shingles", component.alias("component_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def deduplicated(documents: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """The rows of documents that stay: one document of each component."""
    gone = clustered(documents, words, percent).where(~F.col("kept")).select(F.col("doc_id").alias("gone_id")).distinct()
    rows = documents.select(F.struct(*[F.col(f"`{c}`") for c in documents.columns]).alias("doc"))
    return rows.join(gone, F.col("doc.doc_id") == F.col("gone_id"), "left_anti").select("doc.*")
