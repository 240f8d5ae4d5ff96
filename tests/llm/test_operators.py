"""Operators of the training-data pipeline against brute force, library results and edge cases."""

import base64
import collections
import hashlib
import math
import os
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F

import corpus_pipeline
from talkdigest.llm import bpe, fingerprints, langid, lines, mixing, neardup, queries, shards, topk, urls, warc

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, size string, row string, shard string"


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").cache()


@pytest.fixture(scope="module")
def edges(spark):
    """Nulls anywhere, empty and very long texts, repeated rows, ties, extra columns with the operators' own names."""
    long = " ".join(f"w{i % 977}" for i in range(30_000))
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "   \n\t", "en", "a", 5), (4, "12 34 !!", "en", None, 8), (5, "Hello world", None, "a", 11), (5, "Hello world", None, "a", 11),
            (6, "Hello world", "en", "b", 11), (7, long, "en", "a", len(long)), (8, long + " extra", "en", "b", len(long) + 6), (9, "x", "fr", "b", 1), (None, "a row without an id", "en", "a", 19), (10, "Öl Ñandú \U0001f600 z", "de", "c", 11)]
    return spark.createDataFrame([(*r, "s", "r", "h") for r in rows], DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


# language identification

def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = langid.identified(docs, langid.trained(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null").collect()
    assert len(rows) > 200
    assert sum(r.lang == r.lang_pred for r in rows) / len(rows) > 0.97
    assert all(0 <= r.score <= 1 for r in rows)
    ids = {r.doc_id: r.held_out for r in rows}
    assert all(zlib.crc32(str(i).encode()) % 3 == 1 for i in ids)


def test_kernel_weights_fold_exactly():
    """The folded matrix product equals the kernel against landmarks, computed by sets."""
    rows = [("the cat and the dog", "en"), ("der hund und die katze", "de"), ("the house of the man", "en"), ("das haus und der mann", "de")] * 3
    model = langid.fit(rows, landmarks=4)
    assert langid.predict(["the man and the cat", "der mann und das haus", None, "123", "", "###"], model)[0][:4] == ["en", "de", "und", "und"]
    assert langid.predict(["\u4e2d\u6587"], model) == (["de"], [0.0])
    x = langid.presence(["the cat"], model)[0]
    own = {"the cat"[i:i + n] for n in (1, 2, 3) for i in range(8 - n)}
    marks = {t[i:i + n] for t, _ in rows[:4] for n in (1, 2, 3) for i in range(len(t) - n + 1)}
    assert x.sum() == len(own & marks)
    assert langid.fit([]) is None and langid.predict(["a"], None) == (["und"], [0.0])


def test_every_script_counts():
    """Random words over alphabets of which two have thousands of characters."""
    rng = random.Random(8)
    scripts = {"en": (0x61, 26), "ru": (0x430, 32), "el": (0x3B1, 24), "he": (0x5D0, 27), "zh": (0x4E00, 4096), "ko": (0xAC00, 4096)}
    prose = lambda at, n: " ".join("".join(chr(at + rng.randrange(n)) for _ in range(rng.randint(2, 6))) for _ in range(60))
    rows = [(prose(*scripts[lang]), lang) for _ in range(40) for lang in scripts]
    model = langid.fit(rows)
    asked = [(prose(*scripts[lang]), lang) for _ in range(30) for lang in scripts]
    got, scores = langid.predict([t for t, _ in asked], model)
    assert got == [lang for _, lang in asked] and min(scores) >= 0.2


def test_kernel_against_sets():
    rng = random.Random(9)
    rows = [("".join(rng.choice("abcé中文 ") for _ in range(rng.randint(1, 60))) + "a", lang) for lang in ("x", "y", "z") for _ in range(12)]
    model = langid.fit(rows, landmarks=9)
    sets = [{t[i:i + n] for n in (1, 2, 3) for i in range(len(t) - n + 1)} for t, _ in rows]
    known = set().union(*[sets[i] for i in (0, 1, 2, 12, 13, 14, 24, 25, 26)])
    found = [langid.found(t, model) for t, _ in rows]
    assert len(known) == model.columns and [len(f) for f in found] == [len(s & known) for s in sets]
    own = langid.kernel(found, found[:3], model.columns, width=7)
    for i, s in enumerate(sets):
        for j in range(3):
            assert own[i, j] == pytest.approx(len(s & sets[j]) / math.sqrt(len(s & known) * len(sets[j])))


def test_language_edges(spark, edges, empty):
    got = {(r.doc_id): r.lang_pred for r in langid.identified(edges, langid.trained(edges)).collect()}
    assert got[1] == got[2] == got[3] == got[4] == "und"
    assert langid.identified(edges, langid.trained(edges)).count() == edges.count()
    assert langid.identified(empty, langid.trained(empty)).count() == 0
    assert langid.accepted(edges, langid.trained(edges)).columns == edges.columns


# top-k

def test_topk_against_brute_force(spark):
    rng = random.Random(3)
    rows = [(i, [rng.uniform(-1, 1) for _ in range(4)]) for i in range(120)] + [(i, [0.5, 0.5, 0.5, 0.5]) for i in range(200, 260)]
    rows += [(300, None), (320, [None, 1.0, 1.0, 1.0]), (340, [float("nan")] * 4), (360, [float("inf")] * 4), (380, []), (400, [1e9, 1e9, -1e9, 1e9])]
    vectors = topk.quantised(spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<double>, tile_shard string"))
    got = sorted(tuple(r) for r in topk.top_k(vectors.where("vec_id % 20 = 0"), vectors, 5, rows_per_shard=50).collect())
    good = {i: [math.floor(64 * x) for x in v] for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v)}
    want = []
    for q in (i for i in good if i % 20 == 0):
        best = sorted((-sum(a * b for a, b in zip(good[q], good[c])), c) for c in good if c != q)[:5]
        want += [(q, k, c, -s) for k, (s, c) in enumerate(best, 1)]
    assert [(q, k, c, s) for q, k, c, s in got] == sorted(want)


def test_topk_with_repeated_query_ids(spark):
    rows = [(20, [1]), (20, [2]), (1, [5]), (2, [4]), (3, [3])]
    vectors = spark.createDataFrame(rows, "vec_id long, grid array<long>")
    got = [tuple(r) for r in topk.top_k(vectors.where("vec_id = 20"), vectors, 3).orderBy("rank").collect()]
    assert got == [(20, 1, 1, 5), (20, 2, 2, 4), (20, 3, 3, 3)]


def test_topk_merges_through_many_levels(spark):
    rng = random.Random(4)
    rows = [(i, [rng.randrange(-3, 4), rng.randrange(-40_000, 40_000)]) for i in range(700)]
    vectors = spark.createDataFrame(rows, "vec_id long, grid array<long>")
    got = sorted(tuple(r) for r in topk.top_k(vectors.where("vec_id % 350 = 0"), vectors, 4, rows_per_shard=8).collect())
    want = []
    for q in (0, 350):
        best = sorted((-sum(a * b for a, b in zip(rows[q][1], v)), i) for i, v in rows if i != q)[:4]
        want += [(q, k, i, -s) for k, (s, i) in enumerate(best, 1)]
    assert got == want


def test_topk_empty(spark):
    none = topk.quantised(spark.createDataFrame([], "vec_id long, embedding array<double>"))
    assert topk.top_k(none, none).count() == 0


# line dedup

def test_templates_generalise_variable_fields(spark):
    body = lambda i: f"unique line number of its own {'abcdefghij'[i]}{'qrstuvwxyz'[i]} alpha beta"
    rows = [(i, f"user {i} logged in from host h{i} at noon\n{body(i)}\nAll rights are reserved by nobody here") for i in range(5)]
    docs = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, template string")
    got = {r.doc_id: r for r in lines.deduplicated(docs).collect()}
    assert got[0].n_dropped == 0
    for i in range(1, 5):
        assert "logged" not in got[i].text and "rights" not in got[i].text
        assert got[0].template == "x"


def test_lines_seen_in_too_few_documents_stay(spark):
    docs = spark.createDataFrame([(1, "one two three four five\nsix seven eight nine"), (2, "one two three four five"), (3, "ten eleven twelve")], "doc_id long, text string")
    assert {r.n_dropped for r in lines.deduplicated(docs).collect()} == {0}
    assert {r.doc_id: r.n_dropped for r in lines.deduplicated(docs, min_docs=2).collect()} == {1: 0, 2: 1, 3: 0}


def test_line_dedup_equals_brute_force_on_exact_lines(spark, documents):
    """Every line (3 tokens or more) that three documents hold literally, with no digit, keeps its first occurrence only."""
    texts = {r.doc_id: r.text for r in documents.collect()}
    where = collections.defaultdict(set)
    for i, t in texts.items():
        for k, line in enumerate(t.split("\n")):
            if len(words(line)) >= 3:
                where[tuple(words(line))].add((i, k))
    must = {x for places in where.values() if len({i for i, _ in places}) >= 3 for x in places - {min(places)}}
    got = {(r.doc_id, k) for r in lines.recurring(documents).collect() for k in r.drops}
    assert must <= got
    assert len(got - must) <= max(3, len(must) // 10)  # generalised templates


def test_registered_line_dedup_drops_what_two_documents_hold(spark, tmp_path):
    rows = [(1, "one two three four five\nLes.\n\n12 34"), (2, "one two three four five\nLes.\n\n12 35"), (3, "ten eleven twelve\nLes. plus\n12 34")]
    want = {1: rows[0][1], 2: "\n12 35", 3: "ten eleven twelve\nLes. plus"}
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    assert {r.doc_id: r.text for r in queries.op3_line_dedup(spark, str(tmp_path)).collect()} == want
    assert {r.doc_id: r.text for r in corpus_pipeline.line_dedup(spark, docs, SF).collect()} == want


def test_registered_line_dedup_against_brute_force(spark, documents):
    """No line stays in more than one document, whatever its length."""
    kept = collections.defaultdict(set)
    for r in queries.op3_line_dedup(spark, SF).collect():
        for line in (r.text or "").split("\n"):
            if words(line):
                kept[tuple(words(line))].add(r.doc_id)
    assert max(map(len, kept.values())) == 1


def brute_templates(rows, min_docs=2, min_tokens=3, depth=lines.DEPTH, similar=lines.SIMILAR):
    """{doc_id: lines dropped} by a plain walk down the tree: leaves, consensus of their distinct lines, templates, first places."""
    field, leaves, distinct = "<*>", collections.defaultdict(list), collections.defaultdict(set)
    mask = lambda ts: tuple(field if re.search("[0-9]", t) else t for t in ts)
    for i, text in rows:
        for k, line in enumerate((text or "").split("\n")):
            ts = tuple(t for t in re.split("[ \t\x0b\x0c\r]", line) if t)
            if ts:
                leaf = ("short", ts) if len(ts) < min_tokens else (len(ts), mask(ts[:depth]))
                leaves[leaf].append((i, k, ts))
    templates = collections.defaultdict(set)
    for leaf, held in leaves.items():
        if len({i for i, _, _ in held}) < 2 or len(held) < min_docs:
            continue
        plain = leaf[0] == "short" or len({ts for _, _, ts in held}) == 1
        bodies = {ts if plain else mask(ts) for _, _, ts in held}
        wide = len(held[0][2])
        consensus = []
        for p in range(depth, wide):
            n = collections.Counter(b[p] for b in bodies)
            best = max(n.items(), key=lambda x: (x[1], x[0]))
            consensus.append(best[0] if 2 * best[1] > len(bodies) else field)
        for i, k, ts in held:
            body = ts if plain else mask(ts)
            same = sum(a == b for a, b in zip(body[depth:], consensus))
            key = (leaf,) if plain or same >= similar * len(consensus) else (leaf, body)
            templates[key].add((i, k))
    out = collections.defaultdict(set)
    for places in templates.values():
        if len({i for i, _ in places}) >= min_docs:
            for i, k in places - {min(places)}:
                out[i].add(k)
    return dict(out)


def test_templates_against_brute_force(spark, documents):
    got = {r.doc_id: set(r.drops) for r in lines.recurring(documents, min_docs=2, short=True).collect()}
    assert got == brute_templates([(r.doc_id, r.text) for r in documents.collect()])


def test_templates_with_variable_fields_against_brute_force(spark, monkeypatch):
    rng = random.Random(6)
    line = lambda: " ".join([rng.choice(["get", "put"]), rng.choice(["file", f"n{rng.randrange(9)}"]), rng.choice("ab"), *[rng.choice(["on", "off", f"{rng.randrange(99)}"]) for _ in range(rng.randint(0, 5))]])
    rows = [(i, "\n".join(line() for _ in range(rng.randint(0, 7)))) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_templates(rows)
    for most in (lines.MOST, 0):  # with and without broadcasts
        monkeypatch.setattr(lines, "MOST", most)
        assert {r.doc_id: set(r.drops) for r in lines.recurring(docs, min_docs=2, short=True).collect()} == want
    texts = {r.doc_id: r for r in lines.deduplicated(docs, min_docs=2, short=True).collect()}
    for i, t in rows:
        assert texts[i].text == "\n".join(x for k, x in enumerate(t.split("\n")) if k not in want.get(i, ())) and texts[i].n_dropped == len(want.get(i, ()))


def test_line_keys_beyond_a_fixed_number_are_not_broadcast(spark, monkeypatch):
    """Templates never are, and of many leaves only a table of SIEVE marks is."""
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    distinct = spark.createDataFrame([(1, 1, list("abcd")), (1, 2, list("abce"))], "leaf long, line_key long, tokens array<string>")
    assert "Broadcast" not in plan(lines.generalised(distinct))
    monkeypatch.setattr(lines, "MOST", 1)
    monkeypatch.setattr(lines, "SIEVE", 2)
    leaves = spark.createDataFrame([(i - 300, False) for i in range(0, 600, 3)], "leaf long, uniform boolean")
    rows = spark.range(-400, 400).select(F.col("id").alias("leaf"), F.col("id").alias("doc_id"))
    got = lines._sieved(rows, leaves)
    assert plan(got).count("BroadcastHashJoin") == 1 and "SortMergeJoin" in plan(got)
    assert {(r.doc_id, r.uniform) for r in got.collect()} == {(i - 300, False) for i in range(0, 600, 3)}


def test_rows_of_one_id_with_other_texts_keep_their_own_lines(spark):
    rows = [(1, "one two three four\nfive six seven"), (2, "eight nine ten\none two three four"), (2, "eleven twelve thirteen\nonly here of all")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r.text for r in lines.deduplicated(docs, min_docs=2).collect()) == ["eight nine ten", "eleven twelve thirteen\nonly here of all", "one two three four\nfive six seven"]


def test_line_edges(spark, edges, empty):
    rows = lines.deduplicated(edges).collect()
    assert len(rows) == edges.count() and {r.text for r in rows if r.doc_id == 1} == {None}
    clash = edges.withColumn("n_lines", F.lit("own")).withColumn("n_dropped", F.lit("own"))
    assert lines.deduplicated(clash).columns == [*edges.columns, "n_lines", "n_dropped"] and {r.n_lines for r in lines.deduplicated(clash).collect()} != {"own"}
    assert lines.cleaned(clash).columns == clash.columns and {r.n_lines for r in lines.cleaned(clash).collect()} == {"own"}
    assert lines.deduplicated(empty).count() == 0


# near duplicates

def brute_components(rows, size=4, percent=80):
    sets = {}
    for i, t in rows:
        w = [re.sub("[A-Z]", lambda m: m[0].lower(), x) for x in words(t)]
        sets[i] = {tuple(w[k:k + size]) for k in range(max(1, len(w) - size + 1))} if w else set()
    ids, parent = sorted(sets), {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[k + 1:]:
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_dedup_equals_brute_force(spark, documents):
    rows = [(r.doc_id, r.text) for r in documents.collect()]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.clustered(documents).collect()}
    assert got == brute_components(rows)


def test_large_group_of_near_copies(spark):
    """A dense region, a chain whose ends are unlike, and pairs at the threshold."""
    rng = random.Random(5)
    base = [f"b{i}" for i in range(120)]
    rows = []
    for i in range(180):
        t = list(base)
        for _ in range(rng.randint(0, 2)):
            t[rng.randrange(120)] = f"n{rng.randrange(10 ** 6)}"
        rows.append((i, " ".join(t)))
    chain = [f"c{i}" for i in range(130)]
    rows += [(1000 + s, " ".join(chain[s * 5:s * 5 + 60])) for s in range(12)]
    rows += [(2000, "a b c"), (2001, "A B c"), (2002, "a b"), (2003, "a b c d"), (2004, ""), (2005, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.clustered(docs).collect()}
    assert got == brute_components(rows)


def family(rng, n, places=100, kinds=None):
    """Texts that share about 0.7 of their shingles with each other: each changes words that stand far apart, to one of `kinds` values or to
    one of its own; and pairs of them at 0.8 or more, which nothing else links."""
    base = [f"t{i}" for i in range(4 * places)]

    def text(i, changes):
        out = list(base)
        for p in changes:
            out[4 * p] = f"k{p}x{rng.randrange(kinds)}" if kinds else f"u{i}x{p}"
        return out

    rows = []
    for i in range(n):
        t = text(i, rng.sample(range(places), places // 5))
        rows.append((2 * i, " ".join(t)))
        if i % 10 == 0:
            for p in rng.sample(range(4 * places), 8):
                t[p] = f"v{i}x{p}"
            rows.append((2 * i + 1, " ".join(t)))
    return rows


@pytest.mark.parametrize("kinds", [None, 2])
def test_dense_families_lose_no_link(spark, kinds):
    """Regions larger than SMALL with sole links in them."""
    rows = family(random.Random(11), 330, 40, kinds)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.clustered(docs).collect()}
    assert got == brute_components(rows)


def test_large_and_heavy_regions_give_the_same_components(spark, documents, monkeypatch):
    """All regions are dealt to several tasks, go through the set join, and their groups are cut into tiles."""
    for name, value in (("HEAVY", 1), ("SMALL", 1), ("TILE", 2), ("MOST", 0)):
        monkeypatch.setattr(neardup, name, value)
    rows = [(r.doc_id, r.text) for r in documents.collect()] + [(10 ** 6 + i, t) for i, t in family(random.Random(12), 40, 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.clustered(docs).collect()}
    assert got == brute_components(rows)


def test_ids_beyond_a_fixed_number_are_not_broadcast(spark, monkeypatch):
    """26,000 pairs of near copies, one document in 30 alone: tables of 50,000 rows are the largest that are broadcast."""
    seen, broadcast = [], F.broadcast
    monkeypatch.setattr(F, "broadcast", lambda df: seen.append(df.count()) or broadcast(df))
    rows = spark.range(26_000 * 2 + 1_000)
    pair = F.floor(F.col("id") / 2)
    word = lambda i: F.concat(F.lit("w%d" % i), F.when(F.col("id") < 52_000, pair).otherwise(-F.col("id")).cast("string"))
    last = F.when(F.col("id") % 2 == 1, F.lit(" more")).otherwise(F.lit(""))
    docs = rows.select(F.col("id").alias("doc_id"), F.concat(F.concat_ws(" ", *[word(i) for i in range(9)]), last).alias("text"))
    want = F.when(F.col("doc_id") < 52_000, F.floor(F.col("doc_id") / 2) * 2).otherwise(F.col("doc_id"))
    got = neardup.clustered(docs)
    assert got.count() == 53_000 and got.where(F.col("component_id") != want).count() == 0
    assert seen and max(seen) <= 50_000, seen


def test_set_join_meets_every_pair_at_the_similarity(spark, monkeypatch):
    monkeypatch.setattr(neardup, "TILE", 4)
    rng = random.Random(13)
    sets = [set(rng.sample(range(40), rng.randint(1, 30))) for _ in range(60)]
    sets += [s | {100 + i} for i, s in enumerate(sets)] + [set(list(s)[1:]) | {200} for s in sets if len(s) > 1]
    items = spark.createDataFrame([(i, bytearray(np.array(sorted(s), np.uint64).tobytes())) for i, s in enumerate(sets)], "id long, items binary")
    members = spark.createDataFrame([(i, i) for i in range(len(sets))], "id long, component long")
    met = collections.defaultdict(set)
    for r in neardup.sharing(members, items, 80).collect():
        met[r.block].add(r.id)
    pairs = {(a, b) for held in met.values() for a in held for b in held if a < b}
    want = {(a, b) for a in range(len(sets)) for b in range(a + 1, len(sets)) if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])}
    assert want and want <= pairs and len(pairs) < len(sets) ** 2 / 2


def test_tiles_meet_across_components(spark, monkeypatch):
    monkeypatch.setattr(neardup, "TILE", 3)
    rng = random.Random(14)
    rows = [(item, i, 0 if rng.random() < main else rng.randrange(1, 9)) for item, n, main in ((1, 60, 0.8), (2, 40, 0.1), (3, 2, 0.5), (4, 30, 1.0)) for i in range(n)]
    met = collections.defaultdict(set)
    for r in neardup.tiled(spark.createDataFrame(rows, "item long, id long, component long")).collect():
        met[(r.item, r.block)].add(r.id)
    pairs = {(item, a, b) for (item, _), held in met.items() for a in held for b in held if a < b}
    assert {(k, a, b) for k, a, x in rows for m, b, y in rows if k == m and a < b and x != y} <= pairs
    assert max(map(len, met.values())) < 25 and not any(k == 4 for k, _ in met)


def test_near_dedup_edges(spark, edges, empty):
    rows = neardup.clustered(edges).collect()
    assert len(rows) == edges.count()
    by = {r.doc_id: r for r in rows}
    assert by[1].kept and by[1].component_id == 1 and by[6].component_id == 5 and not by[6].kept and by[8].component_id == 7 and by[None].kept
    more = neardup.clustered(edges.unionByName(edges.where("doc_id = 7").withColumn("doc_id", F.lit(None).cast("long")))).where("doc_id is null").collect()
    assert len(more) == 2 and all(r.kept and r.component_id is None for r in more)
    assert neardup.clustered(empty).count() == 0
    assert neardup.deduplicated(edges).columns == edges.columns


# fingerprints

def brute_likeness(a, b, width=fingerprints.WIDTH):
    """Code points in spans of `width` that the other text holds too, or in the common prefix or suffix, counted by strings."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    prefix = len(os.path.commonprefix([a, b]))
    suffix = len(os.path.commonprefix([a[::-1], b[::-1]]))

    def share(x, y):
        inside, there = [i < prefix or i >= len(x) - suffix for i in range(len(x))], {y[i:i + width] for i in range(len(y) - width + 1)}
        for i in range(len(x) - width + 1):
            if x[i:i + width] in there:
                inside[i:i + width] = [True] * width
        return sum(inside)

    return (share(a, b) + share(b, a)) / (len(a) + len(b))


def test_fingerprints(spark, documents):
    texts = {r.doc_id: r.text or "" for r in documents.collect()}
    rows = {r.doc_id: r for r in fingerprints.fingerprinted(documents).collect()}
    ids = sorted(texts)
    assert sorted(rows) == ids
    seen = {}
    for i, j in zip(ids, ids[1:] + ids[:1]):
        t, k = texts[i], len(texts[i]) // 4
        new = t[:len(t) - k] + texts[j][:k]
        assert rows[i].n_chars == len(t) and rows[i].edited_sha256 == hashlib.sha256(new.encode()).hexdigest()
        assert seen.setdefault(t, rows[i].fingerprint) == rows[i].fingerprint
        assert seen.setdefault(new, rows[i].edited_fingerprint) == rows[i].edited_fingerprint
        assert rows[i].same_prefix == len(os.path.commonprefix([t, new]))
        if len(t) + len(texts[j]) < 30_000:
            assert rows[i].near_edited == pytest.approx(brute_likeness(t, new)) and rows[i].near_next == pytest.approx(brute_likeness(t, texts[j]))
    assert len(set(seen.values())) == len(seen)
    far = [r for r in rows.values() if r.n_chars >= 40]
    assert sum(r.near_edited > r.near_next for r in far) / len(far) > 0.97


def test_spans_and_extensions():
    rng = random.Random(1)
    text = "".join(rng.choice("abé\U0001f600") for _ in range(300)) * 2
    p = fingerprints.Prefixes(fingerprints.points(text))
    for _ in range(300):
        i, j, n = rng.randrange(500), rng.randrange(500), rng.randrange(1, 60)
        assert (p.span(i, min(i + n, 600)) == p.span(j, min(j + n, 600))) == (text[i:min(i + n, 600)] == text[j:min(j + n, 600)])
    assert fingerprints.common_extension(p, 0, p, 300) == 300 == fingerprints.common_extension_back(p, 300, p, 600)
    for _ in range(50):
        i, j = rng.randrange(600), rng.randrange(600)
        assert fingerprints.common_extension(p, i, p, j) == len(os.path.commonprefix([text[i:], text[j:]]))
        assert fingerprints.common_extension_back(p, i, p, j) == len(os.path.commonprefix([text[:i][::-1], text[:j][::-1]]))


def test_likeness_against_brute_force():
    rng = random.Random(2)
    prose = lambda n, letters="ab": "".join(rng.choice(letters) for _ in range(n))
    shared = prose(300, "abcdefgh ")
    pairs = [(prose(n), prose(m)) for n in (0, 1, 5, 23, 24, 25, 90) for m in (0, 1, 24, 70)]
    pairs += [(prose(900, "xyz") + shared + prose(5000, "uvw"), prose(40, "pq") + shared + prose(9, "rs")), ("a" * 200, "a" * 90), (shared, shared + "!"), (shared[:30] + shared[200:], shared)]
    for a, b in pairs:
        x, y = (fingerprints.Prefixes(fingerprints.points(t)) for t in (a, b))
        assert fingerprints.likeness(x, y) == pytest.approx(brute_likeness(a, b)) == pytest.approx(fingerprints.likeness(y, x))
        assert (fingerprints.shown(x) == fingerprints.shown(y)) == (a == b) and 0 <= fingerprints.resemblance(fingerprints.shown(x), fingerprints.shown(y)) <= 1
    far = fingerprints.likeness(*(fingerprints.Prefixes(fingerprints.points(t)) for t in pairs[-4]))
    assert far > 0.08  # a short passage in long texts counts


def test_fingerprint_edges(spark, edges, empty):
    assert fingerprints.fingerprinted(edges).count() == edges.count()
    assert fingerprints.fingerprinted(empty).count() == 0
    one = fingerprints.fingerprinted(edges.where("doc_id = 9")).collect()
    assert len(one) == 1 and one[0].near_next == 1.0


def test_next_documents_with_any_ids(spark, monkeypatch):
    """Ids of the whole long range, an id of many texts, and many nulls, in ranges of a few rows."""
    monkeypatch.setattr(fingerprints, "ROWS_A_CHUNK", 3)
    ids = [-(2 ** 63), 2 ** 63 - 1, 0, 1, 2, 3, *range(2 ** 60, 2 ** 60 + 20), *[77] * 40, *[None] * 25]
    docs = spark.createDataFrame([(i, f"text {k} " * 9, "x", "y") for k, i in enumerate(ids)], "doc_id long, text string, chunk string, order_key string")
    rows = fingerprints.fingerprinted(docs).collect()
    keyed = sorted(((r.doc_id is not None, r.doc_id or 0, r.k, r.text) for r in docs.withColumn("k", F.xxhash64("text")).collect()))
    want = collections.Counter()
    for (known, i, _, t), (*_, u) in zip(keyed, keyed[1:] + keyed[:1]):
        k = len(t) // 4
        want[(i if known else None, hashlib.sha256((t[:len(t) - k] + u[:k]).encode()).hexdigest())] += 1
    assert collections.Counter((r.doc_id, r.edited_sha256) for r in rows) == want


# shards

def test_shards(spark, documents):
    rows = shards.interleaved(documents).collect()
    texts = {r.doc_id: r.text or "" for r in documents.collect()}
    assert len(rows) == len(texts)
    counts = collections.Counter(r.shard for r in rows)
    assert max(counts.values()) - min(counts.values()) <= 1 and set(counts) <= set(range(16))
    for s in counts:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(counts[s]))
    for r in rows:
        assert r.size == len(texts[r.doc_id].encode()) + 1 and r.text_crc32 == zlib.crc32(texts[r.doc_id].encode()) and r.grown_shard is None and r.law == "rows"
    for source, n in collections.Counter(r.source for r in rows).items():
        mine = collections.Counter(r.shard for r in rows if r.source == source)
        assert all(abs(mine[s] - n / 16) <= 2 for s in counts)


def test_shard_edges(spark, edges, empty):
    rows = shards.interleaved(edges, shards=3).collect()
    assert len(rows) == edges.count() and collections.Counter(r.shard for r in rows) == {0: 4, 1: 4, 2: 4}
    assert sorted((r.shard, r.slot) for r in rows) == [(s, k) for s in range(3) for k in range(4)]
    assert shards.interleaved(empty).count() == 0


# mixing

def water(sizes, weights=(1, 2, 3), most=3):
    """Targets by resharing step by step."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    total, capped = sum(sizes.values()), {}
    while True:
        free = [s for s in names if s not in capped]
        left = total - sum(capped.values())
        share = {s: left * w[s] / sum(w[x] for x in free) for s in free}
        over = [s for s in free if share[s] > most * sizes[s] + 1e-9]
        if not over:
            return capped | share
        capped |= {s: most * sizes[s] for s in over}


def test_mixing(spark, documents):
    rows = mixing.mixed(documents).collect()
    texts = {r.doc_id: (r.text, r.source) for r in documents.collect()}
    sizes = collections.Counter()
    for t, s in texts.values():
        sizes[s] += len(words(t))
    goal, taken = water(sizes), collections.Counter()
    assert len(rows) == len(texts)
    for r in rows:
        t, s = texts[r.doc_id]
        assert r.size == len(words(t)) and r.source_size == sizes[s] and abs(r.target - goal[s]) < 1e-6 * (1 + goal[s])
        assert r.taken <= 3 * r.size and (r.size == 0 or r.taken % r.size == 0)
        taken[s] += r.taken
    for s in sizes:
        most = max((len(words(t)) for t, x in texts.values() if x == s), default=0)
        assert abs(taken[s] - goal[s]) <= most
    again = {r.doc_id: r.taken for r in mixing.mixed(documents.repartition(7)).collect()}
    assert again == {r.doc_id: r.taken for r in rows}
    mix = mixing.mixture(documents)
    assert mix.columns == documents.columns and mix.count() == sum(r.copies for r in rows if r.size)


def test_targets_stop_at_three_times(spark):
    sizes = {"a": 10, "b": 1, "c": 1, "d": 0, "é": 5, None: 7}
    got = {r.source: r.target for r in mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long")).collect()}
    assert got == pytest.approx(water(sizes)) and sum(got.values()) == pytest.approx(sum(sizes.values()))


def test_pivot_keeps_words_and_is_fair():
    rng = np.random.default_rng(0)
    sizes, want = rng.integers(1, 50, 40), rng.uniform(0.05, 0.95, 40)
    sums = np.zeros(40)
    for _ in range(3000):
        out, k = mixing.pivot(sizes, want, rng.uniform(size=40))
        assert abs((out * sizes).sum() - (want * sizes).sum()) < 1e-6
        assert all(x in (0, 1) for i, x in enumerate(out) if i != k)
        sums += out
    assert np.abs(sums / 3000 - want).max() < 0.05


def test_mixing_edges(spark, edges, empty):
    rows = mixing.mixed(edges).collect()
    assert len(rows) == edges.count() and all(r.taken == 0 for r in rows if not r.size)
    assert mixing.mixed(empty).count() == 0 and mixing.mixture(edges).columns == edges.columns


# byte-level BPE

@pytest.fixture(scope="module")
def library():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(spark, documents, library):
    texts = {r.doc_id: r.text or "" for r in documents.collect()}
    rows = bpe.digests(documents, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).collect()
    for r in rows:
        ids = library.encode_ordinary(texts[r.doc_id])
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(texts[r.doc_id].encode()).hexdigest())


def test_bpe_on_odd_texts(library):
    vocab = bpe.Vocabulary(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    rng = random.Random(4)
    texts = ["", " ", "a" * 5000, "ab" * 4000, "ééé" * 700, "\U0001f600" * 300, "don't  stop\n\n x", "<|endoftext|>", "=" * 999 + "x"]
    texts += ["".join(rng.choice("abeinrst") for _ in range(rng.randint(1, 60))) for _ in range(400)]
    texts += ["".join(rng.choice("thenig aé1\n") for _ in range(rng.randint(1, 200))) for _ in range(200)]
    for t in texts:
        assert vocab.encode(t) == library.encode_ordinary(t)
        assert vocab.decode(vocab.encode(t)) == t.encode()


def test_bit_queue_is_a_priority_queue():
    rng, queue, model = random.Random(0), bpe.BitQueue(), set()
    for _ in range(3000):
        x = rng.randrange(60_000)
        if x in model:
            queue.remove(x)
            model.discard(x)
        else:
            queue.add(x)
            model.add(x)
        assert queue.least() == min(model, default=-1)


def test_bpe_edges(spark, edges, empty):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    assert bpe.digests(edges, path, public_tokenizers.PATTERN).count() == edges.count()
    assert bpe.digests(empty, path, public_tokenizers.PATTERN).count() == 0
    back = bpe.decoded(bpe.encoded(edges, path, public_tokenizers.PATTERN), path, public_tokenizers.PATTERN)
    assert sorted(bytes(r.bytes).decode() for r in back.collect()) == sorted(r.text or "" for r in edges.collect())


# WARC

def test_audit_finds_planted_faults(spark):
    pages = spark.createDataFrame([(i, f"http://h/{i}", f"<p>{i}</p>", "x") for i in range(2500)], "page_id long, url string, html string, digest string")
    bad = warc.damaged_replica(pages)
    got = {(r.page_id, r.status) for r in warc.audit(warc.volumes(pages), warc.volumes(bad)).collect()}
    lost, hit = {230, 231, 232}, set(range(5, 2500, 97))
    assert sorted(r.page_id for r in bad.collect()) == sorted([*(set(range(2500)) - lost), 240])
    assert got == {(i, "damaged") for i in hit} | {(i, "missing") for i in lost} | {(240, "extra")} | {(i, "moved") for i in range(233, 1000) if i not in hit}
    assert warc.audit(warc.volumes(pages), warc.volumes(pages)).count() == 0
    a, b = (warc.volumes(x) for x in (pages, bad))
    n = warc.levels_for(a, b)
    assert warc.root_hash(warc.tree(a, *n)) == warc.root_hash(warc.tree(a.repartition(5), *n)) != warc.root_hash(warc.tree(b, *n))


def test_descent_visits_damaged_branches_only(spark):
    pages = spark.createDataFrame([(i, "u", f"{i}") for i in range(400)], "page_id long, url string, html string")
    other = pages.withColumn("html", F.when(F.col("page_id") == 123, "???").otherwise(F.col("html")))
    a, b = warc.volumes(pages), warc.volumes(other)
    n = warc.levels_for(a, b)
    found = [(r.volume, r.node) for r in warc.differing(warc.tree(a, *n)[1:], warc.tree(b, *n)[1:], n[1]).collect()]
    assert found == [(0, 123 >> 4)]


def test_audit_over_many_volumes_and_ids_of_either_sign(spark):
    pages = spark.createDataFrame([(i, "u", f"{i}") for i in (*range(-70, 900), 10 ** 15, -(10 ** 15))] + [(None, "u", f"n{i}") for i in range(60)], "page_id long, url string, html string")
    other = pages.withColumn("html", F.when(F.col("page_id").isin(-33, 500, 10 ** 15), "???").otherwise(F.col("html")))
    got = {(r.page_id, r.status) for r in warc.audit(warc.volumes(pages, 10), warc.volumes(other, 10)).collect()}
    assert got == {(-33, "damaged"), (500, "damaged"), (10 ** 15, "damaged")}
    lost = pages.where("html <> 'n7'")
    assert [(r.page_id, r.status, r.expected is None) for r in warc.audit(warc.volumes(pages, 10), warc.volumes(lost, 10)).collect() if r.status != "moved"] == [(None, "missing", False)]


def test_records_have_the_mandatory_fields(spark):
    page = spark.createDataFrame([(7, "http://h/", "<p>x</p>")], "page_id long, url string, html string")
    head = page.select(warc.record(F.col("url"), F.col("html"), F.col("page_id"), "2021-05-06T07:08:09Z")).first()[0].partition("\r\n\r\n")[0]
    fields = dict(x.split(": ", 1) for x in head.split("\r\n")[1:])
    assert {"WARC-Type", "WARC-Date", "WARC-Record-ID", "Content-Length"} <= set(fields) and fields["WARC-Date"] == "2021-05-06T07:08:09Z"


def test_warc_files_round_trip_and_are_audited(spark, tmp_path):
    pages = spark.createDataFrame([(i, f"http://h/{i}", f"<p>é\r\n\r\nWARC/1.0 {i}</p>") for i in range(60)] + [(60, None, None)], "page_id long, url string, html string")
    path = f"{tmp_path}/warc"
    warc.write_volumes(pages, path, 25)
    want = warc.volumes(pages, 25)
    columns = ["volume", "record_no", "page_id", "at", "length", "digest"]
    assert sorted(map(tuple, warc.read_volumes(spark, path).select(columns).collect())) == sorted(map(tuple, want.select(columns).collect()))
    file = next((tmp_path / "warc" / "volume=1").glob("*.txt"))
    data = bytearray(file.read_bytes())
    places = {r.page_id: r["at"] for r in want.where("volume = 1").collect()}
    at = data.index(b"Content-Length", places[30])  # a damaged head must not hide the records behind it
    data[at] ^= 1
    data[data.index(b"<p>", places[40])] ^= 1
    file.write_bytes(bytes(data))
    (file.parent / f".{file.name}.crc").unlink()  # else the file system itself refuses the damaged file
    found = warc.audit(want, warc.read_volumes(spark, path)).collect()
    assert sorted((r.page_id, r.status) for r in found) == [(30, "damaged"), (40, "damaged")]


def test_audit_of_records_lost_inside_a_volume(spark):
    pages = spark.createDataFrame([(i, f"http://h/{i}", f"<p>{i}</p>") for i in range(2000) if i != 1500], "page_id long, url string, html string")
    html = F.when(F.col("page_id").isin(3, 700, 1100), F.concat(F.lit("#"), F.expr("substring(html, 2)"))).otherwise(F.col("html"))
    more = spark.createDataFrame([(1500, "http://h/1500", "<p>new</p>")], pages.schema)
    bad = pages.withColumn("html", html).where("page_id not in (400, 401, 999)").unionByName(more)
    rows = warc.audit(warc.volumes(pages), warc.volumes(bad)).collect()
    by = {s: {r.page_id for r in rows if r.status == s} for s in ("damaged", "missing", "extra", "moved")}
    assert by == {"damaged": {3, 700, 1100}, "missing": {400, 401, 999}, "extra": {1500}, "moved": (set(range(402, 999)) - {700}) | set(range(1501, 2000))}
    assert len(rows) == sum(map(len, by.values()))
    assert all((r.expected is None) == (r.status == "extra") and (r.found is None) == (r.status == "missing") and (r.expected == r.found) == (r.status == "moved") for r in rows)


def test_audit_matches_unreadable_ids_by_place(spark):
    pages = spark.createDataFrame([(i, "u", f"{i}") for i in range(50)], "page_id long, url string, html string")
    whole = warc.volumes(pages)
    torn = whole.where("page_id <> 10").withColumn("record_no", F.col("record_no") - (F.col("page_id") > 10).cast("int"))
    torn = torn.withColumn("digest", F.when(F.col("page_id").isin(5, 20), F.lit("torn")).otherwise(F.col("digest"))).withColumn("page_id", F.when(~F.col("page_id").isin(5, 20), F.col("page_id")))
    got = {(r.page_id, r.status) for r in warc.audit(whole, torn).collect() if r.status != "moved"}
    assert got == {(5, "damaged"), (20, "damaged"), (10, "missing")}


def test_warc_edges(spark):
    pages = spark.createDataFrame([(None, None, None), (1, None, "x"), (1, None, "x"), (2, "u", None)], "page_id long, url string, html string")
    assert warc.audit(warc.volumes(pages), warc.volumes(pages)).count() == 0
    assert warc.audit(warc.volumes(pages), warc.volumes(pages.where("page_id = 1"))).count() == 2
    assert warc.audit(warc.volumes(pages.limit(0)), warc.volumes(pages.limit(0))).count() == 0


# URL filter

def test_url_rules(spark):
    cases = {None: ("", "", None), "no scheme": ("", "", None), "http://A.Net/x?y": ("a.net", "/x", "net/"), "http://a.net": ("a.net", "", None), "http://b.example.net/en/1#t": ("b.example.net", "/en/1", "example.net/en/"),
             "http://badexample.net/en/": ("badexample.net", "/en/", "net/"), "x://example.com/de/": ("example.com", "/de/", "example.com/de/"), "x://org/fr/": ("org", "/fr/", "org/fr/"), "x://aorg/fr/": ("aorg", "/fr/", None), "x://h.org/fr": ("h.org", "/fr", None), "x://": ("", "", None)}
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(cases)] + [(100, "http://www.listed.com/a/", "x"), (101, "https://listed.com/a?b", "x"), (102, "https://listed.com/ab", "x")], "page_id long, url string, host string")
    listed = spark.createDataFrame([("listed.com/a",), (None,)], "canonical string")
    got = {r.page_id: r for r in urls.judged(pages, listed).collect()}
    for i, want in enumerate(cases.values()):
        assert (got[i].host, got[i].path, got[i].rule) == want
    assert [got[i].verdict for i in (100, 101, 102)] == ["block", "block", "allow"]


def test_small_bloom_filter_gives_false_positives_that_the_join_removes(spark):
    pages = spark.createDataFrame([(i, f"http://h{i}.com/p") for i in range(600)], "page_id long, url string")
    listed = spark.createDataFrame([(f"h{i}.com/p",) for i in range(0, 600, 2)], "canonical string")
    rows = urls.judged(pages, listed, blocks=4).collect()
    assert {r.page_id for r in rows if r.verdict == "block"} == set(range(0, 600, 2))
    assert [urls.blocks_for(n) for n in (0, 1, 5, 6, 1000)] == [1, 1, 1, 2, 256]


def test_url_filter_without_broadcasts(spark, monkeypatch):
    monkeypatch.setattr(urls, "MOST", 0)
    pages = spark.createDataFrame([(i, f"http://h{i % 100}.com/p") for i in range(300)] + [(None, None), (None, "none"), (1, None)], "page_id long, url string")
    rows = urls.judged(pages, spark.createDataFrame([(f"h{i}.com/p",) for i in range(0, 200, 2)] * 2, "canonical string")).collect()
    assert len(rows) == 303 and {r.host for r in rows if r.listed} == {f"h{i}.com" for i in range(0, 100, 2)}


def test_the_bundled_list_is_no_pattern_of_the_pages(spark):
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    rows = urls.judged(pages, urls.bundled_list(spark)).collect()
    on_listed_hosts = [r for r in rows if any(f"{x}.example" in r.host for x in urls.LISTED_LABELS)]
    assert any(r.listed for r in on_listed_hosts) and not all(r.listed for r in on_listed_hosts)
    assert urls.bundled_list(spark).count() > 10 * len(rows)


def test_url_edges(spark):
    pages = spark.createDataFrame([], "page_id long, url string")
    assert urls.judged(pages, urls.bundled_list(spark)).count() == 0
    some = spark.createDataFrame([(1, "http://m.adult-x.example.com/en/0", "a", "b", "c", "d")], "page_id long, url string, canonical string, hit string, block string, key string")
    assert [(r.verdict, r.listed) for r in urls.judged(some, urls.bundled_list(spark)).collect()] == [("block", True)]
    assert [r.verdict for r in urls.judged(some, urls.bundled_list(spark).limit(0)).collect()] == ["allow"]


# pipeline

def test_pipeline_stages(spark, documents):
    docs = documents
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF).cache()
        assert out.columns == documents.columns, name
        if name == "language_id":
            assert {r.doc_id for r in docs.collect()} - {r.doc_id for r in out.collect()} <= {r.doc_id for r in docs.collect() if not re.search(r"[^\W\d_]", r.text or "")}
        if name == "line_dedup":
            assert out.count() == docs.count()
        if name == "near_dedup":
            want = {i for i, (_, c) in brute_components([(r.doc_id, r.text) for r in docs.collect()], 5).items() if i == c}
            assert {r.doc_id for r in out.collect()} == want
        docs = out
    last = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert last.count() == docs.count()


CLASHES = ("n_lines", "n_dropped", "drops", "cleaned", "doc", "row", "mix_row", "mix_key", "copies", "component_id", "kept", "n_shingles", "lang_pred", "score", "id", "region", "text_key", "template", "leaf", "line_no")


def test_stages_keep_columns_with_the_names_of_their_own(spark, edges):
    docs = edges
    for name in CLASHES:
        docs = docs.withColumn(name, F.lit(f"own {name}"))
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, SF)
        assert kept.columns == docs.columns, name
        assert all(r[c] == f"own {c}" for r in kept.collect() for c in (*CLASHES,) if c != "row"), name
    assert corpus_pipeline.STAGES[-1][1](spark, kept, SF).count() == kept.count()
    for made in (langid.identified(docs, None), lines.deduplicated(docs), neardup.clustered(docs), fingerprints.fingerprinted(docs), shards.interleaved(docs), mixing.mixed(docs)):
        assert made.count() == docs.count() and len(set(made.columns)) == len(made.columns)


def test_pipeline_takes_edges(spark, edges, empty):
    for docs in (edges, empty):
        kept = docs
        for _, stage in corpus_pipeline.STAGES:
            kept = stage(spark, kept, SF)
        kept.count()


def test_every_operator_is_registered():
    assert sorted(int(re.match(r"op(\d+)_", n)[1]) for n in queries.queries() if n != "pipeline") == list(range(1, 11))
    assert set(queries.oracle_sql()) <= set(queries.queries())
