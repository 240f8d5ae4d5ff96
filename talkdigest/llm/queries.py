"""Queries of the operators over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

import importlib

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, fingerprints, langid, lines, mixing, neardup, shards, topk, urls, warc
from .common import table


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return langid.identified(documents, langid.trained(documents))


def op2_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.quantised(table(spark, sf_dir, "embeddings"))
    return topk.top_k(vectors.where("vec_id % 20 = 0"), vectors, 20)


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.deduplicated(table(spark, sf_dir, "documents").select("doc_id", "text"), min_docs=2, short=True)


def op4_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.clustered(table(spark, sf_dir, "documents"))


def op5_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprinted(table(spark, sf_dir, "documents"))


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.interleaved(table(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "source", "copies")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op9_warc_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return warc.audit(warc.volumes(pages), warc.volumes(warc.damaged_replica(pages)))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judged(table(spark, sf_dir, "pages"), urls.bundled_list(spark))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return importlib.import_module("corpus_pipeline").run(spark, sf_dir)


def queries() -> dict:
    return {f.__name__: f for f in (op1_language_id, op2_exact_topk, op3_line_dedup, op4_minhash_near_dedup, op5_document_fingerprints, op6_sharding, op7_mixing, op8_byte_bpe, op9_warc_audit, op10_url_filter, pipeline)}


TOPK_SQL = """
WITH v AS (SELECT vec_id, [CAST(floor(64 * CAST(x AS DOUBLE)) AS DOUBLE) FOR x IN embedding] AS g FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.g, c.g) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id % 20 = 0 AND q.vec_id <> c.vec_id)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM s) WHERE r <= 20
"""

NEARDUP_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS t FROM documents),
g AS (SELECT DISTINCT doc_id, array_to_string(t[i:i+3], ' ') AS s FROM (SELECT doc_id, t, unnest(range(1, greatest(len(t) - 3, 1) + 1)) AS i FROM w WHERE len(t) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT p.a, p.b FROM p JOIN n x ON x.doc_id = p.a JOIN n y ON y.doc_id = p.b WHERE 100 * c >= 80 * (x.n + y.n - c)),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.b FROM r JOIN e ON e.a = r.b),
m AS (SELECT a, min(b) AS component_id FROM r GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.component_id, d.doc_id = m.component_id AS kept
FROM documents d JOIN m ON m.a = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""

WARC_SQL = r"""
WITH p AS (SELECT page_id, CAST(floor(page_id / 1000) AS BIGINT) AS volume, page_id % 1000 AS place, coalesce(url, '') AS url, html FROM pages),
s AS (SELECT 'a' AS side, page_id, volume, url, html, 1 AS copy FROM p
      UNION ALL SELECT 'b', page_id, volume, url, CASE WHEN page_id % 97 = 5 THEN '#' || substring(html, 2) ELSE html END, copy
      FROM p, (SELECT unnest([1, 2]) AS copy)
      WHERE (copy = 1 OR (volume % 7 = 0 AND place = 240)) AND NOT (volume % 7 = 3 AND place >= 990) AND NOT (volume % 7 = 0 AND place BETWEEN 230 AND 232)),
r AS (SELECT *, 'WARC/1.0' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Date: 2020-01-01T00:00:00Z' || chr(13) || chr(10) || 'WARC-Record-ID: <urn:page:' || page_id || '>' || chr(13) || chr(10) || 'WARC-Target-URI: ' || url
        || chr(13) || chr(10) || 'Content-Type: text/html; charset=utf-8' || chr(13) || chr(10) || 'Content-Length: ' || strlen(coalesce(html, '')) AS head, chr(13) || chr(10) || chr(13) || chr(10) AS gap FROM s),
x AS (SELECT side, page_id, volume, copy, head || gap || coalesce(html, '') || gap AS record FROM r),
o AS (SELECT side, page_id, volume, copy, strlen(record) AS length, sha256(record) AS digest, row_number() OVER w - 1 AS record_no,
             CAST(coalesce(sum(strlen(record)) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS "at"
      FROM x WINDOW w AS (PARTITION BY side, volume ORDER BY page_id, copy)),
m AS (SELECT volume, coalesce(a.record_no, b.record_no) AS record_no, page_id, coalesce(a."at", b."at") AS "at", coalesce(a.length, b.length) AS length, a.digest AS expected, b.digest AS found,
             a.record_no = b.record_no AND a."at" = b."at" AS stays
      FROM (SELECT * FROM o WHERE side = 'a') a FULL JOIN (SELECT * FROM o WHERE side = 'b') b USING (volume, page_id, copy))
SELECT volume, record_no, page_id, "at", length, CASE WHEN found IS NULL THEN 'missing' WHEN expected IS NULL THEN 'extra' WHEN expected <> found THEN 'damaged' ELSE 'moved' END AS status, expected, found
FROM m WHERE found IS NULL OR expected IS NULL OR expected <> found OR NOT stays
"""

URL_SQL = r"""
WITH s AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substring(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM (SELECT page_id, coalesce(url, '') AS url FROM pages)),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, rest FROM s),
p AS (SELECT page_id, host, regexp_extract(substring(rest, length(host) + 1), '^[^?#]*') AS path FROM h),
c AS (SELECT *, CASE WHEN host <> '' THEN regexp_replace(host, '^www\.', '') || regexp_replace(path, '/+$', '') END AS canonical FROM p),
l AS (SELECT prefix || label || '.example.' || zone || '/' || lang || '/' || n || ending AS canonical
      FROM range(1000) t(n), (SELECT unnest(['', 'm.', 'blog.']) AS prefix), (SELECT unnest(['ads-track', 'spam-farm', 'casino-win', 'adult-x', 'cheap-pills', 'free-bets']) AS label),
           (SELECT unnest(['com', 'net', 'org']) AS zone), (SELECT unnest(['en', 'de', 'fr', 'es']) AS lang), (SELECT unnest(['', '.html']) AS ending) WHERE n % 5 <> 3),
r AS (SELECT page_id, host, path, c.canonical IN (SELECT canonical FROM l) AS listed,
        CASE WHEN (host = 'example.net' OR host LIKE '%.example.net') AND path LIKE '/en/%' THEN 'example.net/en/'
             WHEN (host = 'example.com' OR host LIKE '%.example.com') AND path LIKE '/de/%' THEN 'example.com/de/'
             WHEN (host = 'org' OR host LIKE '%.org') AND path LIKE '/fr/%' THEN 'org/fr/'
             WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/%' THEN 'net/' END AS rule FROM c)
SELECT page_id, host, path, rule, CASE WHEN rule IN ('example.net/en/', 'org/fr/') THEN 'allow' WHEN rule IS NOT NULL THEN 'block' WHEN coalesce(listed, FALSE) THEN 'block' ELSE 'allow' END AS verdict, coalesce(listed, FALSE) AS listed FROM r
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_topk": TOPK_SQL, "op4_minhash_near_dedup": NEARDUP_SQL, "op9_warc_audit": WARC_SQL, "op10_url_filter": URL_SQL}
