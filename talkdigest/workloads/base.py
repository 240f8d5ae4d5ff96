"""Registry of workload queries, shared inputs, and the common table expressions of their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import gold, meetings

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bundles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return meetings.from_documents(table(spark, sf_dir, "documents"))


def talks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return meetings.from_conversations(table(spark, sf_dir, "conversations"))


def bundles_and_gold(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Gold is built from the utterances several times, so those are kept in memory or on disk for the query, but for their tokens,
    which are larger than the texts and follow from them."""
    utts = meetings.retokenized(bundles(spark, sf_dir).drop("tokens").persist())
    return utts, gold.planted(utts)


def hashed_text(df: DataFrame, column: str = "snippet") -> DataFrame:
    """Long texts are compared by their hash."""
    return df.withColumn(column, F.md5(F.col(column).cast("binary")))


WORDS = r"'[\p{L}\p{N}]+'"

#: u: utterances of bundles.
BUNDLES = rf"""
d AS (SELECT doc_id, coalesce(lang, 'und') AS lang, coalesce(text, '') AS text, row_number() OVER (PARTITION BY coalesce(lang, 'und') ORDER BY doc_id) - 1 AS rk FROM documents),
sp AS (SELECT lang || '-' || CAST(rk // 12 AS BIGINT) AS meeting_id, CAST(rk % 12 AS INTEGER) AS agenda_no, string_split_regex(text, '[.!?\n]+') AS xs FROM d),
ex AS (SELECT meeting_id, agenda_no, trim(unnest(xs)) AS text, unnest(range(len(xs))) AS piece FROM sp),
nu AS (SELECT meeting_id, agenda_no, CAST(row_number() OVER (PARTITION BY meeting_id ORDER BY agenda_no, piece) - 1 AS BIGINT) AS utt_no, text, regexp_extract_all(lower(text), {WORDS}) AS tokens FROM ex WHERE text <> ''),
u AS (SELECT *, CAST(len(tokens) AS BIGINT) AS n_tok, ['PM', 'ME', 'ID', 'UI'][CAST(utt_no % 4 AS INTEGER) + 1] AS speaker,
        CAST(sum(len(tokens)) OVER o AS BIGINT) AS tok_end, CAST(sum(len(tokens)) OVER o - len(tokens) AS BIGINT) AS tok_start,
        CAST(sum(length(text)) OVER o AS BIGINT) AS char_end, CAST(sum(length(text)) OVER o - length(text) AS BIGINT) AS char_start
      FROM nu WINDOW o AS (PARTITION BY meeting_id ORDER BY utt_no ROWS UNBOUNDED PRECEDING)),
ln AS (SELECT meeting_id, max(utt_no) AS last_utt, max(tok_end) AS n FROM u GROUP BY meeting_id)"""

#: u: utterances of conversations.
TALKS = rf"""
nu AS (SELECT CAST(conv_id AS VARCHAR) AS meeting_id, CAST(turn // 2 AS INTEGER) AS agenda_no, CAST(turn AS BIGINT) AS utt_no, role AS speaker, text, regexp_extract_all(lower(text), {WORDS}) AS tokens FROM conversations),
u AS (SELECT *, CAST(len(tokens) AS BIGINT) AS n_tok, CAST(sum(len(tokens)) OVER o AS BIGINT) AS tok_end, CAST(sum(len(tokens)) OVER o - len(tokens) AS BIGINT) AS tok_start,
        CAST(sum(length(text)) OVER o AS BIGINT) AS char_end FROM nu WINDOW o AS (PARTITION BY meeting_id ORDER BY utt_no ROWS UNBOUNDED PRECEDING)),
ln AS (SELECT meeting_id, max(utt_no) AS last_utt, max(tok_end) AS n FROM u GROUP BY meeting_id)"""

#: gold: planted sentences; sp_: their spans.
GOLD = BUNDLES + r""",
it AS (SELECT meeting_id, agenda_no, min(utt_no) AS a, max(utt_no) AS z FROM u GROUP BY meeting_id, agenda_no),
sm AS (SELECT *, lag(z) OVER o AS pz, lag(agenda_no) OVER o AS pa FROM it WINDOW o AS (PARTITION BY meeting_id ORDER BY agenda_no)),
kk AS (SELECT meeting_id, a AS s, z AS t, 2 * agenda_no AS key FROM sm UNION ALL SELECT meeting_id, pz, a, 2 * agenda_no - 1 FROM sm WHERE agenda_no % 2 = 1 AND pa = agenda_no - 1),
oc AS (SELECT *, row_number() OVER (PARTITION BY meeting_id ORDER BY s, t, key) - 1 AS occ, count(*) OVER (PARTITION BY meeting_id) AS n FROM kk),
se AS (SELECT meeting_id, s, t, CAST(CASE WHEN occ % 10 = 0 AND occ + 1 < n THEN occ + 1 WHEN occ % 10 = 1 THEN occ - 1 ELSE occ END AS BIGINT) AS sent_no FROM oc),
ra AS (SELECT se.*, f.speaker AS first_speaker, CASE WHEN s = t THEN f.tokens ELSE list_concat(f.tokens, l.tokens) END AS raw, (5 * CAST(split_part(se.meeting_id, '-', 2) AS BIGINT) + sent_no) % 9 <> 4 AS annotated
       FROM se JOIN u f ON f.meeting_id = se.meeting_id AND f.utt_no = s JOIN u l ON l.meeting_id = se.meeting_id AND l.utt_no = t),
gold AS (SELECT *, [CASE WHEN i % 4 = 0 THEN 'novel' || i ELSE raw[i] END FOR i IN range(1, len(raw) + 1)] AS tokens FROM ra),
sn AS (SELECT meeting_id, sent_no, s AS seg_start, t AS seg_end, CASE WHEN s = t THEN 1 ELSE 2 END AS n_support FROM gold WHERE annotated)"""

#: gr: spans with their snippet number; sg: snippets.
MERGED = GOLD + r""",
rc AS (SELECT *, max(seg_end) OVER (PARTITION BY meeting_id ORDER BY seg_start, seg_end, sent_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM sn),
fr AS (SELECT *, CASE WHEN reach IS NULL OR least(reach, seg_end) - seg_start + 1 < 1 THEN 1 ELSE 0 END AS fresh FROM rc),
gr AS (SELECT *, CAST(sum(fresh) OVER (PARTITION BY meeting_id ORDER BY seg_start, seg_end, sent_no ROWS UNBOUNDED PRECEDING) - 1 AS BIGINT) AS snip_no FROM fr),
sg AS (SELECT meeting_id, snip_no, min(seg_start) AS seg_start, max(seg_end) AS seg_end, list(sent_no ORDER BY seg_start, seg_end, sent_no) AS sent_nos FROM gr GROUP BY meeting_id, snip_no)"""

#: orp: orphans with their snippet; mem: membership; snip: assembled snippets.
ASSEMBLED = MERGED + r""",
sw AS (SELECT DISTINCT sg.meeting_id, snip_no, unnest(u.tokens) AS word FROM sg JOIN u ON u.meeting_id = sg.meeting_id AND u.utt_no BETWEEN seg_start AND seg_end),
ow AS (SELECT DISTINCT meeting_id, sent_no, unnest(tokens) AS word FROM gold WHERE NOT annotated),
ov AS (SELECT ow.meeting_id, sent_no, snip_no, count(*) AS overlap FROM ow JOIN sw ON sw.meeting_id = ow.meeting_id AND sw.word = ow.word GROUP BY ALL),
be AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY meeting_id, sent_no ORDER BY overlap DESC, snip_no) AS r FROM ov) WHERE r = 1),
pr AS (SELECT gold.meeting_id, gold.sent_no, annotated, last_value(gr.snip_no IGNORE NULLS) OVER (PARTITION BY gold.meeting_id ORDER BY gold.sent_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS previous
       FROM gold LEFT JOIN gr ON gr.meeting_id = gold.meeting_id AND gr.sent_no = gold.sent_no),
orp AS (SELECT pr.meeting_id, pr.sent_no, CAST(coalesce(be.snip_no, previous, 0) AS BIGINT) AS snip_no, coalesce(overlap, 0) AS overlap FROM pr LEFT JOIN be ON be.meeting_id = pr.meeting_id AND be.sent_no = pr.sent_no WHERE NOT pr.annotated),
mem AS (SELECT meeting_id, sent_no, snip_no, row_number() OVER (PARTITION BY meeting_id ORDER BY seg_start, seg_end, sent_no) AS place FROM gr UNION ALL SELECT meeting_id, sent_no, snip_no, sent_no + 1000000 FROM orp),
snip AS (SELECT m.meeting_id, m.snip_no, list(m.sent_no ORDER BY place) AS sent_nos, string_agg(array_to_string(g.tokens, ' '), ' ' ORDER BY place) AS text, any_value(sg.seg_start) AS seg_start, any_value(sg.seg_end) AS seg_end
         FROM mem m JOIN gold g ON g.meeting_id = m.meeting_id AND g.sent_no = m.sent_no LEFT JOIN sg ON sg.meeting_id = m.meeting_id AND sg.snip_no = m.snip_no GROUP BY m.meeting_id, m.snip_no)"""

#: spl: meetings with number and split.
SPLIT = r""",
spl AS (SELECT meeting_id, meeting_no, CASE WHEN (53 * meeting_no) % 137 < 97 THEN 'train' WHEN (53 * meeting_no) % 137 < 117 THEN 'validation' ELSE 'test' END AS split
        FROM (SELECT meeting_id, row_number() OVER (ORDER BY meeting_id) - 1 AS meeting_no FROM ln))"""

#: no: snippets widened by noise in the training split.
NOISY = ASSEMBLED + SPLIT + r""",
nc AS (SELECT snip.*, split, meeting_no, last_utt, CASE WHEN split = 'train' THEN (meeting_no * 7919 + snip_no * 104729) % 9 + 6 ELSE 0 END AS noise FROM snip JOIN spl USING (meeting_id) JOIN ln USING (meeting_id)),
no AS (SELECT meeting_id, snip_no, text, split, noise, seg_start AS gold_start, seg_end AS gold_end, greatest(0, seg_start - noise // 2) AS seg_start, least(last_utt, seg_end + noise - noise // 2) AS seg_end FROM nc)"""


def lead_steps(k: int, q: int, resume: str = "after") -> str:
    """Appended to BUNDLES or TALKS under WITH RECURSIVE. st: steps of the lead run with texts."""
    nxt = "least(r.left_utt + {q} - 1, hi.hi) + 1" if resume == "after" else "greatest(least(r.left_utt + {q} - 1, hi.hi), r.left_utt + 1)"
    nxt = nxt.format(q=q)
    return rf""",
hi AS (SELECT a.meeting_id, a.utt_no, greatest(a.utt_no, coalesce(max(b.utt_no), 0)) AS hi FROM u a LEFT JOIN u b ON a.meeting_id = b.meeting_id AND b.tok_end <= a.tok_start + {k} GROUP BY a.meeting_id, a.utt_no),
r AS (SELECT meeting_id, CAST(0 AS BIGINT) AS step, CAST(0 AS BIGINT) AS left_utt FROM ln
      UNION ALL SELECT r.meeting_id, r.step + 1, CAST({nxt} AS BIGINT) FROM r JOIN hi ON hi.meeting_id = r.meeting_id AND hi.utt_no = r.left_utt JOIN ln ON ln.meeting_id = r.meeting_id WHERE least(r.left_utt + {q} - 1, hi.hi) < ln.last_utt),
sb AS (SELECT r.*, hi.hi AS hi_utt, least(r.left_utt + {q} - 1, hi.hi) AS boundary_utt FROM r JOIN hi ON hi.meeting_id = r.meeting_id AND hi.utt_no = r.left_utt),
stx AS (SELECT sb.meeting_id, step, left_utt, hi_utt, boundary_utt, string_agg(u.text, ' ' ORDER BY u.utt_no) AS snippet FROM sb JOIN u ON u.meeting_id = sb.meeting_id AND u.utt_no BETWEEN left_utt AND boundary_utt GROUP BY ALL),
st AS (SELECT x.meeting_id, x.step, x.left_utt, x.hi_utt, a.tok_start AS i_left, CASE WHEN x.hi_utt = x.left_utt THEN least(b.tok_end, a.tok_start + {k}) ELSE b.tok_end END AS i_right, x.snippet, x.boundary_utt,
              coalesce(nx.tok_start, ln.n) - a.tok_start AS stride_tok
       FROM stx x JOIN u a ON a.meeting_id = x.meeting_id AND a.utt_no = x.left_utt JOIN u b ON b.meeting_id = x.meeting_id AND b.utt_no = x.hi_utt JOIN ln ON ln.meeting_id = x.meeting_id
       LEFT JOIN u nx ON nx.meeting_id = x.meeting_id AND nx.utt_no = {"x.boundary_utt + 1" if resume == "after" else "greatest(x.boundary_utt, x.left_utt + 1)"})"""


def window_parts(k: int, q: int) -> str:
    """Appended to BUNDLES: pa: utterance parts of fixed windows; fx: lead snippets of the windows."""
    return rf""",
wn AS (SELECT u.*, greatest(1, CAST(ceil((ln.n - {k}) / CAST({k} AS DOUBLE)) AS BIGINT) + 1) - 1 AS lw FROM u JOIN ln USING (meeting_id)),
we AS (SELECT *, unnest(range(least(lw, tok_start // {k}), least(lw, greatest(tok_end - 1, tok_start) // {k}) + 1)) AS win FROM wn),
wf AS (SELECT *, greatest(0, win * {k} - tok_start) AS win_from, greatest(0, least(n_tok, (win + 1) * {k} - tok_start)) AS win_to FROM we),
pa AS (SELECT *, CASE WHEN win_from = 0 AND win_to = n_tok THEN text ELSE array_to_string(tokens[win_from + 1:win_to], ' ') END AS part, row_number() OVER (PARTITION BY meeting_id, win ORDER BY utt_no) AS nth FROM wf),
fx AS (SELECT meeting_id, CAST(win AS BIGINT) AS step, string_agg(part, ' ' ORDER BY utt_no) FILTER (nth <= {q}) AS snippet, min(tok_start + win_from) AS i_left, CAST(min(tok_start + win_from) + sum(greatest(win_to - win_from, 0)) AS BIGINT) AS i_right FROM pa GROUP BY meeting_id, win)"""


def rouge_sql(outputs: str, references: str, n: int) -> str:
    """outputs, references: CTE names with (meeting_id, text). Appended; rs: match, cand, ref by meeting."""
    gram = "t[i]" if n == 1 else "t[i] || ' ' || t[i + 1]"
    side = lambda src, name: f"{name} AS (SELECT meeting_id, {gram} AS g, count(*) AS c FROM (SELECT meeting_id, t, unnest(range(1, len(t) - {n - 1} + 1)) AS i FROM (SELECT meeting_id, regexp_extract_all(lower(text), {WORDS}) AS t FROM {src})) GROUP BY ALL)"
    return rf""",
{side(outputs, "ca")}, {side(references, "cb")},
cm AS (SELECT ca.meeting_id, sum(least(ca.c, cb.c)) AS m FROM ca JOIN cb USING (meeting_id, g) GROUP BY ALL),
rs AS (SELECT meeting_id, coalesce(m, 0) AS m, coalesce(x, 0) AS x, coalesce(y, 0) AS y FROM (SELECT meeting_id, sum(c) AS x FROM ca GROUP BY ALL) FULL JOIN (SELECT meeting_id, sum(c) AS y FROM cb GROUP BY ALL) USING (meeting_id) LEFT JOIN cm USING (meeting_id)),
rm AS (SELECT count(*) AS n, round(avg(CASE WHEN x > 0 THEN m / x ELSE 0 END), 6) AS p, round(avg(CASE WHEN y > 0 THEN m / y ELSE 0 END), 6) AS r, round(avg(CASE WHEN x + y > 0 THEN 2.0 * m / (x + y) ELSE 0 END), 6) AS f FROM rs)"""
