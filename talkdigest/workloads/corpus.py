"""Corpus statistics, order agreement, coverage and summary conversion on planted gold."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import analysis, convert, coref, split
from ..sources import gold as planted
from ..sources import meetings
from .base import ASSEMBLED, BUNDLES, GOLD, MERGED, NOISY, SPLIT, TALKS, WORDS, bundles, bundles_and_gold, hashed_text, query, table, talks

UTT_SQL = "SELECT meeting_id, agenda_no, utt_no, speaker, md5(text) AS text, n_tok, tok_start, tok_end, char_start, char_end FROM u"


@query("bundle_utterances", f"WITH {BUNDLES} {UTT_SQL}")
def bundle_utterances(spark, d):
    return hashed_text(bundles(spark, d), "text").drop("tokens")


@query("talk_utterances", f"WITH {TALKS} SELECT meeting_id, agenda_no, utt_no, speaker, md5(text) AS text, n_tok, tok_start, tok_end, char_end FROM u")
def talk_utterances(spark, d):
    return hashed_text(talks(spark, d), "text").drop("tokens", "char_start")


PAGES = rf"""
ns AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '(?s)<!--.*?-->', '', 'g'), '(?s)<script[ >].*?</script>', '', 'g'), '(?s)<style[ >].*?</style>', '', 'g'), '(?s)<nav[ >].*?</nav>', '', 'g'), '(?s)<footer[ >].*?</footer>', '', 'g') AS h FROM pages),
pp AS (SELECT page_id, h, string_split_regex(h, '<p>|<p [^>]*>') AS xs FROM ns),
pe AS (SELECT page_id, unnest(xs[2:]) AS x, unnest(range(len(xs) - 1)) AS i FROM pp),
pl AS (SELECT page_id, i, trim(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(x, '(?s)</p>.*', '', 'g'), '<[^>]*>', '', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&')) AS text FROM pe),
pu AS (SELECT CAST(page_id AS VARCHAR) AS meeting_id, row_number() OVER (PARTITION BY page_id ORDER BY i) - 1 AS utt_no, text, CAST(len(regexp_extract_all(lower(text), {WORDS})) AS BIGINT) AS n_tok FROM pl WHERE text <> ''),
ph AS (SELECT CAST(page_id AS VARCHAR) AS meeting_id, trim(replace(replace(replace(replace(replace(replace(regexp_replace(regexp_extract(h, '(?s)<h1[^>]*>(.*?)</h1>', 1), '<[^>]*>', '', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&')) AS headline FROM ns)"""


@query("page_utterances", f"WITH {PAGES} SELECT pu.meeting_id, utt_no, md5(text) AS text, n_tok, md5(headline) AS headline FROM pu JOIN ph USING (meeting_id)")
def page_utterances(spark, d):
    rows = meetings.from_pages(table(spark, d, "pages"))
    return hashed_text(hashed_text(rows, "text"), "headline").drop("tokens")


@query("corpus_stats", rf"""WITH {GOLD}, {PAGES},
a AS (SELECT count(*) AS meetings, round(avg(s), 6) AS source_sentences, round(avg(w), 6) AS source_words FROM (SELECT count(*) AS s, sum(n_tok) AS w FROM u GROUP BY meeting_id)),
b AS (SELECT round(avg(s), 6) AS summary_sentences, round(avg(w), 6) AS summary_words FROM (SELECT count(*) AS s, sum(len(tokens)) AS w FROM gold GROUP BY meeting_id)),
c AS (SELECT count(*) AS meetings, round(avg(s), 6) AS source_sentences, round(avg(w), 6) AS source_words FROM (SELECT count(*) AS s, sum(n_tok) AS w FROM pu GROUP BY meeting_id)),
e AS (SELECT round(avg(1), 6) AS summary_sentences, round(avg(len(regexp_extract_all(lower(headline), {WORDS}))), 6) AS summary_words FROM ph),
t AS (SELECT count(*) AS meetings, round(avg(s), 6) AS source_sentences, round(avg(w), 6) AS source_words FROM (SELECT count(*) AS s, sum(len(regexp_extract_all(lower(text), {WORDS}))) AS w FROM conversations GROUP BY conv_id)),
l AS (SELECT 'documents-' || lang AS corpus, count(*) AS meetings, round(avg(len([x FOR x IN string_split_regex(text, '[.!?\n]+') IF trim(x) <> ''])), 6) AS source_sentences, round(avg(len(regexp_extract_all(lower(text), {WORDS}))), 6) AS source_words FROM documents WHERE lang IS NOT NULL AND text IS NOT NULL GROUP BY lang)
SELECT 'bundles' AS corpus, * FROM a, b UNION ALL SELECT 'pages', * FROM c, e UNION ALL SELECT 'conversations', *, NULL, NULL FROM t UNION ALL SELECT *, NULL, NULL FROM l""")
def corpus_stats(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    pages = table(spark, d, "pages")
    heads = pages.select(F.col("page_id").cast("string").alias("meeting_id"), T.words(T.headline(F.col("html"))).alias("tokens"))
    out = analysis.corpus_stats(utts, gold, "bundles").unionByName(analysis.corpus_stats(meetings.from_pages(pages), heads, "pages"))
    none = talks(spark, d).limit(0)
    out = out.unionByName(analysis.corpus_stats(talks(spark, d), none, "conversations"))
    docs = table(spark, d, "documents").where("lang is not null and text is not null")
    by_lang = docs.groupBy(F.concat(F.lit("documents-"), "lang").alias("corpus")).agg(F.count("*").alias("meetings"), F.round(F.avg(F.size(T.sentences(F.col("text")))), 6).alias("source_sentences"), F.round(F.avg(F.size(T.words(F.col("text")))), 6).alias("source_words"))
    return out.unionByName(by_lang, allowMissingColumns=True)


@query("role_stats", f"WITH {BUNDLES} SELECT speaker, count(*) AS turns, CAST(sum(n_tok) AS BIGINT) AS words, count(DISTINCT meeting_id) AS meetings FROM u GROUP BY speaker")
def role_stats(spark, d):
    return analysis.role_stats(bundles(spark, d))


@query("role_pivot", """SELECT conv_id, count(*) FILTER (role = 'assistant') AS assistant, count(*) FILTER (role = 'system') AS system, count(*) FILTER (role = 'user') AS "user" FROM conversations GROUP BY conv_id""")
def role_pivot(spark, d):
    rows = table(spark, d, "conversations").groupBy("conv_id").pivot("role", ["assistant", "system", "user"]).count()
    return rows.na.fill(0, ["assistant", "system", "user"])


@query("split_sizes", f"WITH {MERGED}{SPLIT} SELECT split, count(*) AS meetings, CAST(sum(k) AS BIGINT) AS snippets FROM (SELECT split, (SELECT count(*) FROM sg WHERE sg.meeting_id = spl.meeting_id) AS k FROM spl) GROUP BY split")
def split_sizes(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    snippets = convert.merge(analysis.support_spans(gold)).groupBy("meeting_id").agg(F.count("*").alias("k"))
    return split.assign(utts).join(snippets, "meeting_id", "left").groupBy("split").agg(F.count("*").alias("meetings"), F.coalesce(F.sum("k"), F.lit(0)).alias("snippets"))


@query("split_exact", f"WITH {BUNDLES}, m AS (SELECT meeting_id, row_number() OVER (ORDER BY meeting_id) - 1 AS i FROM ln) SELECT CASE WHEN i < 50 THEN 'train' WHEN i < 60 THEN 'validation' ELSE 'test' END AS split, count(*) AS meetings FROM m GROUP BY 1")
def split_exact(spark, d):
    return split.assign_exact(bundles(spark, d), 50, 10).groupBy("split").agg(F.count("*").alias("meetings"))


@query("gold_sentences", f"WITH {GOLD} SELECT meeting_id, sent_no, md5(array_to_string(tokens, ' ')) AS text, CAST(len(tokens) AS BIGINT) AS n_words, annotated FROM gold")
def gold_sentences(spark, d):
    _, gold = bundles_and_gold(spark, d)
    return hashed_text(gold, "text").select("meeting_id", "sent_no", "text", F.size("tokens").cast("long").alias("n_words"), F.col("support").isNotNull().alias("annotated"))


@query("support_spans", f"WITH {GOLD} SELECT meeting_id, sent_no, seg_start, seg_end, CAST(n_support AS BIGINT) AS n_support FROM sn")
def support_spans(spark, d):
    return analysis.support_spans(bundles_and_gold(spark, d)[1])


@query("occurrence_order", f"WITH {GOLD} SELECT meeting_id, sent_no, row_number() OVER (PARTITION BY meeting_id ORDER BY seg_start, seg_end, sent_no) - 1 AS occ_rank, row_number() OVER (PARTITION BY meeting_id ORDER BY sent_no) - 1 AS sum_rank FROM sn")
def occurrence_order(spark, d):
    return analysis.occurrence_order(analysis.support_spans(bundles_and_gold(spark, d)[1])).select("meeting_id", "sent_no", "occ_rank", "sum_rank")


AGREE = "SELECT '{m}' AS measure, CAST(sum(hits) AS BIGINT) AS hits, CAST(sum(total) AS BIGINT) AS total, round(sum(hits) / sum(total), 6) AS micro, round(avg(hits / total), 6) AS macro FROM x"
AGREE_SQL = {
    "rank": f"WITH {GOLD}, y AS (SELECT meeting_id, row_number() OVER (PARTITION BY meeting_id ORDER BY seg_start, seg_end, sent_no) = row_number() OVER (PARTITION BY meeting_id ORDER BY sent_no) AS hit FROM sn), x AS (SELECT count(*) FILTER (hit) AS hits, count(*) AS total FROM y GROUP BY meeting_id) " + AGREE.format(m="rank"),
    "adjacent": f"WITH {GOLD}, y AS (SELECT meeting_id, seg_start, lag(seg_start) OVER (PARTITION BY meeting_id ORDER BY sent_no) AS b FROM sn), x AS (SELECT count(*) FILTER (b <= seg_start) AS hits, count(*) AS total FROM y WHERE b IS NOT NULL GROUP BY meeting_id) " + AGREE.format(m="adjacent"),
    "kendall": f"WITH {GOLD}, x AS (SELECT count(*) FILTER (a.seg_start <= b.seg_start) AS hits, count(*) AS total FROM sn a JOIN sn b ON a.meeting_id = b.meeting_id AND a.sent_no < b.sent_no GROUP BY a.meeting_id) " + AGREE.format(m="kendall"),
    "lis": f"""WITH RECURSIVE {GOLD}, q AS (SELECT meeting_id, row_number() OVER (PARTITION BY meeting_id ORDER BY sent_no) AS i, seg_start FROM sn),
r AS (SELECT meeting_id, i, seg_start, 1 AS l FROM q UNION SELECT q.meeting_id, q.i, q.seg_start, r.l + 1 FROM r JOIN q ON q.meeting_id = r.meeting_id AND q.i > r.i AND q.seg_start >= r.seg_start),
x AS (SELECT meeting_id, max(l) AS hits, max(i) AS total FROM r GROUP BY meeting_id) """ + AGREE.format(m="lis"),
}
for _measure, _sql in AGREE_SQL.items():
    query(f"order_agreement_{_measure}", _sql)(lambda spark, d, m=_measure: analysis.order_agreement(analysis.support_spans(bundles_and_gold(spark, d)[1]), m))


def _coverage_sql(count: str, avg: str) -> str:
    c, w = ("1", "1") if count == "set" else ("count(*)", "count(*)")
    value = "sum(m) / sum(t)" if avg == "micro" else "avg(m / t)"
    return rf"""WITH {GOLD},
ga AS (SELECT meeting_id, sent_no, word, {c} AS c FROM (SELECT meeting_id, sent_no, unnest(tokens) AS word FROM gold WHERE annotated) GROUP BY meeting_id, sent_no, word),
gb AS (SELECT meeting_id, sent_no, word, {w} AS c FROM (SELECT sn.meeting_id, sn.sent_no, unnest(u.tokens) AS word FROM sn JOIN u ON u.meeting_id = sn.meeting_id AND u.utt_no BETWEEN seg_start AND seg_end) GROUP BY meeting_id, sent_no, word),
gc AS (SELECT ga.meeting_id, ga.sent_no, sum(least(ga.c, coalesce(gb.c, 0))) AS m, sum(ga.c) AS t FROM ga LEFT JOIN gb ON gb.meeting_id = ga.meeting_id AND gb.sent_no = ga.sent_no AND gb.word = ga.word GROUP BY ga.meeting_id, ga.sent_no)
SELECT CAST(sum(m) AS BIGINT) AS matched, CAST(sum(t) AS BIGINT) AS total, round({value}, 6) AS coverage FROM gc"""


for _avg in ("micro", "macro"):
    for _count in ("multiset", "set"):
        def _coverage(spark, d, a=_avg, c=_count):
            utts, gold = bundles_and_gold(spark, d)
            return analysis.coverage(gold, analysis.segments(utts, gold), c, a)

        query(f"segment_coverage_{_avg}_{_count}", _coverage_sql(_count, _avg))(_coverage)


@query("support_coverage", rf"""WITH {GOLD},
mk AS (SELECT meeting_id, sent_no, s AS utt_no FROM gold WHERE annotated UNION SELECT meeting_id, sent_no, t FROM gold WHERE annotated),
ga AS (SELECT meeting_id, sent_no, word, count(*) AS c FROM (SELECT meeting_id, sent_no, unnest(tokens) AS word FROM gold WHERE annotated) GROUP BY ALL),
gb AS (SELECT meeting_id, sent_no, word, count(*) AS c FROM (SELECT mk.meeting_id, mk.sent_no, unnest(u.tokens) AS word FROM mk JOIN u USING (meeting_id, utt_no)) GROUP BY ALL)
SELECT CAST(sum(least(ga.c, coalesce(gb.c, 0))) AS BIGINT) AS matched, CAST(sum(ga.c) AS BIGINT) AS total, round(sum(least(ga.c, coalesce(gb.c, 0))) / sum(ga.c), 6) AS coverage FROM ga LEFT JOIN gb ON gb.meeting_id = ga.meeting_id AND gb.sent_no = ga.sent_no AND gb.word = ga.word""")
def support_coverage(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return analysis.coverage(gold, analysis.segments(utts, gold, "support"))


@query("novelty_bigram", rf"""WITH {GOLD},
ga AS (SELECT meeting_id, sent_no, g, count(*) AS c FROM (SELECT meeting_id, sent_no, tokens[i] || ' ' || tokens[i + 1] AS g FROM (SELECT *, unnest(range(1, len(tokens))) AS i FROM gold WHERE annotated)) GROUP BY ALL),
gb AS (SELECT meeting_id, sent_no, g, count(*) AS c FROM (SELECT meeting_id, sent_no, tk[i] || ' ' || tk[i + 1] AS g FROM (SELECT sn.meeting_id, sn.sent_no, u.tokens AS tk, unnest(range(1, len(u.tokens))) AS i FROM sn JOIN u ON u.meeting_id = sn.meeting_id AND u.utt_no BETWEEN seg_start AND seg_end)) GROUP BY ALL)
SELECT round(1 - sum(least(ga.c, coalesce(gb.c, 0))) / sum(ga.c), 6) AS novelty FROM ga LEFT JOIN gb ON gb.meeting_id = ga.meeting_id AND gb.sent_no = ga.sent_no AND gb.g = ga.g""")
def novelty_bigram(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return analysis.novelty(gold, analysis.segments(utts, gold), 2)


SUPPORT = r"mk AS (SELECT meeting_id, s AS utt_no FROM gold WHERE annotated UNION SELECT meeting_id, t FROM gold WHERE annotated), su AS (SELECT u.*, ln.n FROM mk JOIN u USING (meeting_id, utt_no) JOIN ln USING (meeting_id))"


@query("lead_bias", f"WITH {GOLD}, {SUPPORT}, x AS (SELECT CAST(least(9, floor(10 * tok_start / CAST(n AS DOUBLE))) AS INTEGER) AS decile, count(*) AS utterances, CAST(sum(n_tok) AS BIGINT) AS words FROM su WHERE n > 0 GROUP BY 1) SELECT *, round(words / sum(words) OVER (), 6) AS share FROM x")
def lead_bias(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return analysis.lead_bias(utts, gold)


@query("truncation_loss", f"WITH {GOLD}, {SUPPORT} SELECT CAST(1024 AS BIGINT) AS k, count(*) AS utterances, count(*) FILTER (tok_end > 1024) AS lost_utterances, CAST(sum(n_tok) AS BIGINT) AS words, CAST(sum(n_tok) FILTER (tok_end > 1024) AS BIGINT) AS lost_words, count(DISTINCT meeting_id) AS meetings, count(DISTINCT meeting_id) FILTER (n > 1024) AS cut_meetings FROM su")
def truncation_loss(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return analysis.truncation_loss(utts, gold)


@query("support_containment", "SELECT b.item_id, d.doc_id, length(d.text) AS doc_chars FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def support_containment(spark, d):
    from ..operators.relational import containment

    return containment(table(spark, d, "benchmark"), table(spark, d, "documents"))


@query("snippet_merge", f"WITH {MERGED} SELECT meeting_id, snip_no, seg_start, seg_end, array_to_string(sent_nos, ',') AS sent_nos FROM sg")
def snippet_merge(spark, d):
    rows = convert.merge(analysis.support_spans(bundles_and_gold(spark, d)[1]))
    return rows.withColumn("sent_nos", F.array_join(rows.sent_nos.cast("array<string>"), ","))


@query("snippet_orphans", f"WITH {ASSEMBLED} SELECT meeting_id, sent_no, snip_no, overlap FROM orp")
def snippet_orphans(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    spans = analysis.support_spans(gold)
    return convert.place_orphans(gold, convert.grouped(spans), convert.merge(spans), utts)


@query("snippet_pronouns", rf"""WITH {ASSEMBLED},
rl AS (SELECT meeting_id, sent_no, 'the ' || CASE first_speaker WHEN 'PM' THEN 'project manager' WHEN 'ME' THEN 'marketing expert' WHEN 'ID' THEN 'industrial designer' ELSE 'user interface designer' END AS role, tokens FROM gold),
x AS (SELECT m.meeting_id, m.snip_no, list(m.sent_no ORDER BY place)[1] AS first_no, string_agg(role || ' ' || array_to_string(tokens, ' '), ' ' ORDER BY place) AS text_a,
             string_agg(CASE WHEN rl.sent_no % 6 = 5 THEN 'they' ELSE role END || CASE WHEN len(tokens) > 0 THEN ' ' ELSE ' ' END || array_to_string(tokens, ' '), ' ' ORDER BY place) AS raw, first(role ORDER BY place) AS role1
      FROM mem m JOIN rl ON rl.meeting_id = m.meeting_id AND rl.sent_no = m.sent_no GROUP BY ALL)
SELECT meeting_id, snip_no, first_no % 6 = 5 AS repaired, md5(CASE WHEN first_no % 6 = 5 THEN role1 || raw[5:] ELSE raw END) AS text FROM x""")
def snippet_pronouns(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    spoken, spans = planted.with_speakers(gold), analysis.support_spans(gold)
    marked = convert.grouped(spans)
    snippets = convert.assembled(spoken, convert.membership(marked, convert.place_orphans(gold, marked, convert.merge(spans), utts)), convert.merge(spans))
    return hashed_text(coref.resolve_openings(snippets, planted.chains(gold)), "text").select("meeting_id", "snip_no", "repaired", "text")


@query("heuristic_chains", rf"""WITH {GOLD},
rl AS (SELECT meeting_id, sent_no, CASE first_speaker WHEN 'PM' THEN 'project manager' WHEN 'ME' THEN 'marketing expert' WHEN 'ID' THEN 'industrial designer' ELSE 'user interface designer' END AS role FROM gold),
pv AS (SELECT meeting_id, sent_no, last_value(CASE WHEN sent_no % 6 <> 5 THEN role END IGNORE NULLS) OVER (PARTITION BY meeting_id ORDER BY sent_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS referent FROM rl)
SELECT meeting_id, sent_no, 'they' AS mention, referent FROM pv WHERE sent_no % 6 = 5 AND referent IS NOT NULL""")
def heuristic_chains(spark, d):
    from ..schema import ROLES

    return coref.heuristic_chains(planted.with_speakers(bundles_and_gold(spark, d)[1]), list(ROLES.values()), ["they"])


@query("snippet_samples", f"WITH {ASSEMBLED} SELECT meeting_id, snip_no, array_to_string(sent_nos, ',') AS sent_nos, md5(text) AS text, seg_start, seg_end FROM snip")
def snippet_samples(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    rows = convert.converted(utts, gold, analysis.support_spans(gold))
    return hashed_text(rows, "text").withColumn("sent_nos", F.array_join(rows.sent_nos.cast("array<string>"), ","))


@query("noise_samples", f"WITH {NOISY} SELECT meeting_id, snip_no, split, CAST(noise AS BIGINT) AS noise, gold_start, gold_end, seg_start, seg_end FROM no")
def noise_samples(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    rows = convert.add_noise(convert.converted(utts, gold, analysis.support_spans(gold)), utts, split.assign(utts))
    return rows.select("meeting_id", "snip_no", "split", "noise", "gold_start", "gold_end", "seg_start", "seg_end")


@query("targets", rf"""WITH {NOISY} SELECT no.meeting_id, no.snip_no, md5(string_agg(u.text, ' ' ORDER BY u.utt_no)) AS source, md5(no.text || ' [SEP] ' || any_value(l.text)) AS target
FROM no JOIN u ON u.meeting_id = no.meeting_id AND u.utt_no BETWEEN no.seg_start AND no.seg_end JOIN u l ON l.meeting_id = no.meeting_id AND l.utt_no = gold_end GROUP BY no.meeting_id, no.snip_no, no.text""")
def targets(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    rows = convert.add_noise(convert.converted(utts, gold, analysis.support_spans(gold)), utts, split.assign(utts))
    out = convert.samples(rows, utts)
    return hashed_text(hashed_text(out, "source"), "target").select("meeting_id", "snip_no", "source", "target")


@query("dedup_sentences", rf"""WITH e AS (SELECT CAST(doc_id AS VARCHAR) AS meeting_id, trim(unnest(xs)) AS x, unnest(range(len(xs))) AS i FROM (SELECT doc_id, string_split_regex(text, '[.!?\n]+') AS xs FROM documents)),
n AS (SELECT *, row_number() OVER (PARTITION BY meeting_id, trim(regexp_replace(lower(x), '\s+', ' ', 'g')) ORDER BY i) AS nth FROM e WHERE x <> '')
SELECT meeting_id, md5(coalesce(string_agg(x, '. ' ORDER BY i) FILTER (nth = 1), '')) AS text, count(*) AS sentences, count(*) FILTER (nth > 1) AS repeated FROM n GROUP BY meeting_id""")
def dedup_sentences(spark, d):
    from ..operators.runs import dedup_sentences as drop

    return hashed_text(drop(table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("meeting_id"), "text")), "text")
