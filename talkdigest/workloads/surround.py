"""Relational operators, functions, formats and streams that a user of the method needs around it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import register as R
from ..functions import subword
from ..functions import text as T
from ..operators import relational
from ..operators.iteration import cut, shared_dir
from ..plans import planner
from ..sources import io, layout
from ..streaming import live
from .base import BUNDLES, GOLD, TALKS, bundles, bundles_and_gold, lead_steps, query, table, talks


def one(name: str, sql: str, spark_sql: str | None = None):
    """A query whose Spark SQL text is the same as, or given beside, the oracle's."""
    def run(spark, d):
        import re

        text = spark_sql or sql
        for t in set(re.findall(r"\b(region|nation|customer|supplier|part|orders|lineitem|events|documents|embeddings|pages|benchmark|labels|conversations)\b", text)):
            text = re.sub(rf"(?i)\b(from|join)\s+{t}\b(?!\.)", rf"\1 parquet.`{d}/{t}.parquet`", text)
        return spark.sql(text)

    query(name, sql)(run)


# scans, projections, predicates

@query("scan_pruned", "SELECT conv_id, turn FROM conversations WHERE role = 'user' AND turn >= 2")
def scan_pruned(spark, d):
    return io.read_meetings(spark, f"{d}/conversations.parquet", ["conv_id", "turn"], "role = 'user' and turn >= 2")


for _fmt in ("json", "csv", "orc", "text"):
    def _roundtrip(spark, d, fmt=_fmt):
        rows = table(spark, d, "conversations")
        path = f"{shared(spark)}/roundtrip-{fmt}-{unique()}"
        io.write(rows.select("text") if fmt == "text" else rows, path, fmt)
        if fmt == "text":
            return spark.read.text(path).select(F.length("value").cast("long").alias("chars")).agg(F.sum("chars").alias("chars"), F.count(F.lit(1)).alias("lines"))
        return io.read_meetings(spark, path, fmt=fmt, schema="conv_id bigint, turn bigint, role string, text string")

    query(f"roundtrip_{_fmt}", "SELECT conv_id, turn, role, text FROM conversations" if _fmt != "text" else "SELECT CAST(sum(length(text) - (length(text) - length(replace(text, chr(10), '')))) AS BIGINT) AS chars, CAST(sum(1 + length(text) - length(replace(text, chr(10), ''))) AS BIGINT) AS lines FROM conversations")(_roundtrip)


def shared(spark) -> str:
    return shared_dir(spark)


def unique() -> str:
    import uuid

    return uuid.uuid4().hex


@query("nested_parquet", f"WITH {BUNDLES} SELECT meeting_id, utt_no, speaker, n_tok, tok_start, tok_end FROM u")
def nested_parquet(spark, d):
    rows = layout.nest(bundles(spark, d)).withColumn("lang", F.substring_index("meeting_id", "-", 1))
    path = f"{shared(spark)}/nested-{unique()}"
    io.write(rows, path, by=["lang"])
    return layout.unnest(io.read_meetings(spark, path)).drop("text", "char_end")


@query("bucketed_meetings", f"WITH {TALKS} SELECT meeting_id, count(*) AS turns FROM u GROUP BY meeting_id")
def bucketed_meetings(spark, d):
    name = f"talks_{unique()}"
    io.write_bucketed(talks(spark, d).select("meeting_id", "utt_no"), name, 4)
    return spark.table(name).groupBy("meeting_id").agg(F.count("*").alias("turns"))


one("project_lengths", "SELECT doc_id, n_chars * 2 AS doubled, CASE WHEN n_chars > 2000 THEN 'long' WHEN n_chars > 500 THEN 'middle' ELSE 'short' END AS size_class FROM documents")
one("filter_predicates", "SELECT doc_id FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 100 AND 2000 AND source LIKE 'src1%' AND regexp_matches(text, '^[A-M]') AND NOT (lang IS NOT DISTINCT FROM NULL)",
    "SELECT doc_id FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 100 AND 2000 AND source LIKE 'src1%' AND text RLIKE '^[A-M]' AND NOT (lang <=> NULL)")

# joins


@query("join_broadcast_roles", "SELECT c.role, full_name, count(*) AS turns FROM conversations c JOIN (VALUES ('system', 'system prompt'), ('user', 'person asking'), ('assistant', 'assistant answering')) r(role, full_name) ON c.role = r.role GROUP BY ALL")
def join_broadcast_roles(spark, d):
    roles = spark.createDataFrame([("system", "system prompt"), ("user", "person asking"), ("assistant", "assistant answering")], "role string, full_name string")
    return table(spark, d, "conversations").join(planner.small(roles), "role").groupBy("role", "full_name").agg(F.count("*").alias("turns"))


for _hint in ("merge", "shuffle_hash"):
    query(f"join_{_hint}", "SELECT o_orderpriority, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")(
        lambda spark, d, h=_hint: table(spark, d, "lineitem").select("l_orderkey").join(table(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint(h), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("lines")))


@query("join_salted", "SELECT o_orderpriority, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_salted(spark, d):
    return relational.salted_join(table(spark, d, "lineitem").select(F.col("l_orderkey").alias("key"), "l_linenumber", "l_partkey"), table(spark, d, "orders").select(F.col("o_orderkey").alias("key"), "o_orderpriority"), "key", 4).groupBy("o_orderpriority").agg(F.count("*").alias("lines"))


@query("join_links", f"WITH {GOLD} SELECT meeting_id, sent_no, utt_no, md5(text) AS text FROM (SELECT meeting_id, sent_no, s AS utt_no FROM gold WHERE annotated UNION SELECT meeting_id, sent_no, t FROM gold WHERE annotated) JOIN u USING (meeting_id, utt_no)")
def join_links(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    links = gold.where("support is not null").select("meeting_id", "sent_no", F.explode("support").alias("utt_no"))
    return links.join(utts.select("meeting_id", "utt_no", F.md5(F.col("text").cast("binary")).alias("text")), ["meeting_id", "utt_no"])


for _how in ("left", "right", "full"):
    one(f"join_outer_{_how}", f"SELECT coalesce(d.doc_id, -1) AS doc_id, coalesce(l.doc_id, -1) AS labelled, coalesce(quality, -1) AS quality FROM documents d {_how.upper()} JOIN labels l ON d.doc_id = l.doc_id")
one("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
one("join_anti", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)", "SELECT d.doc_id, d.lang FROM documents d LEFT ANTI JOIN labels l ON l.doc_id = d.doc_id")

INTERVAL = f"WITH {GOLD} SELECT sn.meeting_id, sent_no, count(*) AS utterances, CAST(sum(n_tok) AS BIGINT) AS words FROM sn JOIN u ON u.meeting_id = sn.meeting_id AND u.utt_no BETWEEN seg_start AND seg_end GROUP BY ALL"
for _kind, _join in (("expanded", relational.interval_expanded), ("theta", relational.interval_theta)):
    def _interval(spark, d, join=_join):
        from ..operators.analysis import support_spans

        utts, gold = bundles_and_gold(spark, d)
        return join(utts.select("meeting_id", "utt_no", "n_tok"), support_spans(gold).select("meeting_id", "sent_no", "seg_start", "seg_end")).groupBy("meeting_id", "sent_no").agg(F.count("*").alias("utterances"), F.sum("n_tok").alias("words"))

    query(f"join_interval_{_kind}", INTERVAL)(_interval)


@query("join_asof", "WITH c AS (SELECT user_id, ts, max(event_id) AS id FROM events WHERE event_type = 'click' GROUP BY ALL), e AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'error') SELECT e.event_id, coalesce(c.id, -1) AS click_id FROM e ASOF LEFT JOIN c ON e.user_id = c.user_id AND e.ts >= c.ts")
def join_asof(spark, d):
    rows = table(spark, d, "events")
    clicks = rows.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("id"))
    return relational.as_of(rows.where("event_type = 'error'").select("event_id", "user_id", "ts"), clicks, "user_id", "ts", "id", "click_id").select("event_id", F.coalesce("click_id", F.lit(-1)).alias("click_id"))


one("join_cross_k", "SELECT k, count(*) AS conversations, CAST(sum(CASE WHEN chars > k THEN 1 ELSE 0 END) AS BIGINT) AS longer FROM (SELECT conv_id, sum(length(text)) AS chars FROM conversations GROUP BY conv_id) c CROSS JOIN (SELECT 500 AS k UNION ALL SELECT 1000 UNION ALL SELECT 2000) g GROUP BY k")


@query("lateral_sentences", r"SELECT doc_id, CAST(i AS INTEGER) AS place, md5(x) AS sentence FROM (SELECT doc_id, xs, unnest(xs) AS x, unnest(range(len(xs))) AS i FROM (SELECT doc_id, [trim(y) FOR y IN string_split_regex(text, '[.!?\n]+') IF trim(y) <> ''] AS xs FROM documents))")
def lateral_sentences(spark, d):
    return table(spark, d, "documents").select("doc_id", F.posexplode(T.sentences(F.col("text"))).alias("place", "s")).select("doc_id", "place", F.md5(F.col("s").cast("binary")).alias("sentence"))


# aggregates

one("agg_by_lang", "SELECT lang, count(*) AS docs, CAST(sum(n_chars) AS BIGINT) AS chars, min(n_chars) AS least, max(n_chars) AS most, round(avg(n_chars), 6) AS mean FROM documents GROUP BY lang")
one("agg_distinct", "SELECT role, count(DISTINCT conv_id) AS meetings, count(*) FILTER (WHERE turn > 2) AS later, CAST(sum(CASE WHEN length(text) > 200 THEN 1 ELSE 0 END) AS BIGINT) AS long_ones FROM conversations GROUP BY role")
one("agg_sets", "SELECT lang, source, count(*) AS n, CAST(grouping(lang) AS INTEGER) AS g FROM documents GROUP BY GROUPING SETS ((lang), (source), (lang, source), ())")
one("agg_cube", "SELECT lang, source, CAST(sum(n_chars) AS BIGINT) AS chars, CAST(grouping(lang) * 2 + grouping(source) AS INTEGER) AS g FROM documents GROUP BY CUBE (lang, source)")
one("agg_rollup", "SELECT lang, source, CAST(sum(n_chars) AS BIGINT) AS chars, CAST(grouping(lang) * 2 + grouping(source) AS INTEGER) AS g FROM documents GROUP BY ROLLUP (lang, source)")
one("agg_decimal", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS total FROM lineitem GROUP BY l_returnflag")
one("agg_argmax", "SELECT conv_id, max_by(turn, length(text) * 1000 + turn) AS longest_turn, min_by(turn, length(text) * 1000 + turn) AS shortest_turn FROM conversations GROUP BY conv_id")


@query("agg_approx")
def agg_approx(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.approx_count_distinct("text", 0.02).alias("texts"), F.percentile_approx("n_chars", F.array(F.lit(0.5), F.lit(0.9)), 10000).alias("quantiles"))


@query("agg_transcript", "SELECT conv_id, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn)) AS transcript FROM conversations GROUP BY conv_id")
def agg_transcript(spark, d):
    lines = F.transform(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))), lambda x: F.concat(x["role"], F.lit(": "), x["text"]))
    return table(spark, d, "conversations").groupBy("conv_id").agg(F.md5(F.array_join(lines, "\n").cast("binary")).alias("transcript"))


@query("pivot_scores", "SELECT l_returnflag AS kind, round(avg(l_quantity), 6) AS quantity, round(avg(l_discount), 6) AS discount, round(avg(l_tax), 6) AS tax FROM lineitem GROUP BY l_returnflag")
def pivot_scores(spark, d):
    """Unpivot the lines' measures to (kind, measure, value), then pivot the means."""
    names = ("quantity", "discount", "tax")
    rows = table(spark, d, "lineitem").select(F.col("l_returnflag").alias("kind"), *[F.col(f"l_{c}").cast("double").alias(c) for c in names])
    rows = rows.unpivot(["kind"], list(names), "measure", "value").groupBy("kind").pivot("measure", list(names)).agg(F.avg("value"))
    return rows.select("kind", *[F.round(c, 6).alias(c) for c in names])


one("unpivot_sizes", "SELECT conv_id, measure, value FROM (SELECT conv_id, CAST(count(*) AS BIGINT) AS turns, CAST(max(length(text)) AS BIGINT) AS longest FROM conversations GROUP BY conv_id) UNPIVOT (value FOR measure IN (turns, longest))")

# windows

one("win_rank", "SELECT conv_id, turn, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
one("win_lag_lead", "SELECT conv_id, turn, coalesce(lag(length(text)) OVER w, -1) AS before, coalesce(lead(length(text), 2) OVER w, -1) AS ahead, first_value(turn) OVER w AS first_turn, coalesce(nth_value(turn, 2) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second_turn FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
one("win_running", "SELECT conv_id, turn, CAST(sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS chars FROM conversations")
one("win_moving", "SELECT conv_id, turn, round(avg(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS mean FROM conversations")
one("win_range_time", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events",
    "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY unix_micros(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events")
one("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20 OFFSET 5")
one("topk_per_meeting", "SELECT conv_id, turn, chars FROM (SELECT conv_id, turn, length(text) AS chars, row_number() OVER (PARTITION BY conv_id ORDER BY length(text) DESC, turn) AS r FROM conversations) t WHERE r <= 2")

# sets

for _name, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    one(f"set_{_name}", f"SELECT turn FROM conversations WHERE role = 'user' {_op} SELECT turn FROM conversations WHERE role = 'assistant'")

# functions

one("fn_string", r"SELECT doc_id, upper(lang) AS u, substring(text, 3, 5) AS s, reverse(source) AS r, length(trim(text)) AS n, levenshtein(source, 'src7') AS lev, md5(text) AS h, translate(source, 'src', 'xyz') AS t, lpad(source, 8, '.') AS p, strpos(text, 'e') AS at, concat_ws('|', lang, source) AS j, replace(source, 'src', 'from') AS f FROM documents",
    r"SELECT doc_id, upper(lang) AS u, substring(text, 3, 5) AS s, reverse(source) AS r, length(trim(text)) AS n, levenshtein(source, 'src7') AS lev, md5(CAST(text AS BINARY)) AS h, translate(source, 'src', 'xyz') AS t, lpad(source, 8, '.') AS p, instr(text, 'e') AS at, concat_ws('|', lang, source) AS j, replace(source, 'src', 'from') AS f FROM documents")
one("fn_date", "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, year(o_orderdate) AS y, dayofyear(o_orderdate) AS dy, CAST(CAST(o_orderdate + INTERVAL 3 DAY AS DATE) AS VARCHAR) AS later, epoch_us(o_orderdate) AS us FROM orders",
    "SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS month, datediff(CAST(o_orderdate AS DATE), DATE '1992-01-01') AS days, year(o_orderdate) AS y, dayofyear(o_orderdate) AS dy, CAST(CAST(o_orderdate + INTERVAL 3 DAY AS DATE) AS STRING) AS later, unix_micros(CAST(o_orderdate AS TIMESTAMP)) AS us FROM orders")
one("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, round(ln(l_extendedprice), 6) AS l, round(sqrt(l_quantity), 6) AS s, round(exp(-l_discount), 6) AS e, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS m, CAST(floor(l_extendedprice / 100) AS BIGINT) AS f, l_partkey % 7 AS p FROM lineitem")


@query("fn_map", r"SELECT conv_id, turn, word, count(*) AS n FROM (SELECT conv_id, turn, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS word FROM conversations) GROUP BY conv_id, turn, word HAVING count(*) > 1")
def fn_map(spark, d):
    """A bag of words per turn as a map, filtered and exploded."""
    words = T.words(F.col("text"))
    bag = F.map_from_entries(F.transform(F.array_distinct("w"), lambda x: F.struct(x, F.size(F.filter("w", lambda y: y == x)))))
    rows = table(spark, d, "conversations").select("conv_id", "turn", words.alias("w"))
    return rows.select("conv_id", "turn", F.explode(F.map_filter(bag, lambda k, v: v > 1)).alias("word", "n")).withColumn("n", F.col("n").cast("long"))


@query("fn_array", "SELECT vec_id, round(list_sum([CAST(x AS DOUBLE) * CAST(x AS DOUBLE) FOR x IN embedding]), 6) AS sq, len([x FOR x IN embedding IF x > 0]) AS pos, round(CAST(list_max(embedding) AS DOUBLE), 6) AS most, round(CAST(list_min(embedding) AS DOUBLE), 6) AS least, round(CAST(embedding[1] AS DOUBLE) + CAST(embedding[2] AS DOUBLE), 6) AS head FROM embeddings")
def fn_array(spark, d):
    x = F.col("embedding")
    sq = F.aggregate(F.transform(x, lambda v: v.cast("double") * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    head = F.aggregate(F.slice(x, 1, 2), F.lit(0.0), lambda s, v: s + v.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(sq, 6).alias("sq"), F.size(F.filter(x, lambda v: v > 0)).cast("long").alias("pos"), F.round(F.array_max(x).cast("double"), 6).alias("most"), F.round(F.array_min(x).cast("double"), 6).alias("least"), F.round(head, 6).alias("head"))


one("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events")


@query("fn_json_struct", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def fn_json_struct(spark, d):
    return table(spark, d, "events").select(F.from_json("props", "k bigint").alias("p")).groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


@query("fn_html", r"SELECT page_id, regexp_extract(html, '<title>(.*?)</title>', 1) AS title, len(regexp_extract_all(html, '<p[ >]')) AS ps, regexp_extract(html, 'lang=.([a-z]+)', 1) AS lang FROM pages")
def fn_html(spark, d):
    h = F.col("html")
    return table(spark, d, "pages").select("page_id", F.regexp_extract(h, "<title>(.*?)</title>", 1).alias("title"), F.regexp_count(h, F.lit("<p[ >]")).cast("long").alias("ps"), F.regexp_extract(h, "lang=.([a-z]+)", 1).alias("lang"))


# user functions

@query("udf_words", f"WITH {TALKS} SELECT meeting_id, utt_no, n_tok FROM u")
def udf_words(spark, d):
    R.register(spark)
    return table(spark, d, "conversations").select(F.col("conv_id").cast("string").alias("meeting_id"), F.col("turn").alias("utt_no"), F.expr("cast(size(words(text)) as bigint)").alias("n_tok"))


@query("udf_lcs")
def udf_lcs(spark, d):
    """(meeting_id, utt_no, lcs): longest common subsequence of each turn with the one before."""
    R.register(spark)
    rows = talks(spark, d).withColumn("before", F.lag("tokens").over(Window.partitionBy("meeting_id").orderBy("utt_no")))
    return rows.where("before is not null").select("meeting_id", "utt_no", F.expr("lcs_length(tokens, before)").alias("lcs"))


@query("udtf_slide", f"WITH RECURSIVE {TALKS}{lead_steps(128, 10 ** 9)} SELECT st.meeting_id, step AS win, left_utt AS first_utt, hi_utt AS last_utt, CAST(sum(n_tok) AS BIGINT) AS tokens FROM st JOIN u ON u.meeting_id = st.meeting_id AND u.utt_no BETWEEN left_utt AND hi_utt GROUP BY ALL")
def udtf_slide(spark, d):
    R.register(spark)
    talks(spark, d).select("meeting_id", "utt_no", "n_tok").createOrReplaceTempView("slide_input")
    return spark.sql("SELECT * FROM slide(TABLE(SELECT * FROM slide_input) PARTITION BY (meeting_id) ORDER BY (utt_no), 128)")


@query("subword_pieces")
def subword_pieces(spark, d):
    """(doc_id, n_words, n_pieces) under 200 merges fitted on the documents."""
    docs = table(spark, d, "documents")
    rows = subword.encode(docs.select("doc_id", "text"), subword.fit(docs, 200))
    return rows.select("doc_id", F.size(T.words(F.col("text"))).alias("n_words"), F.size("pieces").alias("n_pieces"))


@query("recursive_jump", "WITH RECURSIVE c AS (SELECT conv_id, max(turn) AS last FROM conversations GROUP BY conv_id), r AS (SELECT conv_id, CAST(0 AS BIGINT) AS turn, 0 AS step FROM c UNION ALL SELECT r.conv_id, r.turn + 2, r.step + 1 FROM r JOIN c ON c.conv_id = r.conv_id WHERE r.turn + 2 <= c.last) SELECT * FROM r")
def recursive_jump(spark, d):
    """A jump table followed by a recursive query; talks are short, so the level limit of the session is enough."""
    table(spark, d, "conversations").groupBy("conv_id").agg(F.max("turn").alias("last")).createOrReplaceTempView("jump_ends")
    return spark.sql("WITH RECURSIVE r AS (SELECT conv_id, CAST(0 AS BIGINT) AS turn, 0 AS step FROM jump_ends UNION ALL SELECT r.conv_id, r.turn + 2, r.step + 1 FROM r JOIN jump_ends c ON c.conv_id = r.conv_id WHERE r.turn + 2 <= c.last) SELECT * FROM r")


@query("cogroup_gold", f"WITH {GOLD} SELECT u.meeting_id, count(*) AS utterances, any_value(s) AS sentences FROM u JOIN (SELECT meeting_id, count(*) AS s FROM gold GROUP BY meeting_id) g ON g.meeting_id = u.meeting_id GROUP BY u.meeting_id")
def cogroup_gold(spark, d):
    import pyarrow as pa

    def both(a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"meeting_id": pa.array([a["meeting_id"][0].as_py()]), "utterances": pa.array([a.num_rows], pa.int64()), "sentences": pa.array([b.num_rows], pa.int64())})

    utts, gold = bundles_and_gold(spark, d)
    return utts.select("meeting_id", "utt_no").groupBy("meeting_id").cogroup(gold.select(F.col("meeting_id").alias("of_meeting"), "sent_no").groupBy("of_meeting")).applyInArrow(both, "meeting_id string, utterances long, sentences long")


one("star_revenue", "SELECT r_name, n_name, p_brand, count(*) AS lines, CAST(sum(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18, 4))) AS DOUBLE) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE o_orderdate >= TIMESTAMP '1995-01-01' GROUP BY r_name, n_name, p_brand")
one("subquery_scalar", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
one("subquery_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 100000)", "SELECT c.c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 100000)")


@query("persisted_meetings", f"WITH {TALKS} SELECT meeting_id, CAST(sum(n_tok) AS BIGINT) AS words, max(utt_no) AS last_utt FROM u GROUP BY meeting_id")
def persisted_meetings(spark, d):
    rows = cut(planner.persist(talks(spark, d).drop("text", "tokens"), partitions=8))
    return rows.groupBy("meeting_id").agg(F.sum("n_tok").alias("words"), F.max("utt_no").alias("last_utt"))


@query("fluent_digest")
def fluent_digest(spark, d):
    from ..operators.backbones import LeadBackbone
    from ..operators.rouge import reference_texts

    utts, gold = bundles_and_gold(spark, d)
    return planner.Digest(spark).meetings(utts).windows(k=1024).stride("last_support").backbone(LeadBackbone(20)).run().dedup().score(reference_texts(gold))


# streams

def _folder(spark) -> str:
    return f"{shared(spark)}/stream-{unique()}"


def _events(spark, d, files: int = 1):
    return live.read_events(spark, f"{d}/events.parquet", files)


TUMBLING = "SELECT epoch_us(date_trunc('day', ts)) AS win_start, event_type AS key, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL"


def _window_rows(df):
    return df.select(F.unix_micros("win_start").alias("win_start"), "key", "n", "total")


@query("stream_tumbling", TUMBLING)
def stream_tumbling(spark, d):
    return _window_rows(live.drained(live.windowed(_events(spark, d)), f"tumbling_{unique()}", _folder(spark), "complete"))


@query("stream_sliding", "SELECT epoch_us(date_trunc('day', ts)) - o * 86400000000 AS win_start, event_type AS key, count(*) AS n, round(sum(value), 2) AS total FROM events, range(2) t(o) GROUP BY ALL")
def stream_sliding(spark, d):
    return _window_rows(live.drained(live.windowed(_events(spark, d), "sliding"), f"sliding_{unique()}", _folder(spark), "complete"))


@query("stream_session", """WITH a AS (SELECT user_id, ts, value, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 1 DAY THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
b AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT epoch_us(min(ts)) AS win_start, CAST(user_id AS VARCHAR) AS key, count(*) AS n, round(sum(value), 2) AS total FROM b GROUP BY user_id, s""")
def stream_session(spark, d):
    return _window_rows(live.drained(live.windowed(_events(spark, d), "session"), f"session_{unique()}", _folder(spark), "complete"))


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_dedup(spark, d):
    """The events twice over, each kept once."""
    twice = _events(spark, d).union(_events(spark, d))
    return live.drained(live.dedup(twice, "40 days"), "dedup", _folder(spark)).groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_join_static", "SELECT c_mktsegment, event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL")
def stream_join_static(spark, d):
    rows = live.drained(live.join_static(_events(spark, d), table(spark, d, "customer")), "static", _folder(spark))
    return rows.groupBy("c_mktsegment", "event_type").agg(F.count("*").alias("n"))


@query("stream_join_stream", "SELECT a.event_id AS click_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_join_stream(spark, d):
    return live.drained(live.join_streams(_events(spark, d), _events(spark, d)), "pairs", _folder(spark))


@query("live_meetings", f"""WITH RECURSIVE nu AS (SELECT CAST(user_id AS VARCHAR) AS meeting_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS utt_no, CAST(1 + floor(value) % 20 AS BIGINT) AS n_tok, event_type || ' ' || event_id AS text FROM events),
u AS (SELECT *, CAST(sum(n_tok) OVER o AS BIGINT) AS tok_end, CAST(sum(n_tok) OVER o - n_tok AS BIGINT) AS tok_start FROM nu WINDOW o AS (PARTITION BY meeting_id ORDER BY utt_no ROWS UNBOUNDED PRECEDING)),
ln AS (SELECT meeting_id, max(utt_no) AS last_utt, max(tok_end) AS n FROM u GROUP BY meeting_id){__import__("talkdigest.workloads.base", fromlist=["lead_steps"]).lead_steps(64, 4)} SELECT meeting_id, step, left_utt, hi_utt, i_left, i_right, md5(snippet) AS snippet, boundary_utt, stride_tok FROM st""")
def live_meetings(spark, d):
    """The dynamic run on a stream. A last event far in the future moves event time on, so that every meeting is closed."""
    from ..operators.backbones import LeadBackbone
    from .base import hashed_text

    folder = _folder(spark)
    rows = live.from_events(table(spark, d, "events"))
    end = rows.agg(F.max("ts").alias("m")).select(F.lit("end").alias("meeting_id"), F.expr("m + interval 60 days").alias("ts"), F.lit(-1).cast("long").alias("seq"), F.lit(1).cast("long").alias("n_tok"), F.lit("end").alias("text"))
    rows.write.parquet(f"{folder}/in")
    end.coalesce(1).write.mode("append").parquet(f"{folder}/in")
    stream = spark.readStream.schema(rows.schema).parquet(f"{folder}/in")
    steps = live.drained(live.dynamic(stream, LeadBackbone(4), 64, "30 days"), "steps", folder)
    return hashed_text(steps.where("meeting_id <> 'end'"))


@query("meeting_size_classes", f"WITH {BUNDLES} SELECT CASE WHEN n <= 1024 THEN 'one window' ELSE 'several' END AS size_class, count(*) AS meetings, CAST(sum(n) AS BIGINT) AS words FROM ln GROUP BY 1")
def meeting_size_classes(spark, d):
    n = bundles(spark, d).groupBy("meeting_id").agg(F.max("tok_end").alias("n"))
    return n.groupBy(F.when(F.col("n") <= 1024, "one window").otherwise("several").alias("size_class")).agg(F.count("*").alias("meetings"), F.sum("n").alias("words"))

