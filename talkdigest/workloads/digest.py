"""Windows, runs, scores, boundary distance, cost and baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import analysis, baselines, boundary, convert, experiments, measures, rouge, runs, windows
from ..operators.backbones import CohesionBackbone, GoldBackbone, IndicatorBackbone, LeadBackbone, RandomBackbone, Seq2SeqBackbone
from ..sources import gold as planted
from .base import BUNDLES, GOLD, MERGED, TALKS, bundles, bundles_and_gold, hashed_text, lead_steps, query, rouge_sql, table, talks, window_parts

K, Q = 1024, 20
STEP_COLUMNS = "meeting_id, step, left_utt, hi_utt, i_left, i_right, md5(snippet) AS snippet, boundary_utt, stride_tok"


# windows

@query("fixed_windows", f"WITH {BUNDLES}{window_parts(K, Q)} SELECT meeting_id, CAST(win AS BIGINT) AS win, count(*) AS utterances, min(utt_no) AS first_utt, max(utt_no) AS last_utt, CAST(sum(greatest(win_to - win_from, 0)) AS BIGINT) AS tokens FROM pa GROUP BY meeting_id, win")
def fixed_windows(spark, d):
    rows = windows.fixed(bundles(spark, d), K)
    return rows.groupBy("meeting_id", F.col("window").alias("win")).agg(F.count("*").alias("utterances"), F.min("utt_no").alias("first_utt"), F.max("utt_no").alias("last_utt"), F.sum(F.greatest(F.lit(0), F.col("win_to") - F.col("win_from"))).alias("tokens"))


OVERLAP = r"""
wn AS (SELECT u.*, greatest(1, CAST(ceil((ln.n - {k}) / CAST({j} AS DOUBLE)) AS BIGINT) + 1) - 1 AS lw FROM u JOIN ln USING (meeting_id)),
we AS (SELECT *, unnest(range(least(lw, greatest(0, CAST(floor((tok_start - {k}) / CAST({j} AS DOUBLE)) AS BIGINT) + 1)), least(lw, greatest(tok_end - 1, tok_start) // {j}) + 1)) AS win FROM wn)"""


@query("fixed_windows_overlap", f"WITH {TALKS}, {OVERLAP.format(k=128, j=64)} SELECT meeting_id, CAST(win AS BIGINT) AS win, count(*) AS utterances, min(utt_no) AS first_utt, max(utt_no) AS last_utt FROM we GROUP BY meeting_id, win")
def fixed_windows_overlap(spark, d):
    rows = windows.fixed(talks(spark, d), 128, 64)
    return rows.groupBy("meeting_id", F.col("window").alias("win")).agg(F.count("*").alias("utterances"), F.min("utt_no").alias("first_utt"), F.max("utt_no").alias("last_utt"))


@query("overlap_votes", f"WITH {TALKS}, {OVERLAP.format(k=128, j=64)}, nt AS (SELECT *, row_number() OVER (PARTITION BY meeting_id, win ORDER BY utt_no) AS nth FROM we) SELECT meeting_id, utt_no, count(*) AS windows, count(*) FILTER (nth <= 1) AS votes FROM nt GROUP BY meeting_id, utt_no")
def overlap_votes(spark, d):
    return runs.overlap_votes(talks(spark, d), 128, 64, 1)


LINES = r"""
li AS (SELECT l_orderkey, CAST(l_quantity AS BIGINT) AS n_tok, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_shipdate, l_partkey, l_suppkey, l_extendedprice) - 1 AS utt_no, l_shipdate FROM lineitem),
lp AS (SELECT *, sum(n_tok) OVER (PARTITION BY l_orderkey ORDER BY utt_no ROWS UNBOUNDED PRECEDING) AS tok_end FROM li)"""


def order_lines(spark, d):
    """Orders as meetings, lines as utterances of l_quantity tokens."""
    from pyspark.sql import Window

    from ..operators.positions import attach

    rank = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_shipdate", "l_partkey", "l_suppkey", "l_extendedprice")) - 1
    rows = table(spark, d, "lineitem").select(F.col("l_orderkey").cast("string").alias("meeting_id"), rank.cast("long").alias("utt_no"), F.col("l_quantity").cast("long").alias("n_tok"), "l_shipdate")
    return attach(rows, {"tok": F.col("n_tok")})


@query("order_windows", f"WITH {LINES}, w AS (SELECT *, CAST((tok_end - n_tok) // 64 AS BIGINT) AS lo, CAST((greatest(tok_end, tok_end - n_tok + 1) - 1) // 64 AS BIGINT) AS hi FROM lp) SELECT CAST(l_orderkey AS VARCHAR) AS meeting_id, CAST(win AS BIGINT) AS win, count(*) AS lines FROM (SELECT l_orderkey, unnest(range(lo, hi + 1)) AS win FROM w) GROUP BY ALL")
def order_windows(spark, d):
    return windows.fixed(order_lines(spark, d), 64).groupBy("meeting_id", F.col("window").alias("win")).agg(F.count("*").alias("lines"))


@query("order_window_merge", r"""WITH x AS (SELECT l_orderkey, CAST(epoch(l_shipdate) // 86400 AS BIGINT) AS s, CAST(epoch(l_shipdate) // 86400 AS BIGINT) + CAST(l_quantity AS BIGINT) AS t,
 row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_shipdate, l_partkey, l_suppkey, l_extendedprice) - 1 AS i FROM lineitem),
y AS (SELECT *, max(t) OVER (PARTITION BY l_orderkey ORDER BY s, t, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM x),
z AS (SELECT *, sum(CASE WHEN reach IS NULL OR least(reach, t) - s + 1 < 1 THEN 1 ELSE 0 END) OVER (PARTITION BY l_orderkey ORDER BY s, t, i ROWS UNBOUNDED PRECEDING) - 1 AS g FROM y)
SELECT CAST(l_orderkey AS VARCHAR) AS meeting_id, CAST(g AS BIGINT) AS snip_no, min(s) AS seg_start, max(t) AS seg_end, count(*) AS lines FROM z GROUP BY l_orderkey, g""")
def order_window_merge(spark, d):
    day = F.floor(F.unix_timestamp(F.col("l_shipdate").cast("timestamp")) / 86400)
    rows = order_lines(spark, d).select("meeting_id", F.col("utt_no").alias("sent_no"), day.alias("seg_start"), (day + F.col("n_tok")).alias("seg_end"))
    return convert.merge(rows).select("meeting_id", "snip_no", "seg_start", "seg_end", F.size("sent_nos").cast("long").alias("lines"))


# runs

@query("run_dynamic_lead", f"WITH RECURSIVE {BUNDLES}{lead_steps(K, Q)} SELECT {STEP_COLUMNS} FROM st")
def run_dynamic_lead(spark, d):
    return hashed_text(runs.dynamic(bundles(spark, d), LeadBackbone(Q), K))


@query("run_dynamic_lead_at", f"WITH RECURSIVE {BUNDLES}{lead_steps(K, 60, 'at')} SELECT {STEP_COLUMNS} FROM st")
def run_dynamic_lead_at(spark, d):
    return hashed_text(runs.dynamic(bundles(spark, d), LeadBackbone(60), K, resume="at"))


@query("talks_dynamic_lead", f"WITH RECURSIVE {TALKS}{lead_steps(128, 1)} SELECT {STEP_COLUMNS} FROM st")
def talks_dynamic_lead(spark, d):
    return hashed_text(runs.dynamic(talks(spark, d), LeadBackbone(1), 128))


@query("run_frontier_lead", f"WITH RECURSIVE {TALKS}{lead_steps(128, 1)} SELECT {STEP_COLUMNS} FROM st")
def run_frontier_lead(spark, d):
    return hashed_text(runs.frontier(talks(spark, d), LeadBackbone(1), 128))


@query("run_jump_lead", f"WITH RECURSIVE {BUNDLES}{lead_steps(K, Q)} SELECT meeting_id, step, left_utt, hi_utt, boundary_utt FROM st")
def run_jump_lead(spark, d):
    return runs.jump(bundles(spark, d), K, Q)


@query("run_fixed_lead", f"WITH {BUNDLES}{window_parts(K, Q)} SELECT meeting_id, step, md5(snippet) AS snippet, i_left, i_right FROM fx")
def run_fixed_lead(spark, d):
    return hashed_text(runs.fixed_run(bundles(spark, d), LeadBackbone(Q), K))


TRUNCATED = rf""",
tr AS (SELECT *, CASE WHEN least(n_tok, {K} - tok_start) = n_tok THEN text ELSE array_to_string(tokens[1:{K} - tok_start], ' ') END AS part, row_number() OVER (PARTITION BY meeting_id ORDER BY utt_no) AS nth FROM u WHERE tok_start < {K}),
tx AS (SELECT meeting_id, CAST(0 AS BIGINT) AS step, string_agg(part, ' ' ORDER BY utt_no) FILTER (nth <= {Q}) AS snippet, CAST(0 AS BIGINT) AS i_left, CAST(sum(least(n_tok, {K} - tok_start)) AS BIGINT) AS i_right FROM tr GROUP BY meeting_id)"""
SEGMENTED = rf""",
gs AS (SELECT sg.meeting_id, snip_no, u.utt_no, u.text, u.tokens, u.n_tok, u.tok_start - min(u.tok_start) OVER (PARTITION BY sg.meeting_id, snip_no) AS ofs, min(u.tok_start) OVER (PARTITION BY sg.meeting_id, snip_no) AS fst FROM sg JOIN u ON u.meeting_id = sg.meeting_id AND u.utt_no BETWEEN seg_start AND seg_end),
gp AS (SELECT *, CASE WHEN least(n_tok, {K} - ofs) = n_tok THEN text ELSE array_to_string(tokens[1:{K} - ofs], ' ') END AS part, row_number() OVER (PARTITION BY meeting_id, snip_no ORDER BY utt_no) AS nth FROM gs WHERE ofs < {K}),
gx AS (SELECT meeting_id, snip_no AS step, string_agg(part, ' ' ORDER BY utt_no) FILTER (nth <= {Q}) AS snippet, min(fst) AS i_left, CAST(min(fst) + sum(least(n_tok, {K} - ofs)) AS BIGINT) AS i_right FROM gp GROUP BY meeting_id, snip_no)"""


@query("run_truncate_lead", f"WITH {BUNDLES}{TRUNCATED} SELECT meeting_id, step, md5(snippet) AS snippet, i_left, i_right FROM tx")
def run_truncate_lead(spark, d):
    return hashed_text(runs.truncate_run(bundles(spark, d), LeadBackbone(Q), K))


@query("run_gold_lead", f"WITH {MERGED}{SEGMENTED} SELECT meeting_id, step, md5(snippet) AS snippet, i_left, i_right FROM gx")
def run_gold_lead(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return hashed_text(runs.gold_run(utts, experiments.gold_segments(gold), LeadBackbone(Q), K))


@query("run_dynamic_cohesion")
def run_dynamic_cohesion(spark, d):
    return runs.dynamic(bundles(spark, d), CohesionBackbone(), K)


@query("run_dynamic_indicator")
def run_dynamic_indicator(spark, d):
    return runs.dynamic(bundles(spark, d), IndicatorBackbone(), K)


PICKED = f""", pk AS (SELECT st.*, u.text, u.utt_no, row_number() OVER (PARTITION BY st.meeting_id, step ORDER BY (u.utt_no * 7919) % 104729, u.utt_no) AS nth FROM st JOIN u ON u.meeting_id = st.meeting_id AND u.utt_no BETWEEN left_utt AND hi_utt)
SELECT meeting_id, step, left_utt, hi_utt, i_left, i_right, md5(string_agg(text, ' ' ORDER BY utt_no)) AS snippet, boundary_utt, stride_tok FROM pk WHERE nth <= {Q} GROUP BY ALL"""


@query("run_dynamic_random", f"WITH RECURSIVE {BUNDLES}{lead_steps(K, 10 ** 9)}{PICKED}")
def run_dynamic_random(spark, d):
    return hashed_text(runs.dynamic(bundles(spark, d), RandomBackbone(Q), K))


@query("talks_dynamic_seq2seq")
def talks_dynamic_seq2seq(spark, d):
    """The dynamic run with the (untrained, seeded) encoder-decoder as its generator."""
    from ..operators import nn

    return runs.dynamic(talks(spark, d), Seq2SeqBackbone(nn.Seq2Seq(1000)), 128)


@query("talks_consistency_seq2seq")
def talks_consistency_seq2seq(spark, d):
    """(run, meetings, grams, supported) of the truncated and the dynamic run of the encoder-decoder: bigrams of what it wrote that the source has."""
    from ..operators import nn

    utts, backbone, out = talks(spark, d), Seq2SeqBackbone(nn.Seq2Seq(1000)), None
    for run, steps in (("truncate", runs.truncate_run(utts, backbone, 128)), ("dynamic", runs.dynamic(utts, backbone, 128))):
        row = measures.consistency(runs.assemble(steps), utts).agg(F.count("*").alias("meetings"), F.sum("grams").alias("grams"), F.sum("supported").alias("supported")).withColumn("run", F.lit(run))
        out = row if out is None else out.unionByName(row)
    return out


def _talk_ids(spark, d):
    ids = F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("utt_no", "tokens"))), lambda x: x["tokens"]))
    return talks(spark, d).groupBy("meeting_id").agg(F.transform(ids, lambda w: F.pmod(F.xxhash64(w), F.lit(1000)).cast("int")).alias("ids"))


@query("decoder_outputs")
def decoder_outputs(spark, d):
    """(meeting_id, outputs): up to eight ids that six encoder and six decoder layers write of each window of a talk, greedily."""
    from ..operators import nn

    return nn.decode_column(_talk_ids(spark, d), nn.Seq2Seq(1000), most=8).select("meeting_id", "outputs")


@query("banded_encoding")
def banded_encoding(spark, d):
    """(meeting_id, encoding): as encoder_layers, with attention to places at most 16 apart."""
    from ..operators import nn

    return nn.encode_column(_talk_ids(spark, d), nn.Seq2Seq(1000), band=16).select("meeting_id", F.col("encoded").alias("encoding"))


@query("run_dynamic_learned")
def run_dynamic_learned(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    backbone, _ = experiments.learned(utts, gold)
    return runs.dynamic(utts, backbone, K)


@query("training_history")
def training_history(spark, d):
    """(epoch, loss, val_r2, chosen) of the boundary head over 20 epochs; the chosen one has the best ROUGE-2 on validation."""
    utts, gold = bundles_and_gold(spark, d)
    backbone, history = experiments.learned(utts, gold)
    return spark.createDataFrame([(e, float(loss), s, w == backbone.coefs) for e, w, loss, s in history], "epoch int, loss double, val_r2 double, chosen boolean")


@query("run_dynamic_stride")
def run_dynamic_stride(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return runs.dynamic(utts, experiments.direct(utts, gold, LeadBackbone(Q), K), K)


@query("run_dynamic_policy")
def run_dynamic_policy(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    backbone, _ = experiments.policy(utts, gold, LeadBackbone(8), K, episodes=3)
    return runs.dynamic(utts, backbone, K)


@query("run_dynamic_gold", f"WITH {MERGED} SELECT meeting_id, snip_no AS step, seg_end AS boundary_utt FROM sg")
def run_dynamic_gold(spark, d):
    """With the gold backbone, one step a gold segment; the boundary of the last window may lie before the transcript's end."""
    from ..sources.layout import nest
    from .goldsteps import gold_steps

    utts, gold = bundles_and_gold(spark, d)
    return gold_steps(nest(utts), experiments.gold_segments(gold), K)


# scores

OUTPUTS = {
    "dynamic": ("WITH RECURSIVE " + GOLD + lead_steps(K, Q), "st"),
    "fixed": ("WITH " + GOLD + window_parts(K, Q), "fx"),
    "truncate": ("WITH " + GOLD + TRUNCATED, "tx"),
    "gold": ("WITH " + MERGED + SEGMENTED, "gx"),
}
REFERENCE = ", rf AS (SELECT meeting_id, string_agg(array_to_string(tokens, ' '), chr(10) ORDER BY sent_no) AS text FROM gold GROUP BY meeting_id)"


def assembled_sql(run: str) -> str:
    head, steps = OUTPUTS[run]
    return f"{head}, oa AS (SELECT meeting_id, string_agg(snippet, chr(10) ORDER BY step) AS text FROM {steps} GROUP BY meeting_id){REFERENCE}"


def steps_of(utts, gold, run, backbone=None):
    backbone = backbone or LeadBackbone(Q)
    if run == "dynamic":
        return runs.dynamic(utts, backbone, K)
    if run == "fixed":
        return runs.fixed_run(utts, backbone, K)
    if run == "truncate":
        return runs.truncate_run(utts, backbone, K)
    return runs.gold_run(utts, experiments.gold_segments(gold), backbone, K)


for _run in OUTPUTS:
    for _n in (1, 2):
        def _rouge(spark, d, run=_run, n=_n):
            utts, gold = bundles_and_gold(spark, d)
            return rouge.means(rouge.ngram(rouge.pairs(runs.assemble(steps_of(utts, gold, run)), rouge.reference_texts(gold)), n), f"r{n}")

        query(f"rouge_{_n}_{_run}", f"{assembled_sql(_run)}{rouge_sql('oa', 'rf', _n)} SELECT 'r{_n}' AS measure, * FROM rm")(_rouge)

    def _rouge_l(spark, d, run=_run):
        utts, gold = bundles_and_gold(spark, d)
        return rouge.means(rouge.longest(rouge.pairs(runs.assemble(steps_of(utts, gold, run)), rouge.reference_texts(gold))), "rl")

    query(f"rouge_l_{_run}")(_rouge_l)


@query("rouge_l_summary_truncate")
def rouge_l_summary_truncate(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    reference = rouge.reference_texts(gold)
    return rouge.means(rouge.longest(rouge.sentence_pairs(runs.assemble(steps_of(utts, gold, "truncate")), reference), "summary"), "rl_summary")


@query("scoreboard")
def scoreboard(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return experiments.scoreboard(utts, gold, experiments.outputs_of(utts, gold, CohesionBackbone(), K))


@query("scoreboard_baselines")
def scoreboard_baselines(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return experiments.compared(utts, gold, CohesionBackbone(), k=K)


@query("summary_runner_trained")
def summary_runner_trained(spark, d):
    """(meeting_id, utt_no, place, score) of all meetings, with weights from greedy labels of the training meetings."""
    from ..operators import neural

    utts, gold = bundles_and_gold(spark, d)
    return baselines.summary_runner(utts, weights=neural.fitted(utts, gold)["runner"])


@query("network_picks")
def network_picks(spark, d):
    """(run, meeting_id, utt_no, place, score) of all meetings, for each network."""
    from ..operators import neural

    utts, gold = bundles_and_gold(spark, d)
    return neural.picked(utts, neural.fitted(utts, gold))


@query("boundary_distance", rf"""WITH {MERGED},
hi AS (SELECT sg.meeting_id, snip_no, seg_start, seg_end, greatest(seg_start, coalesce(max(b.utt_no), 0)) AS hi FROM sg JOIN u a ON a.meeting_id = sg.meeting_id AND a.utt_no = seg_start LEFT JOIN u b ON b.meeting_id = sg.meeting_id AND b.tok_end <= a.tok_start + {K} GROUP BY sg.meeting_id, snip_no, seg_start, seg_end),
pd AS (SELECT *, least(seg_start + {Q} - 1, hi) AS pred FROM hi),
ds AS (SELECT abs(pred - seg_end) AS x, abs(p.char_end - g.char_end) AS y FROM pd JOIN u p ON p.meeting_id = pd.meeting_id AND p.utt_no = pred JOIN u g ON g.meeting_id = pd.meeting_id AND g.utt_no = seg_end)
SELECT count(*) AS n, round(avg(x), 6) AS utterances, round(avg(y), 6) AS characters, round(avg(CASE WHEN x <= 3 THEN 1.0 ELSE 0.0 END), 6) AS hit_rate FROM ds""")
def boundary_distance(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return boundary.summary(experiments.boundary_distances(utts, gold, lambda: LeadBackbone(Q), K))


@query("boundary_distance_by_backbone")
def boundary_distance_by_backbone(spark, d):
    """(backbone, n, utterances, characters, hit_rate): gold is 0 off, then lead, cohesion and learned."""
    utts, gold = bundles_and_gold(spark, d)
    trained, _ = experiments.learned(utts, gold)
    rows = experiments.boundary_distances_by(utts, gold, {"lead": LeadBackbone(Q), "cohesion": CohesionBackbone(), "learned": trained}, K)
    return boundary.summary(rows, by=("backbone",)).select("n", "utterances", "characters", "hit_rate", "backbone")


@query("boundary_distance_free", rf"""WITH RECURSIVE {MERGED}{lead_steps(K, Q)},
nr AS (SELECT st.meeting_id, step, boundary_utt, seg_end, row_number() OVER (PARTITION BY st.meeting_id, step ORDER BY abs(boundary_utt - seg_end), seg_end) AS r FROM st JOIN sg ON sg.meeting_id = st.meeting_id),
ds AS (SELECT abs(boundary_utt - seg_end) AS x, abs(p.char_end - g.char_end) AS y FROM nr JOIN u p ON p.meeting_id = nr.meeting_id AND p.utt_no = boundary_utt JOIN u g ON g.meeting_id = nr.meeting_id AND g.utt_no = seg_end WHERE r = 1)
SELECT count(*) AS n, round(avg(x), 6) AS utterances, round(avg(y), 6) AS characters, round(avg(CASE WHEN x <= 3 THEN 1.0 ELSE 0.0 END), 6) AS hit_rate FROM ds""")
def boundary_distance_free(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    steps = runs.dynamic(utts, LeadBackbone(Q), K)
    ends = experiments.gold_segments(gold).select("meeting_id", "snip_no", F.col("seg_end").alias("gold_utt"))
    return boundary.summary(boundary.distance(steps.select("meeting_id", F.col("step").alias("snip_no"), F.col("boundary_utt").alias("pred_utt")), ends, utts, "free"))


@query("boundary_locate", rf"""WITH {BUNDLES}, t AS (SELECT meeting_id, utt_no AS at, greatest(0, utt_no - 30) AS left_utt, utt_no + 10 AS hi_utt, text FROM u),
nm AS (SELECT meeting_id, utt_no, trim(regexp_replace(lower(text), '\s+', ' ', 'g')) AS norm FROM u)
SELECT t.meeting_id, left_utt, hi_utt, md5(t.text) AS text, min(nm.utt_no) FILTER (nm.utt_no BETWEEN left_utt AND hi_utt) AS found FROM t LEFT JOIN nm ON nm.meeting_id = t.meeting_id AND nm.norm = trim(regexp_replace(lower(t.text), '\s+', ' ', 'g')) GROUP BY ALL""")
def boundary_locate(spark, d):
    utts = bundles(spark, d)
    asked = utts.select("meeting_id", F.greatest(F.lit(0).cast("long"), F.col("utt_no") - 30).alias("left_utt"), (F.col("utt_no") + 10).alias("hi_utt"), "text")
    return hashed_text(boundary.locate_exact(asked, utts), "text")


SUPPORTED = r""",
oo AS (SELECT DISTINCT meeting_id, t[i] || ' ' || t[i + 1] AS g FROM (SELECT meeting_id, t, unnest(range(1, len(t))) AS i FROM (SELECT meeting_id, regexp_extract_all(lower(x), '[\p{L}\p{N}]+') AS t FROM (SELECT meeting_id, unnest(string_split_regex(text, '[.!?\n]+')) AS x FROM oa)))),
ss AS (SELECT DISTINCT meeting_id, tokens[i] || ' ' || tokens[i + 1] AS g FROM (SELECT meeting_id, tokens, unnest(range(1, len(tokens))) AS i FROM u))
SELECT oo.meeting_id, count(*) AS grams, count(ss.g) AS supported FROM oo LEFT JOIN ss ON ss.meeting_id = oo.meeting_id AND ss.g = oo.g GROUP BY oo.meeting_id"""
for _run in ("truncate", "dynamic"):
    def _consistency(spark, d, run=_run):
        utts, gold = bundles_and_gold(spark, d)
        return measures.consistency(runs.assemble(steps_of(utts, gold, run)), utts)

    query(f"consistency_rate_{_run}", assembled_sql(_run) + SUPPORTED)(_consistency)


@query("consistency_window", "WITH RECURSIVE " + BUNDLES + lead_steps(K, Q) + r""",
oo AS (SELECT DISTINCT meeting_id, step, t[i] || ' ' || t[i + 1] AS g FROM (SELECT meeting_id, step, t, unnest(range(1, len(t))) AS i FROM (SELECT meeting_id, step, regexp_extract_all(lower(x), '[\p{L}\p{N}]+') AS t FROM (SELECT meeting_id, step, unnest(string_split_regex(snippet, '[.!?\n]+')) AS x FROM st)))),
ss AS (SELECT DISTINCT meeting_id, step, tokens[i] || ' ' || tokens[i + 1] AS g FROM (SELECT st.meeting_id, step, tokens, unnest(range(1, len(tokens))) AS i FROM st JOIN u ON u.meeting_id = st.meeting_id AND u.utt_no BETWEEN left_utt AND hi_utt))
SELECT oo.meeting_id, oo.step, count(*) AS grams, count(ss.g) AS supported FROM oo LEFT JOIN ss ON ss.meeting_id = oo.meeting_id AND ss.step = oo.step AND ss.g = oo.g GROUP BY oo.meeting_id, oo.step""")
def consistency_window(spark, d):
    return measures.own_window_consistency(runs.dynamic_with_source(bundles(spark, d), LeadBackbone(Q), K))


@query("mention_support", rf"""WITH {GOLD}{REFERENCE},
m AS (SELECT DISTINCT meeting_id, unnest(regexp_extract_all(lower(text), '[0-9]+')) AS m FROM rf), s AS (SELECT DISTINCT meeting_id, unnest(regexp_extract_all(lower(text), '[0-9]+')) AS m FROM u)
SELECT m.meeting_id, count(*) AS mentions, count(s.m) AS supported FROM m LEFT JOIN s ON s.meeting_id = m.meeting_id AND s.m = m.m GROUP BY m.meeting_id""")
def mention_support(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return measures.mention_support(rouge.reference_texts(gold), utts, "[0-9]+")


@query("redundancy", r"""WITH e AS (SELECT doc_id, trim(unnest(string_split_regex(text, '[.!?\n]+'))) AS x FROM documents), n AS (SELECT doc_id, trim(regexp_replace(lower(x), '\s+', ' ', 'g')) AS y, count(*) AS c FROM e WHERE x <> '' GROUP BY ALL)
SELECT CAST(sum(c) AS BIGINT) AS sentences, CAST(sum(c - 1) AS BIGINT) AS repeated, round(sum(c - 1) / sum(c), 6) AS share FROM n""")
def redundancy(spark, d):
    return runs.redundancy(table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("meeting_id"), "text"))


COST = "SELECT CAST(sum(steps) AS BIGINT) AS steps, CAST(sum(tokens) AS BIGINT) AS tokens, CAST(sum(greatest(0, tokens - reach)) AS BIGINT) AS again, CAST(sum(attention) AS BIGINT) AS attention, '{run}' AS run FROM (SELECT count(*) AS steps, sum(i_right - i_left) AS tokens, max(i_right) - min(i_left) AS reach, sum((i_right - i_left) * (i_right - i_left)) AS attention FROM {steps} GROUP BY meeting_id)"


@query("window_cost", " UNION ALL ".join(["WITH RECURSIVE " + MERGED + lead_steps(K, Q) + window_parts(K, Q) + TRUNCATED + SEGMENTED + " " + COST.format(run="dynamic", steps="st"), *[COST.format(run=r, steps=s) for r, s in (("fixed", "fx"), ("truncate", "tx"), ("gold", "gx"))]]))
def window_cost(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    out = None
    for run in OUTPUTS:
        row = measures.cost(steps_of(utts, gold, run)).withColumn("run", F.lit(run))
        out = row if out is None else out.unionByName(row)
    return out


SWEEP = (64, 128, 256, 512, 1024)


def _sweep_sql() -> str:
    parts = []
    for k in SWEEP:
        parts.append(f"SELECT * FROM (WITH RECURSIVE {TALKS}{lead_steps(k, 2)} SELECT CAST({k} AS BIGINT) AS k, count(*) AS steps, CAST(sum(i_right - i_left) AS BIGINT) AS tokens FROM st)")
    return " UNION ALL ".join(parts)


@query("k_sweep", _sweep_sql())
def k_sweep(spark, d):
    utts, out = talks(spark, d), None
    for k in SWEEP:
        row = measures.cost(runs.dynamic(utts, LeadBackbone(2), k)).select(F.lit(k).cast("long").alias("k"), "steps", "tokens")
        out = row if out is None else out.unionByName(row)
    return out


RECALL_SWEEP = (64, 128, 256, 512, 1024)


def _recall_sql() -> str:
    """Steps, cost and support recall of the lead run for each window size."""
    one = lambda k: f"""SELECT * FROM (WITH RECURSIVE {GOLD}{lead_steps(k, 8)},
 kc AS (SELECT count(*) AS steps, sum(i_right - i_left) AS tokens, max(i_right) - min(i_left) AS reach, sum((i_right - i_left) * (i_right - i_left)) AS attention FROM st GROUP BY meeting_id),
 kw AS (SELECT meeting_id, s AS utt_no FROM gold WHERE annotated UNION SELECT meeting_id, t FROM gold WHERE annotated),
 kr AS (SELECT count(*) AS n, count(*) FILTER (EXISTS (SELECT 1 FROM st WHERE st.meeting_id = kw.meeting_id AND kw.utt_no BETWEEN st.left_utt AND st.boundary_utt)) AS seen FROM kw)
 SELECT CAST({k} AS BIGINT) AS k, CAST(sum(steps) AS BIGINT) AS steps, CAST(sum(tokens) AS BIGINT) AS tokens, CAST(sum(greatest(0, tokens - reach)) AS BIGINT) AS again, CAST(sum(attention) AS BIGINT) AS attention,
  (SELECT round(seen / n, 6) FROM kr) AS recall FROM kc)"""  # noqa: E731
    return " UNION ALL ".join(one(k) for k in RECALL_SWEEP)


@query("k_sweep_recall", _recall_sql())
def k_sweep_recall(spark, d):
    utts, gold = bundles_and_gold(spark, d)
    return experiments.sweep_k(utts, gold, 8, RECALL_SWEEP)


@query("segmentation_quality")
def segmentation_quality(spark, d):
    """(meeting_id, pk, window_diff) of cohesion cuts against gold segment ends."""
    utts, gold = bundles_and_gold(spark, d)
    cuts = experiments.gold_segments(gold).select("meeting_id", F.col("seg_end").alias("utt_no"))
    return measures.segmentation(cuts, baselines.topic_cuts(utts), utts)


# baselines

@query("lead_q", f"WITH {BUNDLES} SELECT meeting_id, utt_no, CAST(row_number() OVER (PARTITION BY meeting_id ORDER BY utt_no) - 1 AS INTEGER) AS place FROM u WHERE utt_no < 10")
def lead_q(spark, d):
    return baselines.lead(bundles(spark, d))


@query("random_q", f"WITH {BUNDLES}, r AS (SELECT meeting_id, utt_no, row_number() OVER (PARTITION BY meeting_id ORDER BY (utt_no * 7919) % 104729, utt_no) AS nth FROM u) SELECT meeting_id, utt_no, CAST(row_number() OVER (PARTITION BY meeting_id ORDER BY utt_no) - 1 AS INTEGER) AS place FROM r WHERE nth <= 10")
def random_q(spark, d):
    return baselines.hashed(bundles(spark, d))


@query("textrank_top")
def textrank_top(spark, d):
    return baselines.textrank(bundles(spark, d))


def _textrank_sql(rounds: int) -> str:
    out = rf"""WITH {TALKS},
nd AS (SELECT meeting_id, utt_no, list_distinct(tokens) AS w, len(list_distinct(tokens)) AS size FROM u WHERE len(list_distinct(tokens)) >= 2),
cn AS (SELECT meeting_id, count(*) AS n FROM nd GROUP BY meeting_id), fl AS (SELECT meeting_id, utt_no, size, unnest(w) AS word FROM nd),
dw AS (SELECT fl.meeting_id, word FROM fl JOIN cn USING (meeting_id) GROUP BY fl.meeting_id, word HAVING count(*) >= 2),
fk AS (SELECT fl.* FROM fl JOIN dw ON dw.meeting_id = fl.meeting_id AND dw.word = fl.word),
eg AS (SELECT a.meeting_id, a.utt_no AS i, b.utt_no AS j, count(*) / (ln(any_value(a.size)) + ln(any_value(b.size))) AS w FROM fk a JOIN fk b ON a.meeting_id = b.meeting_id AND a.word = b.word AND a.utt_no < b.utt_no GROUP BY a.meeting_id, a.utt_no, b.utt_no),
bo AS (SELECT meeting_id, i AS a, j AS b, w FROM eg UNION ALL SELECT meeting_id, j, i, w FROM eg), sh AS (SELECT meeting_id, a, b, w / sum(w) OVER (PARTITION BY meeting_id, a) AS s FROM bo),
r0 AS (SELECT nd.meeting_id, utt_no AS a, n, 1.0 / n AS rank FROM nd JOIN cn USING (meeting_id))"""
    for r in range(rounds):
        out += f",\nr{r + 1} AS MATERIALIZED (SELECT r.meeting_id, r.a, r.n, 0.15 / r.n + 0.85 * coalesce(g.got, 0) AS rank FROM r{r} r LEFT JOIN (SELECT sh.meeting_id, sh.b, sum(sh.s * p.rank) AS got FROM sh JOIN r{r} p ON p.meeting_id = sh.meeting_id AND p.a = sh.a GROUP BY sh.meeting_id, sh.b) g ON g.meeting_id = r.meeting_id AND g.b = r.a)"
    return out + f" SELECT meeting_id, a AS utt_no, round(rank, 6) AS rank FROM r{rounds}"


@query("textrank_frames", _textrank_sql(10))
def textrank_frames(spark, d):
    rows = baselines.textrank_frames(talks(spark, d), 10)
    return rows.withColumn("rank", F.round("rank", 6))


@query("summary_runner_top")
def summary_runner_top(spark, d):
    return baselines.summary_runner(bundles(spark, d))


@query("attention_weights", rf"""WITH {TALKS}, s AS (SELECT meeting_id, utt_no, ln(1 + n_tok) AS s FROM u), e AS (SELECT *, exp(s - max(s) OVER (PARTITION BY meeting_id)) AS e FROM s) SELECT meeting_id, utt_no, round(e / sum(e) OVER (PARTITION BY meeting_id), 6) AS weight FROM e""")
def attention_weights(spark, d):
    return baselines.attention_weights(talks(spark, d)).withColumn("weight", F.round("weight", 6))


@query("pointer_mix", rf"""WITH {TALKS}, s AS (SELECT meeting_id, utt_no, n_tok, tokens, ln(1 + n_tok) AS s FROM u WHERE n_tok > 0), e AS (SELECT *, exp(s - max(s) OVER (PARTITION BY meeting_id)) AS e FROM s),
w AS (SELECT *, e / sum(e) OVER (PARTITION BY meeting_id) AS a FROM e), c AS (SELECT meeting_id, word, sum(a / n_tok) AS c, count(*) AS n FROM (SELECT meeting_id, a, n_tok, unnest(tokens) AS word FROM w) GROUP BY ALL)
SELECT meeting_id, word, round(0.5 * n / sum(n) OVER (PARTITION BY meeting_id) + 0.5 * c, 6) AS p FROM c""")
def pointer_mix(spark, d):
    return baselines.pointer_mixture(talks(spark, d)).withColumn("p", F.round("p", 6))


@query("gate_weights", rf"""WITH {TALKS}, s AS (SELECT *, 1 / (1 + exp(-(n_tok - avg(n_tok) OVER (PARTITION BY meeting_id)) / 10)) AS gate FROM u WHERE n_tok > 0), c AS (SELECT meeting_id, word, sum(gate) AS g FROM (SELECT meeting_id, gate, unnest(tokens) AS word FROM s) GROUP BY ALL)
SELECT meeting_id, word, round(g / sum(g) OVER (PARTITION BY meeting_id), 6) AS weight FROM c""")
def gate_weights(spark, d):
    return baselines.gated_weights(talks(spark, d)).withColumn("weight", F.round("weight", 6))


@query("topic_gaps", rf"""WITH {TALKS}, t AS (SELECT u.meeting_id, utt_no, last_utt, unnest(tokens) AS word FROM u JOIN ln USING (meeting_id)),
l AS (SELECT meeting_id, word, unnest(range(utt_no, least(utt_no + 1, last_utt) + 1)) AS gap, 1 AS a, 0 AS b FROM t), r AS (SELECT meeting_id, word, unnest(range(greatest(utt_no - 2, 0), utt_no)) AS gap, 0 AS a, 1 AS b FROM t WHERE utt_no > 0),
c AS (SELECT meeting_id, gap, word, sum(a) AS a, sum(b) AS b FROM (SELECT * FROM l UNION ALL SELECT * FROM r) GROUP BY ALL), s AS (SELECT meeting_id, gap, sum(a * b) AS d, sum(a * a) AS x, sum(b * b) AS y FROM c GROUP BY ALL)
SELECT s.meeting_id, gap AS utt_no, round(CASE WHEN x * y > 0 THEN d / sqrt(x * y) ELSE 0 END, 6) AS score FROM s JOIN ln USING (meeting_id) WHERE gap < last_utt""")
def topic_gaps(spark, d):
    return baselines.topic_gaps(talks(spark, d), 2).withColumn("score", F.round("score", 6))


@query("topicseg_cuts")
def topicseg_cuts(spark, d):
    return baselines.topic_cuts(bundles(spark, d))


@query("topicseg_run")
def topicseg_run(spark, d):
    utts = bundles(spark, d)
    return runs.gold_run(utts, baselines.topic_segments(utts, baselines.topic_cuts(utts)), LeadBackbone(3), K)


@query("hier_pool", rf"""WITH {BUNDLES}, t AS (SELECT meeting_id, speaker, CASE WHEN n_tok > 0 THEN list_sum([length(x) FOR x IN tokens]) / CAST(n_tok AS DOUBLE) ELSE 0 END AS turn, CASE WHEN n_tok > 0 THEN len(list_distinct(tokens)) / CAST(n_tok AS DOUBLE) ELSE 0 END AS types FROM u)
SELECT meeting_id, round(avg(turn), 6) AS length, round(avg(types), 6) AS type_share, round(avg(CASE WHEN speaker = 'PM' THEN 1.0 ELSE 0.0 END), 6) AS pm, round(avg(CASE WHEN speaker = 'ME' THEN 1.0 ELSE 0.0 END), 6) AS me, round(avg(CASE WHEN speaker = 'ID' THEN 1.0 ELSE 0.0 END), 6) AS id, round(avg(CASE WHEN speaker = 'UI' THEN 1.0 ELSE 0.0 END), 6) AS ui FROM t GROUP BY meeting_id""")
def hier_pool(spark, d):
    return baselines.hierarchical_pool(bundles(spark, d))


EDGES = r""",
ed AS (SELECT meeting_id, utt_no AS a, lead(utt_no) OVER (PARTITION BY meeting_id ORDER BY utt_no) AS nx, lead(utt_no) OVER (PARTITION BY meeting_id, speaker ORDER BY utt_no) AS sm, lead(speaker) OVER (PARTITION BY meeting_id ORDER BY utt_no) AS ns, speaker FROM u),
eg AS (SELECT meeting_id, a, nx AS b, 'next' AS relation FROM ed WHERE nx IS NOT NULL UNION ALL SELECT meeting_id, a, sm, 'same' FROM ed WHERE sm IS NOT NULL UNION ALL SELECT meeting_id, a, nx, 'reply' FROM ed WHERE nx IS NOT NULL AND ns <> speaker)"""


@query("discourse_edges", f"WITH {TALKS}{EDGES} SELECT * FROM eg")
def discourse_edges(spark, d):
    return baselines.discourse_edges(talks(spark, d))


@query("graph_conv", rf"""WITH {TALKS}{EDGES}, bo AS (SELECT meeting_id, a, b, relation FROM eg UNION ALL SELECT meeting_id, b, a, relation FROM eg),
mn AS (SELECT bo.meeting_id, a, relation, avg(n_tok) AS x FROM bo JOIN u ON u.meeting_id = bo.meeting_id AND u.utt_no = bo.b GROUP BY ALL UNION ALL SELECT meeting_id, utt_no, 'self', n_tok FROM u)
SELECT meeting_id, a AS utt_no, round(greatest(sum(x * CASE relation WHEN 'self' THEN 1.0 WHEN 'next' THEN 0.5 WHEN 'same' THEN 0.25 ELSE 0.125 END), 0), 6) AS value FROM mn GROUP BY meeting_id, a""")
def graph_conv(spark, d):
    utts = talks(spark, d)
    return baselines.graph_convolution(utts, baselines.discourse_edges(utts)).withColumn("value", F.round("value", 6))


# network parts on embeddings

SLICE = "v AS (SELECT vec_id, vec_id // 32 AS win, [CAST(x AS DOUBLE) FOR x IN embedding] AS e FROM embeddings)"


@query("attention_softmax", f"WITH {SLICE}, s AS (SELECT a.vec_id, b.vec_id AS other_id, list_dot_product(a.e, b.e) / sqrt(len(a.e)) AS s FROM v a JOIN v b ON a.win = b.win), e AS (SELECT *, exp(s - max(s) OVER (PARTITION BY vec_id)) AS e FROM s) SELECT vec_id, other_id, round(e / sum(e) OVER (PARTITION BY vec_id), 6) AS weight FROM e")
def attention_softmax(spark, d):
    from ..operators import nn

    return nn.attention_rows(table(spark, d, "embeddings")).withColumn("weight", F.round("weight", 6))


@query("attention_output", f"WITH {SLICE}, s AS (SELECT a.vec_id, b.vec_id AS o, list_dot_product(a.e, b.e) / sqrt(len(a.e)) AS s, b.e AS be FROM v a JOIN v b ON a.win = b.win), e AS (SELECT *, exp(s - max(s) OVER (PARTITION BY vec_id)) AS x FROM s), w AS (SELECT *, x / sum(x) OVER (PARTITION BY vec_id) AS w FROM e), p AS (SELECT vec_id, w, unnest(be) AS y, unnest(range(len(be))) AS place FROM w) SELECT vec_id, CAST(place AS INTEGER) AS place, round(sum(w * y), 6) AS value FROM p GROUP BY vec_id, place")
def attention_output(spark, d):
    from ..operators import nn

    return nn.attention_output(table(spark, d, "embeddings")).withColumn("value", F.round("value", 6))


@query("layer_norm", "WITH e AS (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS x, unnest(range(len(embedding))) AS place FROM embeddings) SELECT vec_id, CAST(place AS INTEGER) AS place, round((x - avg(x) OVER w) / sqrt(var_pop(x) OVER w + 0.00001), 6) AS value FROM e WINDOW w AS (PARTITION BY vec_id)")
def layer_norm(spark, d):
    from ..operators import nn

    return table(spark, d, "embeddings").select("vec_id", F.posexplode(nn.norm_column(F.col("embedding"))).alias("place", "value")).withColumn("value", F.round("value", 6))


@query("ffn_step", "WITH e AS (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS x, unnest(range(len(embedding))) AS i FROM embeddings), h AS (SELECT vec_id, j, greatest(0, sum(x * ((i * 7 + j * 3) % 5 - 2) / 4.0)) AS h FROM e, range(8) t(j) GROUP BY vec_id, j) SELECT vec_id, round(sum(h * (j % 3 - 1)), 6) AS value FROM h GROUP BY vec_id")
def ffn_step(spark, d):
    """Two layers with a rectifier and small fixed weights, as array functions."""
    rows = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    weighted = lambda j: F.transform("e", lambda x, i: x * ((i * 7 + j * 3) % 5 - 2) / 4.0)
    hidden = F.array(*[F.greatest(F.lit(0.0), F.aggregate(weighted(j), F.lit(0.0), lambda s, y: s + y)) for j in range(8)])
    out = F.aggregate(F.zip_with(F.col("h"), F.array(*[F.lit(float(j % 3 - 1)) for j in range(8)]), lambda a, b: a * b), F.lit(0.0), lambda s, y: s + y)
    return rows.withColumn("h", hidden).select("vec_id", F.round(out, 6).alias("value"))


@query("encoder_layers")
def encoder_layers(spark, d):
    """(meeting_id, encoding): encoding of all word ids of each talk under six seeded layers, in windows of up to 1,024."""
    from ..operators import nn

    return nn.encode_column(_talk_ids(spark, d), nn.Seq2Seq(1000)).select("meeting_id", F.col("encoded").alias("encoding"))
