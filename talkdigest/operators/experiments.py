"""Comparisons of runs: scoreboard, sweeps over the window size, training of the learned backbones."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import words
from ..sources.layout import nest
from . import analysis, baselines, boundary, convert, measures, neural, rouge, runs, split, train
from .backbones import Backbone, LearnedBackbone, LeadBackbone, PolicyBackbone, Sliding, StrideBackbone, bags
from .iteration import cut
from .windows import View, advance


def gold_segments(gold: DataFrame) -> DataFrame:
    """(meeting_id, snip_no, seg_start, seg_end) of merged annotated sentences."""
    return convert.merge(analysis.support_spans(gold)).drop("sent_nos")


def outputs_of(utts: DataFrame, gold: DataFrame, backbone: Backbone, k: int = 1024) -> dict[str, DataFrame]:
    """Steps of the four runs of a backbone."""
    return {"truncate": runs.truncate_run(utts, backbone, k), "fixed": runs.fixed_run(utts, backbone, k), "gold": runs.gold_run(utts, gold_segments(gold), backbone, k), "dynamic": runs.dynamic(utts, backbone, k)}


def scoreboard(utts: DataFrame, gold: DataFrame, steps: dict[str, DataFrame], longest: bool = True) -> DataFrame:
    """(run, measure, n, p, r, f) of ROUGE-1, -2 and -L, and of factual support beside them."""
    reference, out = rouge.reference_texts(gold), None
    for name, rows in steps.items():
        text = runs.dedup_sentences(runs.assemble(rows)).select("meeting_id", "text").persist()  # one short text a meeting, read by four measures
        pairs = rouge.pairs(text, reference)
        parts = [rouge.means(rouge.ngram_by_row(pairs, 1), "r1"), rouge.means(rouge.ngram_by_row(pairs, 2), "r2")] + ([rouge.means(rouge.longest(pairs), "rl")] if longest else [])
        support = measures.consistency_by_row(text, utts).agg(F.count("*").alias("n"), F.round(F.sum("supported") / F.sum("grams"), 6).alias("p")).withColumns({"r": F.lit(None).cast("double"), "f": F.lit(None).cast("double"), "measure": F.lit("support")})
        for part in [*parts, support]:
            part = part.withColumn("run", F.lit(name))
            out = part if out is None else out.unionByName(part)
    return out


def sweep_k(utts: DataFrame, links: DataFrame, q: int, sizes=(64, 128, 256, 512, 1024)) -> DataFrame:
    """(k, steps, tokens, again, attention, recall) of the dynamic lead run for each window size; one plan for all sizes."""
    out = None
    for k in sizes:
        steps = runs.dynamic(utts, LeadBackbone(q), k)
        row = measures.cost(steps).crossJoin(measures.support_recall(steps, links).select("recall")).withColumn("k", F.lit(k).cast("long"))
        out = row if out is None else out.unionByName(row)
    return out


def noisy_segments(utts: DataFrame, gold: DataFrame) -> DataFrame:
    """Snippet segments with split and noise; validation and test without."""
    return convert.add_noise(gold_segments(gold), utts, split.assign(utts))


def learned(utts: DataFrame, gold: DataFrame, lr: float = 0.3, epochs: int = 20, positive: float = 20.0, k: int = 1024) -> tuple[LearnedBackbone, list]:
    """The learned backbone with the weights of the epoch that scores best on validation, and the history [(epoch, weights, loss, ROUGE-2 F on
    validation)] of all epochs.

    The published rate of 2e-5 belongs to a pre-trained network; a head that starts at zero needs a larger one."""
    segs = noisy_segments(utts, gold).persist()
    rows = cut(train.boundary_blocks(utts, segs.where("split = 'train'")))  # a table: a plan with all that is behind it, in each of 40 passes, fills the driver
    history = train.adamw(rows, lr, epochs, positive=positive, steps_per_epoch=2, width=train.WIDTH)
    scores = validated(utts, gold, {e: w for e, w, _ in history}, k)
    history = [(e, w, loss, scores.get(e, 0.0)) for e, w, loss in history]
    best = train.best_checkpoint(utts.sparkSession.createDataFrame([(e, w, s) for e, w, _, s in history], "epoch int, weights array<double>, val_r2 double")).first()
    return LearnedBackbone(list(best.weights)), history


def validated(utts: DataFrame, gold: DataFrame, weights: dict[int, list[float]], k: int = 1024) -> dict[int, float]:
    """{epoch: ROUGE-2 F of its dynamic run on the validation meetings}. A meeting passes once: the runs of all epochs share what its windows
    have in common, and are scored where they are made."""
    if not weights:
        return {}
    names = split.assign(utts).where("split = 'validation'").select("meeting_id")
    reference = rouge.reference_texts(gold.join(names, "meeting_id", "left_semi")).select("meeting_id", words(F.col("text")).alias("reference"))
    nested = nest(utts.join(names, "meeting_id", "left_semi").withColumn("line", F.array_join("tokens", " ")), ("line",))
    nested = nested.select("meeting_id", *[F.col(f"utterances.{c}").alias(c) for c in (*runs.ARRAYS, "line")])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                ref = bigrams([] if r.reference is None else list(r.reference))
                texts = [] if r.utt_no is None else epoch_texts(r, weights, k)
                for e, text in texts or ((e, []) for e in weights):
                    cand = bigrams(text)
                    out.append((f"{e}@{r.meeting_id}", sum(min(n, ref[g]) for g, n in cand.items()), sum(cand.values()), sum(ref.values())))
            yield pd.DataFrame(out, columns=["key", "match", "cand", "ref"])

    counts = nested.join(reference, "meeting_id", "full").mapInPandas(run, "key string, match long, cand long, ref long")
    return {int(r.run): r.f for r in mean_scores(counts, "r2").collect()}  # a row an epoch


def bigrams(tokens: list[str]) -> Counter:
    return Counter(zip(tokens, tokens[1:]))


def epoch_texts(record, weights: dict[int, list[float]], k: int) -> list[tuple[int, list[str]]]:
    """(epoch, tokens of all snippets) of the dynamic runs over one meeting. Windows that several epochs visit are looked at once."""
    meeting, line = runs.Meeting(record), [x.split() for x in record.line]
    sliding, out = Sliding(bags(meeting.text), meeting.speaker), []
    sliding.features, sliding.salient = lru_cache(2048)(sliding.features), lru_cache(8192)(sliding.salient)
    for epoch, w in weights.items():
        backbone = Places(w).over(sliding)
        out.append((epoch, [t for s in runs.steps_of(meeting, backbone, k, "after", "boundary") for i in s[6] for t in line[i]]))
    return out


class Places(LearnedBackbone):
    """The learned backbone with places instead of texts as snippets, for a meeting at hand."""

    def of(self, meeting) -> Backbone:
        return self

    def generate(self, view: View):
        return self.chosen(view)


def run_pairs(texts: DataFrame, reference: DataFrame, names: list[str]) -> DataFrame:
    """Pairs for ROUGE of several runs at once: texts (run, meeting_id, text) against the reference (meeting_id, text) of every meeting; keys are run@meeting."""
    runs_ = texts.sparkSession.createDataFrame([(n,) for n in names], "run string")
    tag = lambda df: df.select(F.concat_ws("@", "run", "meeting_id").alias("meeting_id"), "text")
    return rouge.pairs(tag(texts), tag(reference.crossJoin(F.broadcast(runs_))))  # a reference for each of the few names


def mean_scores(counts: DataFrame, measure: str) -> DataFrame:
    """(run, measure, n, p, r, f): means over the meetings of each run."""
    rows = counts.select(F.split("key", "@")[0].alias("run"), rouge.scored(F.col("match"), F.col("cand"), F.col("ref")).alias("s")).select("run", "s.*")
    return rows.groupBy("run").agg(F.lit(measure).alias("measure"), F.count("*").alias("n"), *[F.round(F.avg(c), 6).alias(c) for c in ("p", "r", "f")])


def compared(utts: DataFrame, gold: DataFrame, backbone: Backbone, q: int = 10, k: int = 1024) -> DataFrame:
    """(run, measure, n, p, r, f) of ROUGE-1, -2 and -L on the test meetings: the extractive baselines, the networks with their trained read-outs,
    segments by cohesion, and the four runs of a backbone. All runs are scored in one plan a measure."""
    read_outs = neural.fitted(utts, gold, q)
    names = split.assign(utts).where("split = 'test'").select("meeting_id")
    some, wanted = utts.join(names, "meeting_id", "left_semi").persist(), gold.join(names, "meeting_id", "left_semi").persist()
    chosen = {"textrank": baselines.textrank(some, q), "summary_runner": baselines.summary_runner(some, q, read_outs["runner"]), "lead": baselines.lead(some, q), "random": baselines.hashed(some, q)}
    segments = baselines.topic_segments(some, baselines.topic_cuts(some))
    made = {"topic_segments": runs.gold_run(some, segments, LeadBackbone(1), k), **outputs_of(some, wanted, backbone, k)}
    nets = neural.picked(some, read_outs, q).select("run", "meeting_id", "utt_no")
    for name, rows in chosen.items():
        nets = nets.unionByName(rows.select(F.lit(name).alias("run"), "meeting_id", "utt_no"))
    of_run = nets.join(some.select("meeting_id", "utt_no", "text"), ["meeting_id", "utt_no"]).groupBy("run", "meeting_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("utt_no", "text"))), lambda x: x["text"]), "\n").alias("text"))
    for name, steps in made.items():
        of_run = of_run.unionByName(runs.dedup_sentences(runs.assemble(steps)).select(F.lit(name).alias("run"), "meeting_id", "text"))
    pairs = run_pairs(of_run, rouge.reference_texts(wanted), [*neural.NETWORKS, *chosen, *made]).persist()
    return mean_scores(rouge.ngram(pairs, 1), "r1").unionByName(mean_scores(rouge.ngram(pairs, 2), "r2")).unionByName(mean_scores(rouge.longest(pairs), "rl"))


def direct(utts: DataFrame, gold: DataFrame, inner: Backbone, k: int = 1024) -> StrideBackbone:
    """Stride predicted as a number from window features, fitted on the training split."""
    segs = noisy_segments(utts, gold).where("split = 'train'").select("meeting_id", "gold_start", "gold_end").withColumnRenamed("gold_start", "seg_start")
    return StrideBackbone(inner, train.direct_stride(train.stride_rows(utts, segs, k)))


def policy(utts: DataFrame, gold: DataFrame, inner: Backbone, k: int = 1024, episodes: int = 4, lr: float = 0.5) -> tuple[PolicyBackbone, list]:
    """Strides by reward: an episode is one distributed run over the training meetings, its reward ROUGE-1 F; sums over meetings reach the driver."""
    names = split.assign(utts).where("split = 'train'").select("meeting_id")
    some = utts.join(names, "meeting_id", "left_semi").persist()
    reference = rouge.reference_texts(gold.join(names, "meeting_id", "left_semi")).persist()

    def reward(logits: list[float], episode: int):
        backbone = PolicyBackbone(inner, logits, seed=episode)

        @F.pandas_udf("int")
        def action(meetings: pd.Series, lefts: pd.Series) -> pd.Series:
            return pd.Series([backbone.action(m, int(x)) for m, x in zip(meetings, lefts)], dtype="int32")

        steps = runs.dynamic(some, backbone, k).persist()
        scores = rouge.ngram(rouge.pairs(runs.assemble(steps), reference), 1).select("key", rouge.scored(F.col("match"), F.col("cand"), F.col("ref"))["f"].alias("f"))
        acts = steps.select(F.col("meeting_id").alias("key"), action("meeting_id", "left_utt").alias("act"))
        places = range(len(logits))
        rows = acts.groupBy("key").agg(*[F.count_if(F.col("act") == a).alias(f"c{a}") for a in places]).join(scores, "key")
        s = rows.agg(F.count("*").alias("n"), F.sum("f").alias("f"), *[F.sum(f"c{a}").alias(f"c{a}") for a in places], *[F.sum(F.col(f"c{a}") * F.col("f")).alias(f"r{a}") for a in places]).first()
        steps.unpersist()
        return s.n, s.f or 0.0, np.array([s[f"c{a}"] or 0 for a in places], float), np.array([s[f"r{a}"] or 0.0 for a in places])

    history = train.policy_gradient(reward, len(PolicyBackbone(inner, [0.0]).actions), episodes, lr)
    return PolicyBackbone(inner, history[-1][1], greedy=True), history


def boundary_distances(utts: DataFrame, gold: DataFrame, make: Callable[[], Backbone], k: int = 1024) -> DataFrame:
    """Distances of a backbone's boundary from gold when each window starts at a gold segment (teacher)."""
    return boundary_distances_by(utts, gold, {"one": make()}, k).drop("backbone")


def boundary_distances_by(utts: DataFrame, gold: DataFrame, backbones: dict[str, Backbone], k: int = 1024) -> DataFrame:
    """As boundary_distances(), of several backbones (column backbone); a meeting passes once for all of them."""
    segs = gold_segments(gold)
    asked = segs.select("meeting_id", "snip_no", "seg_start", F.col("seg_end").alias("gold_utt"))
    return boundary.distance(teacher_boundaries(utts, asked, backbones, k), asked.select("meeting_id", "snip_no", "gold_utt"), utts, also=("backbone",))


def teacher_boundaries(utts: DataFrame, asked: DataFrame, backbones: dict[str, Backbone], k: int = 1024) -> DataFrame:
    """(backbone, meeting_id, snip_no, pred_utt): one window from each asked left edge; a meeting's windows in one task."""
    edges = asked.groupBy("meeting_id").agg(F.collect_list(F.struct("snip_no", "seg_start")).alias("edges"))
    shared = utts.sparkSession.sparkContext.broadcast(backbones)

    def run(batches):
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                m = runs.Meeting(r)
                for name, backbone in shared.value.items():
                    backbone = backbone.of(m)
                    for e in r.edges:
                        left = int(np.searchsorted(m.utt_no, e["seg_start"]))
                        _, _, _, _, b, _ = runs.step(m, left, backbone, k, "after")
                        out.append((name, r.meeting_id, int(e["snip_no"]), int(m.utt_no[advance(left, b, len(m.utt_no) - 1)[0]])))
            yield pd.DataFrame(out, columns=["backbone", "meeting_id", "snip_no", "pred_utt"])

    return runs.arrays(nest(utts)).join(edges, "meeting_id").mapInPandas(run, "backbone string, meeting_id string, snip_no long, pred_utt long")
