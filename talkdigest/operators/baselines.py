"""Baselines of the comparison: two extractive ones, and column forms of the distinguishing operator of six neural ones.

The column forms work on simple features (lengths); the networks themselves are in neural.py. Scores are never the published ones.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import words
from ..schema import ROLES, positive
from .backbones import bags, best_in_order, depths, gap_scores
from .iteration import cut
from .nn import softmax

DAMPING, ROUNDS = 0.85, 20

# extractive

def edges(utts: DataFrame, most_share: float = 1.0) -> DataFrame:
    """(meeting_id, i, j, weight), i < j: shared distinct words over the sum of log sizes, for utterances of two words or more.

    With most_share below 1, words that stand in a larger share of a meeting's utterances link nothing."""
    rows = utts.select("meeting_id", "utt_no", F.array_distinct("tokens").alias("w")).where("size(w) >= 2")
    n = rows.groupBy("meeting_id").agg(F.count("*").alias("n"))
    flat = rows.select("meeting_id", "utt_no", F.size("w").alias("size"), F.explode("w").alias("word"))
    df = flat.groupBy("meeting_id", "word").agg(F.count("*").alias("df")).join(n, "meeting_id").where(f"df >= 2 and df <= greatest(2, n * {most_share})").select("meeting_id", "word")
    flat = flat.join(df, ["meeting_id", "word"])
    a, b = flat.select("meeting_id", "word", F.col("utt_no").alias("i"), F.col("size").alias("si")), flat.select("meeting_id", "word", F.col("utt_no").alias("j"), F.col("size").alias("sj"))
    return a.join(b, ["meeting_id", "word"]).where("i < j").groupBy("meeting_id", "i", "j").agg((F.count("*") / (F.ln(F.first("si").cast("double")) + F.ln(F.first("sj").cast("double")))).alias("weight"))


def textrank_frames(utts: DataFrame, rounds: int = ROUNDS, keep=None, most_share: float = 1.0) -> DataFrame:
    """(meeting_id, utt_no, rank): damped ranks by joins and sums, a round a pass; keep(df) cuts the lineage every fifth."""
    keep = keep or cut
    one = edges(utts, most_share)
    both = one.select("meeting_id", F.col("i").alias("a"), F.col("j").alias("b"), "weight").unionByName(one.select("meeting_id", F.col("j").alias("a"), F.col("i").alias("b"), "weight"))
    total = both.groupBy("meeting_id", "a").agg(F.sum("weight").alias("total"))
    both = keep(both.join(total, ["meeting_id", "a"]).select("meeting_id", "a", "b", (F.col("weight") / F.col("total")).alias("share")))
    nodes = utts.where(F.size(F.array_distinct("tokens")) >= 2).select("meeting_id", F.col("utt_no").alias("a"))
    nodes = nodes.withColumn("n", F.count("*").over(Window.partitionBy("meeting_id"))).withColumn("rank", 1 / F.col("n"))
    for r in range(rounds):
        got = both.join(nodes.select("meeting_id", "a", "rank"), ["meeting_id", "a"]).groupBy("meeting_id", F.col("b").alias("a")).agg(F.sum(F.col("share") * F.col("rank")).alias("got"))
        nodes = nodes.drop("rank").join(got, ["meeting_id", "a"], "left").withColumn("rank", (1 - DAMPING) / F.col("n") + DAMPING * F.coalesce("got", F.lit(0.0))).drop("got")
        if r % 5 == 4:
            nodes = keep(nodes)
    return nodes.select("meeting_id", F.col("a").alias("utt_no"), "rank")


DENSE = 4000  # utterances up to which shared words are counted by one matrix product


def shared_words(items: list[Counter], nodes: list[int], most_share: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, number of shared words), i < j, for pairs that share any."""
    holders: dict[str, list[int]] = {}
    for i in nodes:
        for w in items[i]:
            holders.setdefault(w, []).append(i)
    used = [at for at in holders.values() if 2 <= len(at) <= max(2, len(nodes) * most_share)]
    if len(items) <= DENSE:
        x = np.zeros((len(items), len(used)), np.float32)
        for c, at in enumerate(used):
            x[at, c] = 1
        both = np.triu(x @ x.T, 1)
        i, j = np.nonzero(both)
        return i, j, both[i, j]
    shared: Counter = Counter()
    for at in used:
        shared.update((a, b) for x, a in enumerate(at) for b in at[x + 1:])
    i, j = np.array(list(shared), np.int64).reshape(-1, 2).T
    return i, j, np.array(list(shared.values()), float)


def text_ranks(items: list[Counter], rounds: int = ROUNDS, most_share: float = 1.0) -> np.ndarray:
    """Ranks of one meeting's utterances; 0 for those of fewer than two words."""
    nodes = [i for i, x in enumerate(items) if len(x) >= 2]
    rank = np.zeros(len(items))
    if not nodes:
        return rank
    i, j, n = shared_words(items, nodes, most_share)
    if len(i):
        size = np.log(np.maximum([len(x) for x in items], 1))
        w = n / (size[i] + size[j])
        total = np.bincount(np.r_[i, j], np.r_[w, w], len(items))
        src, dst, share = np.r_[i, j], np.r_[j, i], np.r_[w / total[i], w / total[j]]
    rank[nodes] = 1 / len(nodes)
    for _ in range(rounds):
        new = np.zeros(len(items))
        new[nodes] = (1 - DAMPING) / len(nodes)
        if len(i):
            new += DAMPING * np.bincount(dst, share * rank[src], len(items))
        rank = new
    return rank


def lines_of(utts: DataFrame) -> DataFrame:
    """(meeting_id, utt_no, speaker, line): a row of arrays a meeting; a line holds the tokens of an utterance, joined by a space, as nested
    arrays are slow to pass to Python."""
    rows = utts.groupBy("meeting_id").agg(F.sort_array(F.collect_list(F.struct("utt_no", "speaker", F.array_join("tokens", " ").alias("line")))).alias("u"))
    return rows.select("meeting_id", *[F.col(f"u.{c}").alias(c) for c in ("utt_no", "speaker", "line")])


def per_meeting(utts: DataFrame, pick, schema: str = "meeting_id string, utt_no long, place long, score double") -> DataFrame:
    """pick(tokens of all utterances, speakers) -> [(index, score)] for each meeting, in a task of its own."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                out += [(r.meeting_id, int(r.utt_no[i]), place, float(score)) for place, (i, score) in enumerate(pick([Counter(t.split()) for t in r.line], list(r.speaker)))]
            yield pd.DataFrame(out, columns=["meeting_id", "utt_no", "place", "score"])

    return lines_of(utts).mapInPandas(run, schema)


def textrank(utts: DataFrame, q: int = 10, rounds: int = ROUNDS, most_share: float = 1.0) -> DataFrame:
    """(meeting_id, utt_no, place, score): the q best-ranked utterances in source order; ties to earlier ones."""
    positive(q=q)

    def pick(items, speakers):
        ranks = text_ranks(items, rounds, most_share)
        return [(i, ranks[i]) for i in best_in_order([round(x, 12) for x in ranks], q)]

    return per_meeting(utts, pick)


class Cells:
    """Word counts of a meeting's utterances as flat arrays, a cell for each distinct word of an utterance: `item`, `word` (a place in
    `words`) and `n`."""

    def __init__(self, items: list[Counter]):
        self.items, index = items, {}
        self.word = np.array([index.setdefault(w, len(index)) for x in items for w in x], np.int64)
        self.n = np.array([n for x in items for n in x.values()], float)
        self.sizes = np.array([len(x) for x in items], np.int64)
        self.item = np.repeat(np.arange(len(items)), self.sizes)
        self.words, self.at = list(index), np.r_[0, np.cumsum(self.sizes)]
        self.length = self.summed(self.n)

    def summed(self, cells: np.ndarray) -> np.ndarray:
        """Sums of a value a cell, by utterance."""
        return np.bincount(self.item, cells, len(self.items))

    @cached_property
    def total(self) -> np.ndarray:
        """Counts in the whole meeting, by word."""
        return np.bincount(self.word, self.n, len(self.words))

    @cached_property
    def squares(self) -> np.ndarray:
        return self.summed(self.n * self.n)


def cells_of(items) -> Cells:
    return items if isinstance(items, Cells) else Cells(items)


def greedy_labels(items: list[Counter] | Cells, reference: Counter, most: int) -> set[int]:
    """Utterances taken one by one while the unigram F1 with the reference grows; an utterance's gain is counted over its own words."""
    cells = cells_of(items)
    wanted, size, chosen, best, hits = sum(reference.values()), 0.0, set(), 0.0, 0.0
    most_hits = np.array([reference[w] for w in cells.words], float)
    used = most_hits[cells.word] > 0
    item, word, n = cells.item[used], cells.word[used], cells.n[used]
    have, taken = np.zeros(len(most_hits)), np.zeros(len(cells.items), bool)
    while len(chosen) < min(most, len(cells.items)):
        had, bound = have[word], most_hits[word]
        both = hits + np.bincount(item, np.minimum(had + n, bound) - np.minimum(had, bound), len(taken))
        f = np.where(both > 0, 2 * both / np.maximum(size + cells.length + wanted, 1), 0.0)
        f[taken] = -1.0
        i = int(f.argmax())
        if f[i] <= best:
            break
        best, hits = float(f[i]), both[i]
        chosen.add(i)
        taken[i] = True
        have[word[item == i]] += n[item == i]
        size += cells.length[i]
    return chosen


def ratios(dot: np.ndarray, a, b) -> np.ndarray:
    """Cosines of dot products and squared norms; 0 for a product of 0."""
    return np.divide(dot, np.sqrt(a * b), out=np.zeros(len(dot)), where=dot != 0)


def runner_features(cells: Cells) -> np.ndarray:
    """Bias, content, salience against the whole, novelty against what is taken (1: nothing is taken yet), absolute and relative place."""
    n, total = len(cells.items), cells.total
    salient = ratios(cells.summed(cells.n * total[cells.word]), cells.squares, total @ total)
    place = np.arange(n)
    return np.column_stack([np.ones(n), np.log1p(cells.length), salient, np.ones(n), np.log1p(place) / 8, place / max(1, n - 1)])


#: Signs of a plain keep/drop rule, used where no trained weights are given (fixed values).
RUNNER_WEIGHTS = (-1.5, 0.4, 2.0, 0.5, -0.2, -0.3)


def runner_scores(cells: Cells, weights) -> list[float]:
    """Each utterance's keep probability against the summary so far, which takes so much of it. The summary's norm is kept up from the
    products at hand, not summed anew over its words for each utterance."""
    w = np.array(weights, float)
    novel = float(w[3])
    rest, squares = (runner_features(cells) @ w).tolist(), cells.squares.tolist()
    have, norm, scores, word, n, at = [0.0] * len(cells.words), 0.0, [], cells.word.tolist(), cells.n.tolist(), cells.at.tolist()
    for i, z in enumerate(rest):
        mine = range(at[i], at[i + 1])
        dot = 0.0
        for c in mine:
            dot += n[c] * have[word[c]]
        if dot:
            z -= novel * dot / math.sqrt(squares[i] * norm)
        p = 1 / (1 + math.exp(-z))
        scores.append(p)
        for c in mine:
            have[word[c]] += n[c] * p
        norm += p * (2 * dot + p * squares[i])
    return scores


def summary_runner(utts: DataFrame, q: int = 10, weights=RUNNER_WEIGHTS) -> DataFrame:
    """(meeting_id, utt_no, place, score): a pass over the utterances that weighs each against the summary so far (in soft counts), then the q best in order."""
    def pick(items, speakers):
        scores = runner_scores(Cells(items), weights)
        return [(i, scores[i]) for i in best_in_order([round(s, 12) for s in scores], q)]

    return per_meeting(utts, pick)


def lead(utts: DataFrame, q: int = 10) -> DataFrame:
    return utts.withColumn("place", F.row_number().over(Window.partitionBy("meeting_id").orderBy("utt_no")) - 1).where(F.col("place") < q).select("meeting_id", "utt_no", "place")


def hashed(utts: DataFrame, q: int = 10, seed: int = 0) -> DataFrame:
    """q utterances by an arithmetic hash, in source order: a reproducible random baseline."""
    h = (F.col("utt_no") * 7919 + seed) % 104729
    nth = F.row_number().over(Window.partitionBy("meeting_id").orderBy(h, "utt_no"))
    rows = utts.withColumn("nth", nth).where(F.col("nth") <= q)
    return rows.select("meeting_id", "utt_no", (F.row_number().over(Window.partitionBy("meeting_id").orderBy("utt_no")) - 1).alias("place"))


def texts(picked: DataFrame, utts: DataFrame) -> DataFrame:
    """(meeting_id, text) of picked utterances, in source order."""
    return picked.join(utts.select("meeting_id", "utt_no", "text"), ["meeting_id", "utt_no"]).groupBy("meeting_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("utt_no", "text"))), lambda x: x["text"]), "\n").alias("text"))


# cores of neural ones

def additive_attention(query: np.ndarray, keys: np.ndarray, wq: np.ndarray, wk: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(weights, context): softmax of v . tanh(Wq q + Wk k) over the keys."""
    weights = softmax(np.tanh(query @ wq + keys @ wk) @ v)
    return weights, weights @ keys


def recurrent_step(x: np.ndarray, h: np.ndarray, w: dict) -> np.ndarray:
    """One gated recurrent step."""
    sig = lambda a: 1 / (1 + np.exp(-a))
    z, r = sig(x @ w["xz"] + h @ w["hz"]), sig(x @ w["xr"] + h @ w["hr"])
    return (1 - z) * h + z * np.tanh(x @ w["xh"] + (r * h) @ w["hh"])


def attention_weights(utts: DataFrame) -> DataFrame:
    """(meeting_id, utt_no, weight): softmax over a meeting's utterances of a score that grows with their words (log-length), in column form."""
    w = Window.partitionBy("meeting_id")
    rows = utts.select("meeting_id", "utt_no", F.ln(1 + F.col("n_tok").cast("double")).alias("s"))
    rows = rows.withColumn("e", F.exp(F.col("s") - F.max("s").over(w)))
    return rows.select("meeting_id", "utt_no", (F.col("e") / F.sum("e").over(w)).alias("weight"))


def pointer_mixture(utts: DataFrame, p_gen: float = 0.5) -> DataFrame:
    """(meeting_id, word, p): generation over the meeting's word frequencies mixed with copying by attention; sums to 1 a meeting."""
    att = attention_weights(utts.where("n_tok > 0"))
    copied = utts.join(att, ["meeting_id", "utt_no"]).select("meeting_id", F.explode("tokens").alias("word"), (F.col("weight") / F.col("n_tok")).alias("copy"), F.lit(1).alias("one"))
    rows = copied.groupBy("meeting_id", "word").agg(F.sum("copy").alias("copy"), F.sum("one").alias("n"))
    vocab = F.col("n") / F.sum("n").over(Window.partitionBy("meeting_id"))
    return rows.select("meeting_id", "word", (p_gen * vocab + (1 - p_gen) * F.col("copy")).alias("p"))


def coverage_vector(attentions: list[np.ndarray]) -> tuple[np.ndarray, float]:
    """(sum of earlier attentions, penalty): attention that falls on what was attended before."""
    seen, penalty = np.zeros_like(attentions[0]), 0.0
    for a in attentions:
        penalty += float(np.minimum(a, seen).sum())
        seen = seen + a
    return seen, penalty


def gated_weights(utts: DataFrame) -> DataFrame:
    """(meeting_id, word, weight): an utterance's gate (logistic of its length against the mean) scales its words; renormalised a meeting."""
    w = Window.partitionBy("meeting_id")
    rows = utts.where("n_tok > 0").withColumn("gate", 1 / (1 + F.exp(-(F.col("n_tok") - F.avg("n_tok").over(w)) / 10)))
    rows = rows.select("meeting_id", F.explode("tokens").alias("word"), "gate").groupBy("meeting_id", "word").agg(F.sum("gate").alias("g"))
    return rows.select("meeting_id", "word", (F.col("g") / F.sum("g").over(w)).alias("weight"))


def topic_gaps(utts: DataFrame, block: int = 8) -> DataFrame:
    """(meeting_id, utt_no, score): cosine of summed word counts of the blocks before and after the gap behind each utterance, by joins."""
    last = utts.groupBy("meeting_id").agg(F.max("utt_no").alias("last_utt"))
    cells = utts.join(last, "meeting_id").select("meeting_id", "utt_no", "last_utt", F.explode("tokens").alias("word"))
    left = cells.select("meeting_id", "word", F.explode(F.sequence("utt_no", F.least(F.col("utt_no") + block - 1, F.col("last_utt")))).alias("gap"), F.lit(1).alias("a"), F.lit(0).alias("b"))
    right = cells.where("utt_no > 0").select("meeting_id", "word", F.explode(F.sequence(F.greatest(F.col("utt_no") - block, F.lit(0)), F.col("utt_no") - 1)).alias("gap"), F.lit(0).alias("a"), F.lit(1).alias("b"))
    rows = left.unionByName(right).groupBy("meeting_id", "gap", "word").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    rows = rows.groupBy("meeting_id", "gap").agg(F.sum(F.col("a") * F.col("b")).alias("dot"), F.sum(F.col("a") * F.col("a")).alias("aa"), F.sum(F.col("b") * F.col("b")).alias("bb"))
    rows = rows.join(last, "meeting_id").where("gap < last_utt")
    return rows.select("meeting_id", F.col("gap").alias("utt_no"), F.when(F.col("aa") * F.col("bb") > 0, F.col("dot") / F.sqrt((F.col("aa") * F.col("bb")).cast("double"))).otherwise(0.0).alias("score"))


def topic_cuts(utts: DataFrame, block: int = 8, c: float = 1.0) -> DataFrame:
    """(meeting_id, utt_no, place, score): cuts behind utterances whose depth exceeds mean + c * deviation of the meeting's depths."""
    def pick(items, speakers):
        deep = depths(gap_scores(items, block))
        if not len(deep):
            return []
        bound = deep.mean() + c * deep.std()
        return [(i, d) for i, d in enumerate(deep) if d > bound]

    return per_meeting(utts, pick)


def topic_segments(utts: DataFrame, cuts: DataFrame) -> DataFrame:
    """(meeting_id, snip_no, seg_start, seg_end) between cuts."""
    rows = utts.select("meeting_id", "utt_no").join(cuts.select("meeting_id", (F.col("utt_no") + 1).alias("utt_no"), F.lit(1).alias("cut")), ["meeting_id", "utt_no"], "left")
    rows = rows.withColumn("snip_no", F.coalesce(F.sum("cut").over(Window.partitionBy("meeting_id").orderBy("utt_no")), F.lit(0)).cast("long"))
    return rows.groupBy("meeting_id", "snip_no").agg(F.min("utt_no").alias("seg_start"), F.max("utt_no").alias("seg_end"))


def role_vector(speaker):
    return F.array(*[(speaker == r).cast("double") for r in ROLES])


def hierarchical_pool(utts: DataFrame) -> DataFrame:
    """(meeting_id, length, type_share, pm, me, id, ui): word -> turn -> meeting averages, with the role one-hot joined to a turn."""
    word = F.transform("tokens", lambda t: F.length(t).cast("double"))
    turn = F.when(F.size("tokens") > 0, F.aggregate(word, F.lit(0.0), lambda s, x: s + x) / F.size("tokens")).otherwise(0.0)
    types = F.when(F.size("tokens") > 0, F.size(F.array_distinct("tokens")) / F.size("tokens")).otherwise(0.0)
    rows = utts.select("meeting_id", turn.alias("turn"), types.alias("types"), role_vector(F.col("speaker")).alias("role"))
    return rows.groupBy("meeting_id").agg(F.round(F.avg("turn"), 6).alias("length"), F.round(F.avg("types"), 6).alias("type_share"), *[F.round(F.avg(F.col("role")[i]), 6).alias(r.lower()) for i, r in enumerate(ROLES)])


def discourse_edges(utts: DataFrame) -> DataFrame:
    """(meeting_id, a, b, relation): to the next turn, to the same speaker's next turn, and to the next turn of another speaker (reply)."""
    order = Window.partitionBy("meeting_id").orderBy("utt_no")
    own = Window.partitionBy("meeting_id", "speaker").orderBy("utt_no")
    rows = utts.select("meeting_id", F.col("utt_no").alias("a"), F.lead("utt_no").over(order).alias("next"), F.lead("utt_no").over(own).alias("same"), F.lead("speaker").over(order).alias("next_speaker"), "speaker")
    out = F.array(F.struct(F.col("next").alias("b"), F.lit("next").alias("relation")), F.struct(F.col("same").alias("b"), F.lit("same").alias("relation")), F.struct(F.when(F.col("next_speaker") != F.col("speaker"), F.col("next")).alias("b"), F.lit("reply").alias("relation")))
    return rows.select("meeting_id", "a", F.inline(out)).where("b is not null")


#: Weights of the one-feature convolution: the utterance itself and each relation (fixed values).
RELATIONS = {"self": 1.0, "next": 0.5, "same": 0.25, "reply": 0.125}


def graph_convolution(utts: DataFrame, edge_rows: DataFrame, weights: dict[str, float] = RELATIONS) -> DataFrame:
    """(meeting_id, utt_no, value): one step on a feature (tokens) over typed edges, rectified: own value and, of each relation, the mean over
    neighbours on both sides, each under its own weight."""
    both = edge_rows.select("meeting_id", "a", "b", "relation").unionByName(edge_rows.select("meeting_id", F.col("b").alias("a"), F.col("a").alias("b"), "relation"))
    feature = utts.select("meeting_id", F.col("utt_no").alias("b"), F.col("n_tok").cast("double").alias("x"))
    means = both.join(feature, ["meeting_id", "b"]).groupBy("meeting_id", "a", "relation").agg(F.avg("x").alias("x"))
    rows = means.unionByName(feature.select("meeting_id", F.col("b").alias("a"), F.lit("self").alias("relation"), "x"))
    weight = F.element_at(F.create_map(*[F.lit(v) for pair in weights.items() for v in pair]), F.col("relation"))
    return rows.groupBy("meeting_id", F.col("a").alias("utt_no")).agg(F.greatest(F.sum(F.col("x") * weight), F.lit(0.0)).alias("value"))


def word_bag(text):
    return bags([text])[0]


def word_counts(utts: DataFrame) -> DataFrame:
    return utts.select("meeting_id", F.explode(words(F.col("text"))).alias("word")).groupBy("meeting_id", "word").count()
