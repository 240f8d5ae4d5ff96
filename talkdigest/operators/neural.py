"""Network baselines as scorers of utterances: hidden layers that differ in their distinguishing part, and a trained read-out.

A network turns a meeting into a row of features for each utterance; the q utterances that its read-out scores best are the
summary. Only the read-out is trained, by least squares on greedy labels of the training meetings, summed on the cluster. Hidden
layers keep seeded weights: the scores show what the parts do, and are not those of networks trained end to end."""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import cache, cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import words
from ..schema import ROLES, positive
from . import split, train
from .backbones import best_in_order
from .baselines import RUNNER_WEIGHTS, Cells, greedy_labels, lines_of, ratios, recurrent_step, runner_features
from .iteration import cut
from .nn import softmax
from .rouge import reference_texts

SIZE, BUCKETS, STEPS = 16, 4096, 4


@cache
def seeded(name: str, rows: int = SIZE, columns: int = SIZE) -> np.ndarray:
    """The weights of a named layer, the same in every process."""
    return np.random.default_rng(zlib.crc32(name.encode())).standard_normal((rows, columns)) / math.sqrt(rows)


def layer(name: str) -> np.ndarray:
    return seeded(name)[0] * math.sqrt(SIZE)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def word_vectors(words: list[str]) -> np.ndarray:
    return seeded("words", BUCKETS)[[zlib.crc32(w.encode()) % BUCKETS for w in words]] * math.sqrt(BUCKETS / SIZE)


class Items(Cells):
    """A meeting's utterances, with what several networks need of them computed once."""

    @cached_property
    def vectors(self) -> np.ndarray:
        """A row a word."""
        return word_vectors(self.words) if self.words else np.zeros((0, SIZE))

    def rows_summed(self, rows: np.ndarray) -> np.ndarray:
        """Sums of a row a cell, by utterance; zeros without words."""
        out, some = np.zeros((len(self.items), rows.shape[1])), self.sizes > 0
        if some.any():
            out[some] = np.add.reduceat(rows, self.at[:-1][some], axis=0)
        return out

    @cached_property
    def embedded(self) -> np.ndarray:
        """A vector an utterance: its word vectors by their counts, over the root of its length; zeros without words."""
        return self.rows_summed(self.vectors[self.word] * self.n[:, None]) / np.sqrt(np.maximum(self.length, 1))[:, None]

    @cached_property
    def states(self) -> np.ndarray:
        return states(self.embedded)


def items_of(items) -> Items:
    return items if isinstance(items, Items) else Items(items)


def embed(items: list[Counter]) -> np.ndarray:
    return items_of(items).embedded


def states(x: np.ndarray) -> np.ndarray:
    """A recurrent pass over the utterances."""
    return states_together([x])[0]


def states_together(inputs: list[np.ndarray]) -> list[np.ndarray]:
    """A recurrent pass over the utterances of each of some meetings, all of them moving on by one utterance at a time."""
    w = {k: seeded(f"cell {k}") for k in ("xz", "hz", "xr", "hr", "xh", "hh")}
    sizes = np.array([len(x) for x in inputs])
    order, starts, flat = np.argsort(-sizes, kind="stable"), np.r_[0, np.cumsum(sizes)], np.concatenate(inputs)
    longer, at = -sizes[order], starts[order]
    out, h = np.zeros_like(flat), np.zeros((len(inputs), SIZE))
    for t in range(int(sizes.max(initial=0))):
        open_ = int(np.searchsorted(longer, -t, "left"))  # meetings of more than t utterances come first
        h = recurrent_step(flat[at[:open_] + t], h[:open_], w)
        out[at[:open_] + t] = h
    return np.split(out, starts[1:-1])


def decoded(h: np.ndarray, coverage: float = 0.0):
    """(attention, context, state) of each of a few decoding steps over the states; earlier attention lowers a score by `coverage`."""
    w = {k: seeded(f"decoder {k}") for k in ("xz", "hz", "xr", "hr", "xh", "hh")}
    s, seen, keys, query, score = h[-1], np.zeros(len(h)), h @ seeded("key"), seeded("query"), layer("score")
    for _ in range(STEPS):
        a = softmax(np.tanh(s @ query + keys) @ score)  # baselines.additive_attention, with the keys' part computed once
        if coverage:
            a = softmax(np.log(a + 1e-12) - coverage * len(h) * seen)
        c = a @ h
        s, seen = recurrent_step(c, s, w), seen + a
        yield a, c, s


def places(items: Items) -> np.ndarray:
    """What all networks see of an utterance: bias, length, place from the start, and share of the meeting before it."""
    n = len(items.items)
    at = np.arange(n)
    return np.column_stack([np.ones(n), np.log1p(items.length), np.log1p(at) / 8, at / max(1, n - 1)])


def attention(items: list[Counter] | Items, speakers: list) -> np.ndarray:
    """Attention that a decoder pays to an utterance, mean and greatest, and its likeness to the last decoder state."""
    items = items_of(items)
    x, h = items.embedded, items.states
    steps = list(decoded(h))
    a = np.array([s[0] for s in steps]) * len(h)
    return np.column_stack([places(items), a.mean(0), a.max(0), h @ steps[-1][2], x @ steps[-1][2]])


def pointer(items: list[Counter] | Items, speakers: list) -> np.ndarray:
    """Attention under coverage, and the mean log probability of an utterance's words when generation by the meeting's word frequencies is mixed with copying."""
    items = items_of(items)
    h, total, share = items.states, items.total, items.n / np.maximum(items.length, 1)[items.item]
    out, seen, again = np.zeros(len(items.words)), np.zeros(len(h)), np.zeros(len(h))
    for a, c, s in decoded(h, coverage=1.0):
        generate = float(sigmoid(c @ layer("generate context") + s @ layer("generate state")))
        out += ((1 - generate) * np.bincount(items.word, a[items.item] * share, len(out)) + generate * total / max(1, total.sum())) / STEPS
        again, seen = again + np.minimum(a, seen), seen + a
    gain = np.where(items.length > 0, items.summed(items.n * np.log(out)[items.word]) / np.maximum(items.length, 1), -20.0)
    return np.column_stack([places(items), seen * len(h), again * len(h), gain])


def gated(items: list[Counter] | Items, speakers: list) -> np.ndarray:
    """A gate an utterance, from its own state and the meeting's, that scales the state; its mean, the scaled state's norm, and likenesses."""
    items = items_of(items)
    x, h = items.embedded, items.states
    gate = sigmoid(h @ seeded("gate state") + h[-1] @ seeded("gate meeting"))
    g = gate * h
    return np.column_stack([places(items), gate.mean(1), np.linalg.norm(g, axis=1), g @ h[-1], x @ g.mean(0)])


def pooled(rows: np.ndarray, name: str) -> tuple[np.ndarray, np.ndarray]:
    """(weights, mean): attention of a fixed query over rows."""
    weights = softmax(np.tanh(rows @ seeded(f"{name} pool")) @ layer(f"{name} query"))
    return weights, weights @ rows


def hierarchical(items: list[Counter] | Items, speakers: list) -> np.ndarray:
    """Words are pooled into a turn, to which a vector of the speaker's role is added, and turns into the meeting."""
    items = items_of(items)
    roles = np.array([[float(s == r) for r in ROLES] for s in speakers])
    # pooled() of each utterance's word vectors, all utterances at once
    score = (np.tanh(items.vectors @ seeded("word pool")) @ layer("word query"))[items.word]
    top, some = np.zeros(len(items.items)), items.sizes > 0
    if some.any():
        top[some] = np.maximum.reduceat(score, items.at[:-1][some])
    e = np.exp(score - top[items.item])
    turns = items.rows_summed(items.vectors[items.word] * (e / items.summed(e)[items.item])[:, None]) + roles @ seeded("roles", len(ROLES))
    weights, meeting = pooled(turns, "turn")
    return np.column_stack([places(items), roles, weights * len(turns), turns @ meeting])


def relations(speakers: list) -> dict[str, list[tuple[int, int]]]:
    """Edges by type: to the next turn, to the speaker's own next turn, and to the next turn of another speaker."""
    out, last = {"next": [], "same": [], "reply": []}, {}
    for i, s in enumerate(speakers):
        if i:
            out["next"].append((i - 1, i))
            if speakers[i - 1] != s:
                out["reply"].append((i - 1, i))
        if s in last:
            out["same"].append((last[s], i))
        last[s] = i
    return out


def graph(items: list[Counter] | Items, speakers: list) -> np.ndarray:
    """One convolution over typed edges: own vector and, of each relation, the mean of the neighbours' vectors under its own weights."""
    items = items_of(items)
    x = items.embedded
    out = x @ seeded("self")
    for name, pairs in relations(speakers).items():
        total, degree = np.zeros_like(x), np.zeros(len(x))
        if pairs:
            a, b = np.array(pairs).T
            for i, j in ((a, b), (b, a)):
                np.add.at(total, i, x[j])
                np.add.at(degree, i, 1)
        out = out + total / np.maximum(degree, 1)[:, None] @ seeded(f"relation {name}")
    h = np.maximum(out, 0)
    return np.column_stack([places(items), np.linalg.norm(h, axis=1), h @ h.mean(0), x @ x.mean(0)])


NETWORKS = {"attention": attention, "pointer": pointer, "gated": gated, "hierarchical": hierarchical, "graph": graph}


def taught(items: list[Counter] | Items, labels: set[int]) -> np.ndarray:
    """Features of the sequential keep/drop rule, with the labelled utterances before each as the summary so far."""
    items = items_of(items)
    out, have, at = runner_features(items), np.zeros(len(items.words)), items.at
    for i, end in zip(taken := sorted(labels), [*taken[1:], len(items.items) - 1]):
        mine, then = slice(at[i], at[i + 1]), slice(at[i + 1], at[end + 1])  # the summary stays as it is up to the next labelled one
        have[items.word[mine]] += items.n[mine]
        dot = np.bincount(items.item[then] - i - 1, items.n[then] * have[items.word[then]], end - i)
        out[i + 1:end + 1, 3] -= ratios(dot, items.squares[i + 1:end + 1], have @ have)
    return out


def batched(records: Iterator, most: int = 20_000) -> Iterator[list]:
    """[(record, Items)] of meetings of some ten thousand utterances together, with their recurrent states."""
    open_, size = [], 0
    for r in records:
        open_.append((r, Items([Counter(t.split()) for t in r.line])))
        size += len(r.line)
        if size >= most:
            yield with_states(open_)
            open_, size = [], 0
    if open_:
        yield with_states(open_)


def with_states(group: list) -> list:
    for (_, items), h in zip(group, states_together([items.embedded for _, items in group])):
        items.states = h
    return group


def labelled(utts: DataFrame, gold: DataFrame, most: int = 10) -> DataFrame:
    """(meeting_id, block, sums): of each meeting the features of the sequential rule and y as a block of train.adamw(), and the normal
    equations of all networks, one after the other; y = 1 for the utterances that a greedy choice by unigram F1 takes."""
    positive(most=most)
    rows = lines_of(utts).join(reference_texts(gold).select("meeting_id", words(F.col("text")).alias("reference")), "meeting_id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for group in batched(batch.itertuples(index=False)):
                out = []
                for r, items in group:
                    labels, speakers = greedy_labels(items, Counter(r.reference), most), list(r.speaker)
                    y = np.zeros(len(speakers))
                    y[list(labels)] = 1
                    sums = [train.equations(net(items, speakers), y) for net in NETWORKS.values()]
                    out.append((r.meeting_id, train.block_of(taught(items, labels), y), np.concatenate(sums).tolist()))
                yield pd.DataFrame(out, columns=["meeting_id", "block", "sums"])

    return rows.mapInPandas(run, "meeting_id string, block binary, sums array<double>")


def fitted(utts: DataFrame, gold: DataFrame, most: int = 10) -> dict[str, list[float]]:
    """{name: read-out} of `runner` (logistic) and of each network (least squares), from the training meetings; ValueError if there are none."""
    names = split.assign(utts).where("split = 'train'").select("meeting_id")
    rows = labelled(utts.join(names, "meeting_id", "left_semi"), gold, most)
    rows = cut(rows)  # a table: a plan with all that is behind it, in each of 40 passes, fills the driver
    sums, at, out = train.summed(rows, "sums"), 0, {}
    if not len(sums):
        raise ValueError("no training meetings")
    for name, net in NETWORKS.items():
        width = net([Counter()], ["PM"]).shape[1]
        out[name] = train.solved(sums[at:at + width * (width + 1)])
        at += width * (width + 1)
    out["runner"] = train.adamw(rows, 0.3, 20, steps_per_epoch=2, width=len(RUNNER_WEIGHTS))[-1][1]
    return out


def picked(utts: DataFrame, read_outs: dict[str, list[float]], q: int = 10) -> DataFrame:
    """(run, meeting_id, utt_no, place, score): each network's q best utterances in source order; ties to earlier ones. Meetings pass once for all networks."""
    positive(q=q)
    weights = {name: np.array(read_outs[name]) for name in NETWORKS}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for group in batched(batch.itertuples(index=False)):
                out = []
                for r, items in group:
                    speakers = list(r.speaker)
                    for name, net in NETWORKS.items():
                        scores = [round(s, 9) for s in (net(items, speakers) @ weights[name]).tolist()]
                        out += [(name, r.meeting_id, int(r.utt_no[i]), place, scores[i]) for place, i in enumerate(best_in_order(scores, q))]
                yield pd.DataFrame(out, columns=["run", "meeting_id", "utt_no", "place", "score"])

    return lines_of(utts).mapInPandas(run, "run string, meeting_id string, utt_no long, place long, score double")
