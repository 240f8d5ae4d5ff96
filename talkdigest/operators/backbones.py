"""Generators that turn a window into a snippet and the last utterance that supports it."""

from __future__ import annotations

import math
import zlib
from collections import Counter
from copy import copy

import numpy as np

from .boundary import WORD
from .windows import View


class Backbone:
    """generate(view) -> (snippet, boundary place or None or text). Instances are small and travel by pickling."""

    name = "backbone"

    def generate(self, view: View):
        raise NotImplementedError

    def of(self, meeting) -> Backbone:
        """This backbone for the windows of one meeting, with what they share; itself if they share nothing."""
        return self

    def spec(self) -> dict:
        return {"kind": type(self).__name__, **self.__dict__}


class LeadBackbone(Backbone):
    """The first q utterances; the last of them is the boundary."""

    name = "lead"

    def __init__(self, q: int = 20):
        self.q = q

    def generate(self, view: View):
        b = min(view.left + self.q - 1, view.hi)
        return " ".join(view.texts[view.left:b + 1]), b


class TextBoundary(Backbone):
    """Another backbone whose boundary is given as the utterance's text, as a generator's output has it; the run locates it."""

    name = "text"

    def __init__(self, inner: Backbone):
        self.inner = inner

    def generate(self, view: View):
        snippet, b = self.inner.generate(view)
        return snippet, view.texts[b]


class RandomBackbone(Backbone):
    """q utterances by a hash of their numbers, in order; a baseline. The whole window counts as used."""

    name = "random"

    def __init__(self, q: int = 20, seed: int = 0):
        self.q, self.seed = q, seed

    def generate(self, view: View):
        places = range(view.left, view.hi + 1)
        pick = sorted(sorted(places, key=lambda i: ((int(view.utt_nos[i]) * 7919 + self.seed) % 104729, i))[:self.q])
        return " ".join(view.texts[i] for i in pick), view.hi


class GoldBackbone(Backbone):
    """The true snippet and boundary of the segment that starts at or after the window's left edge.

    segments: {meeting: [(start, end, text)]} of the meetings at hand: for tests and bounded evaluation sets."""

    name = "gold"

    def __init__(self, segments: dict):
        self.segments = segments

    def generate(self, view: View):
        for start, end, text in self.segments.get(view.meeting_id, ()):
            if end >= view.left:
                return text, end
        return "", view.hi


def bags(texts: list[str]) -> list[Counter]:
    return [Counter(WORD.findall((t or "").lower())) for t in texts]


def cosine(a: Counter, b: Counter) -> float:
    dot = sum(n * b[w] for w, n in a.items())
    return dot / math.sqrt(sum(n * n for n in a.values()) * sum(n * n for n in b.values())) if dot else 0.0


def gap_scores(items: list[Counter], block: int) -> np.ndarray:
    """Similarity of the `block` utterances before and after each inner gap, from running counts of both sides.

    The counts, their squares and their product change word by word as the gap moves on, so a word is touched four times in all."""
    n = len(items)
    out = np.zeros(max(0, n - 1))
    left, right = Counter(), Counter()
    dot = aa = bb = 0

    def into_left(x, sign):
        nonlocal dot, aa
        for w, c in x.items():
            c, had = sign * c, left[w]
            aa += c * (2 * had + c)
            dot += c * right[w]
            left[w] = had + c

    def into_right(x, sign):
        nonlocal dot, bb
        for w, c in x.items():
            c, had = sign * c, right[w]
            bb += c * (2 * had + c)
            dot += c * left[w]
            right[w] = had + c

    for x in items[:block]:
        into_right(x, 1)
    for g in range(n - 1):
        into_right(items[g], -1)
        into_left(items[g], 1)
        if g + block < n:
            into_right(items[g + block], 1)
        if g >= block:
            into_left(items[g - block], -1)
        out[g] = dot / math.sqrt(aa * bb) if dot else 0.0
    return out


def depths(scores: np.ndarray) -> np.ndarray:
    """How far each gap lies below the nearest peaks on both sides."""
    def peaks(values: list[float]) -> list[float]:
        """What a climb backwards from each place reaches: the climb of the place before goes on, unless that lies lower."""
        out: list[float] = []
        for g, s in enumerate(values):
            out.append(out[-1] if g and values[g - 1] >= s else s)
        return out

    values = np.asarray(scores, float).tolist()
    return np.array([a - s + b - s for a, s, b in zip(peaks(values), values, peaks(values[::-1])[::-1])])


def salience(items: list[Counter], weights: dict | None = None) -> list[float]:
    """Summed tf-idf of an utterance over the root of its length; idf from the window itself unless weights are given."""
    if weights is None:
        df = Counter(w for x in items for w in x)
        weights = {w: math.log(1 + len(items) / n) for w, n in df.items()}
    return [sum(n * weights.get(w, 0.0) for w, n in x.items()) / math.sqrt(max(1, sum(x.values()))) for x in items]


def best_in_order(scores: list[float], q: int) -> list[int]:
    return sorted(sorted(range(len(scores)), key=lambda i: (-scores[i], i))[:q])


class Sliding:
    """A meeting's word counts with what its windows share: similarities at gaps, also those that an edge of a window cuts, and where a
    word stood before."""

    def __init__(self, items: list[Counter], speakers: list, block: int = 8):
        self.items, self.block, last, before, index = items, block, {}, [], {}
        for i, x in enumerate(items):
            before += [last.get(w, -1) for w in x]
            last.update(dict.fromkeys(x, i))
        self.before, self.n = np.array(before, np.int64), np.array([c for x in items for c in x.values()], np.int64)
        lengths = np.array([len(x) for x in items], np.int64)
        self.at = np.r_[0, np.cumsum(lengths)]
        sizes = [sum(x.values()) for x in items]
        self.sizes, self.logs = np.array(sizes, np.int64), np.array([math.log1p(s) for s in sizes])
        self.place_logs = np.array([math.log1p(i) for i in range(len(items))])
        self.changes = np.array([float(a != b) for a, b in zip(speakers, speakers[1:])])
        word = np.array([index.setdefault(w, len(index)) for x in items for w in x], np.int64)
        self.before_edge, self.after_edge = self._cut_scores(word, np.repeat(np.arange(len(items)), lengths))

    def _cut_scores(self, word: np.ndarray, item: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Similarities at each gap of the a = 1..block utterances before and `block` after it, and of `block` before and b = 1..block after.

        Blocks' products are sums of products of two utterances, which lie less than two blocks apart: dot[i, d] of i and i + d. Counts
        are whole numbers, so the sums are exact in any order."""
        size, lags, many = self.block, 2 * self.block, len(self.items)
        order = np.lexsort((item, word))
        word, item, n = word[order], item[order], self.n[order].astype(float)
        dot = np.zeros((many + 2 * lags, lags))  # padded with empty utterances on both sides
        dot[lags:lags + many, 0] = np.bincount(item, n * n, many)
        for s in range(1, lags):  # a word stands in at most so many of the next utterances
            d = item[s:] - item[:-s]
            near = (word[s:] == word[:-s]) & (d < lags)
            dot[lags:lags + many] += np.bincount(item[:-s][near] * lags + d[near], (n[s:] * n[:-s])[near], many * lags).reshape(many, lags)
        reached = np.c_[np.zeros(len(dot)), np.cumsum(dot[:, 1:], axis=1)]  # [i, m]: products of i with the next m

        def rows(shift: int, m: int) -> np.ndarray:
            """reached[i + shift, m] for all i."""
            return reached[lags + shift:lags + shift + many, m]

        own = lambda shift: dot[lags + shift:lags + shift + many, 0]
        aa, bb, cross_a, cross_b = np.zeros((size, many)), np.zeros((size, many)), np.zeros((size, many)), np.zeros((size, many))
        for k in range(size):
            aa[k] = aa[k - 1] + own(-k) + 2 * rows(-k, k) if k else own(0)
            cross_a[k] = (cross_a[k - 1] if k else 0) + rows(-k, k + size) - rows(-k, k)
            inner = sum(dot[lags + 1 + k - d:lags + 1 + k - d + many, d] for d in range(1, k + 1))
            bb[k] = (bb[k - 1] if k else 0) + own(1 + k) + 2 * inner
            for b in range(size):
                cross_b[b] += rows(-k, k + b + 1) - rows(-k, k)
        ratio = lambda x, y: np.divide(x, np.sqrt(y), out=np.zeros(x.shape), where=x != 0)
        return ratio(cross_a, aa * bb[-1]), ratio(cross_b, aa[-1] * bb)

    def scores(self, left: int, hi: int) -> np.ndarray:
        """gap_scores() of the utterances left..hi; only short windows are counted anew, as both edges cut their gaps."""
        near = self.block
        if hi - left <= 2 * near:
            return gap_scores(self.items[left:hi + 1], near)
        to = np.arange(near)
        return np.concatenate([self.before_edge[to, left + to], self.before_edge[-1, left + near:hi - near], self.after_edge[to, hi - 1 - to][::-1]])

    def features(self, left: int, hi: int) -> np.ndarray:
        """Of each utterance in left..hi: place in the window, cohesion at its right gap and depth there, share of new words in the next one, change of speaker, length, distance."""
        n, scores = hi - left + 1, self.scores(left, hi)
        out = np.zeros((n, 8))
        out[:, 0], out[:, 1], out[:, 6], out[:, 7] = 1.0, np.arange(n) / max(1, n - 1), self.logs[left:hi + 1], self.place_logs[:n]
        out[:-1, 2], out[:-1, 3], out[:-1, 5], out[-1, 4] = scores, depths(scores), self.changes[left:hi], 1.0
        lo, to = self.at[left + 1], self.at[hi + 1]
        fresh = np.r_[0, np.cumsum(np.where(self.before[lo:to] < left, self.n[lo:to], 0))][self.at[left + 1:hi + 2] - lo]
        out[:-1, 4] = np.diff(fresh) / np.maximum(1, self.sizes[left + 1:hi + 1])
        return out

    def salient(self, left: int, cut: int, q: int) -> list[int]:
        """The q most salient of the utterances left..left + cut, in order."""
        return [left + i for i in best_in_order(salience(self.items[left:left + cut + 1]), q)]


class SlidingBackbone(Backbone):
    """A boundary from what a meeting's windows share; snippet of the q most salient utterances before it."""

    sliding: Sliding | None = None

    def of(self, meeting) -> Backbone:
        return self.over(Sliding(bags(meeting.text), meeting.speaker, self.block))

    def over(self, sliding: Sliding) -> Backbone:
        one = copy(self)
        one.sliding = sliding
        return one

    def cut(self, sliding: Sliding, left: int, hi: int) -> int:
        """The boundary, counted from left."""
        raise NotImplementedError

    def chosen(self, view: View) -> tuple[list[int], int]:
        """Places of the snippet's utterances, and the boundary."""
        sliding, at = self.sliding, 0
        if sliding is None:
            sliding, at = Sliding(bags(view.texts[view.left:view.hi + 1]), view.speakers[view.left:view.hi + 1], self.block), view.left
        cut = self.cut(sliding, view.left - at, view.hi - at)
        return [at + i for i in sliding.salient(view.left - at, cut, self.q)], view.left + cut

    def generate(self, view: View):
        places, b = self.chosen(view)
        return " ".join(view.texts[i] for i in places), b


class CohesionBackbone(SlidingBackbone):
    """Boundary at the deepest fall of lexical similarity; snippet of the q most salient utterances before it."""

    name = "cohesion"

    def __init__(self, block: int = 8, q: int = 8, least: int = 4):
        self.block, self.q, self.least = block, q, least

    def cut(self, sliding: Sliding, left: int, hi: int) -> int:
        found = depths(sliding.scores(left, hi))[self.least:]
        return int(found.argmax()) + self.least if len(found) and found.max() > 0 else hi - left


def features(items: list[Counter], speakers: list, block: int = 8) -> np.ndarray:
    """Sliding.features() of all items."""
    return Sliding(items, speakers, block).features(0, len(items) - 1)


class LearnedBackbone(SlidingBackbone):
    """Boundary at the best logistic score of an utterance; snippet of the q most salient utterances before it."""

    name = "learned"

    def __init__(self, coefs: list[float], block: int = 8, q: int = 8):
        self.coefs, self.block, self.q = list(coefs), block, q

    def cut(self, sliding: Sliding, left: int, hi: int) -> int:
        return int((sliding.features(left, hi) @ np.array(self.coefs)).argmax())


class StrideBackbone(Backbone):
    """Another backbone's snippet, with the boundary from a predicted stride in tokens (a function of window features)."""

    name = "stride"

    def __init__(self, inner: Backbone, coefs: list[float]):
        self.inner, self.coefs = inner, list(coefs)

    def generate(self, view: View):
        snippet, _ = self.inner.generate(view)
        j = float(np.dot(self.coefs, window_features(view)))
        ends = np.cumsum(view.n_tok[view.left:view.hi + 1])
        j = min(max(j, 1.0), float(view.k - 1))
        return snippet, view.left + max(0, int(np.searchsorted(ends, j, "right")) - 1)


def window_features(view: View) -> np.ndarray:
    """Bias, tokens over k, utterances over k, first and last similarity, place of the deepest gap in tokens over k."""
    items = bags(view.texts[view.left:view.hi + 1])
    scores = gap_scores(items, 8)
    deep = depths(scores)
    ends = np.cumsum(view.n_tok[view.left:view.hi + 1])
    at = float(ends[int(deep.argmax())]) if len(deep) else float(ends[-1])
    total = float(ends[-1])
    return np.array([1.0, total / view.k, len(items) / view.k, scores[0] if len(scores) else 0.0, scores[-1] if len(scores) else 0.0, at / view.k]) * view.k


class IndicatorBackbone(Backbone):
    """Scans the window and moves on while a rule says so: the boundary is the first utterance with enough words that no earlier one has."""

    name = "indicator"

    def __init__(self, most: float = 0.5, least: int = 4, q: int = 8):
        self.most, self.least, self.q = most, least, q

    def generate(self, view: View):
        items, seen, cut = bags(view.texts[view.left:view.hi + 1]), set(), None
        for i, x in enumerate(items):
            fresh = len(x.keys() - seen) / max(1, len(x))
            seen |= x.keys()
            if i >= self.least and fresh > self.most:
                cut = i - 1
                break
        cut = len(items) - 1 if cut is None else cut
        return " ".join(view.texts[view.left + i] for i in best_in_order(salience(items[:cut + 1]), self.q)), view.left + cut


class PolicyBackbone(Backbone):
    """Another backbone's snippet, with a stride drawn from a softmax over shares of k; the draw follows from a hash, so reruns agree."""

    name = "policy"

    def __init__(self, inner: Backbone, logits: list[float], actions=(0.25, 0.5, 0.75, 1.0), seed: int = 0, greedy: bool = False):
        self.inner, self.logits, self.actions, self.seed, self.greedy = inner, list(logits), tuple(actions), seed, greedy

    def probabilities(self) -> np.ndarray:
        e = np.exp(np.array(self.logits) - max(self.logits))
        return e / e.sum()

    def action(self, meeting_id: str, left: int) -> int:
        p = self.probabilities()
        if self.greedy:
            return int(p.argmax())
        h = 0
        for c in f"{self.seed}:{meeting_id}:{left}":
            h = (h * 1000003 + ord(c)) % 2147483647
        return int(np.searchsorted(np.cumsum(p), (h % 1000003) / 1000003, "right").clip(0, len(p) - 1))

    def generate(self, view: View):
        j = self.actions[self.action(view.meeting_id, view.left)] * view.k
        ends = np.cumsum(view.n_tok[view.left:view.hi + 1])
        cut = max(0, int(np.searchsorted(ends, j, "right")) - 1)
        inner = View(view.meeting_id, view.utt_nos, view.speakers, view.texts, view.n_tok, view.left, view.left + cut, view.k)
        return self.inner.generate(inner)[0], view.left + cut


class Seq2SeqBackbone(Backbone):
    """The encoder-decoder itself: a window's words are encoded, and decoding writes a snippet, the separator and the last supporting
    utterance, which the run then looks up by its text.

    Words are hashed to the model's vocabulary. A step scores the distinct words of the window (an output points at what was read;
    a word is written once), and the snippet ends after q words or when the end token scores best. The supporting utterance is the
    one whose words the decoder, after the separator, scores highest on average. Weights are seeded or given."""

    name = "seq2seq"

    def __init__(self, model, q: int = 12, sep: str = "[SEP]"):
        self.model, self.q, self.sep = model, q, sep

    def ids(self, words: list[str]) -> list[int]:
        return [2 + zlib.crc32(w.encode()) % (self.model.vocabulary - 2) for w in words]

    def written(self, view: View) -> str:
        """What the decoder writes of a window."""
        utterances = [WORD.findall((t or "").lower()) for t in view.texts[view.left:view.hi + 1]]
        words = [w for u in utterances for w in u]
        if not words:
            return f"{self.sep} {view.texts[view.hi] or ''}"
        encoded = np.vstack([self.model.encode(self.ids(words[i:i + view.k])) for i in range(0, len(words), view.k)])
        open_ = list(dict.fromkeys(words))
        places, reader, snippet = self.ids(open_), self.model.reader(encoded), []
        logits = reader.logits(0)
        while open_ and len(snippet) < self.q:
            scores = logits[places]
            best = int(scores.argmax())
            if snippet and logits[1] > scores[best]:
                break
            snippet.append(open_.pop(best))
            logits = reader.logits(places.pop(best))
        logits = reader.logits(1)
        means = [float(logits[self.ids(u)].mean()) if u else -math.inf for u in utterances]
        return f"{' '.join(snippet)} {self.sep} {view.texts[view.left + int(np.argmax(means))]}"

    def generate(self, view: View):
        snippet, _, support = self.written(view).partition(f"{self.sep} ")
        return snippet.rstrip(), support
