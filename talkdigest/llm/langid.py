"""Language identification by string kernels.

The blended-spectrum presence kernel counts the n-grams (n = 1..ORDER, of lower-cased code points) that two texts
share, each once, and is normalised to 1 on the diagonal. A bounded sample of labelled rows gives the Nystroem
landmarks and the rows that one-versus-rest kernel ridge regression is fitted on. As scoring is linear in the
kernel against the landmarks, and that kernel in the presence vector, the learned weights fold into one matrix
(n-grams x languages): a batch of texts is scored by one matrix product of its presence rows.

The space of n-grams is that of all n-grams of the landmarks, of whatever script; whole texts are read.

Fit bounds (parameters): per_lang rows a language, landmarks in all, both drawn by the least hashes of texts of at
most fit_chars code points. Prediction has no bound.

Defined results: null text or one without a letter is `und` with score 0; ties go to the language that sorts first, so
does, with score 0, a text that shares no n-gram with the landmarks; no usable training row: everything is `und`;
repeated rows are predicted alike; an empty table gives no rows; further columns, of whatever name, are ignored by
identified() and kept by accepted().
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import small_or_plain

ORDER = 3
BATCH = 64
CELLS = 1 << 22  # of a batch's presence rows
SPARE = 8
LETTER = regex.compile(r"\p{L}")
SPREAD = np.uint64(0x9E3779B97F4A7C15)


class Columns:
    """Column of each known packed n-gram: an open hash table over arrays, asked for many at once."""

    def __init__(self, known: np.ndarray):
        bits = max(4, (4 * len(known)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.place = np.full(1 << bits, -1, np.int64), np.zeros(1 << bits, np.int32)
        left, slot = np.arange(len(known)), self._slot(known)
        while len(left):
            free = np.flatnonzero(self.keys[slot] < 0)
            _, first = np.unique(slot[free], return_index=True)
            won = free[first]
            self.keys[slot[won]], self.place[slot[won]] = known[left[won]], left[won]
            rest = np.ones(len(left), bool)
            rest[won] = False
            left, slot = left[rest], slot[rest] + 1 & self.mask

    def _slot(self, packed: np.ndarray) -> np.ndarray:
        return (packed.view(np.uint64) * SPREAD >> self.shift).astype(np.int64)

    def of(self, packed: np.ndarray) -> np.ndarray:
        """Columns of those that are known."""
        out, slot = [], self._slot(packed)
        while len(packed):
            there = self.keys[slot]
            hit = there == packed
            out.append(self.place[slot[hit]])
            on = ~hit & (there >= 0)
            packed, slot = packed[on], slot[on] + 1 & self.mask
        return np.concatenate(out) if out else np.empty(0, np.int32)


@dataclass
class Model:
    langs: list[str]
    chars: np.ndarray  # code point -> place in the alphabet of the landmarks, 0 for others
    base: int
    known: Columns
    weights: np.ndarray  # columns x languages

    @property
    def columns(self) -> int:
        return len(self.weights)


def points(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "replace"), np.uint32)


def grams(text: str, chars: np.ndarray, base: int) -> np.ndarray:
    """Packed n-grams (n = 1..ORDER) without those that hold a character that the alphabet lacks; n-grams of different
    lengths are different numbers, as places start at 1."""
    code = chars[np.minimum(points(text), len(chars) - 1)].astype(np.int64)
    packed, known, out = code, code > 0, [code[code > 0]]
    for n in range(2, ORDER + 1):
        if len(code) < n:
            break
        packed, known = packed[:-1] * base + code[n - 1:], known[:-1] & (code[n - 1:] > 0)
        out.append(packed[known])
    return np.concatenate(out)


def found(text: str, model: Model) -> np.ndarray:
    """Distinct columns of a text."""
    return np.unique(model.known.of(grams(text, model.chars, model.base)))


def presence(texts: list[str], model: Model) -> np.ndarray:
    out = np.zeros((len(texts), model.columns), np.float32)
    for row, text in zip(out, texts):
        row[model.known.of(grams(text, model.chars, model.base))] = 1
    return out


def kernel(rows: list[np.ndarray], marks: list[np.ndarray], columns: int, width: int = 1 << 14) -> np.ndarray:
    """Normalised kernel of rows against marks, both as sorted columns; by products of blocks of columns."""
    def block(sets, at):
        out = np.zeros((len(sets), width), np.float32)
        for row, s in zip(out, sets):
            row[s[np.searchsorted(s, at):np.searchsorted(s, at + width)] - at] = 1
        return out

    shared = np.zeros((len(rows), len(marks)))
    for at in range(0, columns, width):
        shared += block(rows, at) @ block(marks, at).T
    size = lambda sets: np.sqrt(np.maximum([len(s) for s in sets], 1))
    return shared / size(rows)[:, None] / size(marks)[None, :]


def fit(rows: list[tuple[str, str]], landmarks: int = 128, ridge: float = 1e-2) -> Model | None:
    """rows: (text, lang), in a fixed order."""
    rows = [(t, l) for t, l in rows if t and LETTER.search(t)]
    if not rows:
        return None
    langs = sorted({l for _, l in rows})
    per = max(1, landmarks // len(langs))
    marks = [t for lang in langs for t in [t for t, l in rows if l == lang][:per]]
    alphabet = np.unique(np.concatenate([points(t) for t in marks]))
    chars = np.zeros(int(alphabet.max()) + 2, np.int32)
    chars[alphabet] = np.arange(1, len(alphabet) + 1)
    base = len(alphabet) + 1
    known = np.unique(np.concatenate([grams(t, chars, base) for t in marks]))
    model = Model(langs, chars, base, Columns(known), np.zeros((len(known), len(langs)), np.float32))
    mark_sets = [found(t, model) for t in marks]
    values, vectors = np.linalg.eigh(kernel(mark_sets, mark_sets, len(known)))
    good = values > 1e-6 * values.max()
    whiten = vectors[:, good] / np.sqrt(values[good])
    mapped = np.vstack([kernel([found(t, model) for t, _ in rows[i:i + BATCH]], mark_sets, len(known)) for i in range(0, len(rows), BATCH)]) @ whiten
    goal = np.array([[float(l == lang) for lang in langs] for _, l in rows])
    solved = np.linalg.solve(mapped.T @ mapped + ridge * len(rows) / len(langs) * np.eye(mapped.shape[1]) * 1e-2, mapped.T @ goal)
    for columns, weight in zip(mark_sets, whiten @ solved):
        model.weights[columns] += (weight / np.sqrt(max(1, len(columns)))).astype(np.float32)
    return model


def _unit(rows: np.ndarray) -> np.ndarray:
    return rows / np.sqrt(np.maximum(rows.sum(1, keepdims=True), 1))


def predict(texts: list[str | None], model: Model | None) -> tuple[list[str], list[float]]:
    langs, scores = ["und"] * len(texts), [0.0] * len(texts)
    usable = [i for i, t in enumerate(texts) if model and t and LETTER.search(t)]
    size = max(1, min(BATCH, CELLS // max(1, model.columns))) if model else 1
    for at in range(0, len(usable), size):
        part = usable[at:at + size]
        for i, row in zip(part, _unit(presence([texts[i] for i in part], model)) @ model.weights):
            k = int(row.argmax())
            langs[i], scores[i] = model.langs[k], float(min(1.0, max(0.0, row[k])))
    return langs, scores


def sample(labelled: DataFrame, per_lang: int = 400, fit_chars: int = 20_000) -> list[tuple[str, str]]:
    """At most per_lang (text, lang) of each language: those with the least hashes of row and text.

    Rows are first thinned to about SPARE * per_lang a language by the hash, at rates from the languages' counts, so what is
    ranked does not grow with the input. Languages are few (a broadcast is checked); with all, fewer than per_lang are left
    only where a language has fewer."""
    labelled = labelled.where("lang is not null and text is not null")
    rows = labelled.where(F.length("text") <= fit_chars).select("text", "lang", F.xxhash64("text", "doc_id").alias("drawn"))
    counts = labelled.groupBy(F.col("lang").alias("of_lang")).agg(F.count("*").alias("lang_rows"))
    rows = rows.join(small_or_plain(counts, 100_000), F.col("lang") == F.col("of_lang"))
    rows = rows.where(F.pmod("drawn", F.lit(1 << 30)) <= F.least(F.lit(1.0), F.lit(float(SPARE * per_lang)) / F.col("lang_rows")) * float(1 << 30))
    least = Window.partitionBy("lang").orderBy(F.pmod("drawn", F.lit(1 << 30)), "drawn", "text")
    rows = rows.withColumn("nth", F.row_number().over(least)).where(F.col("nth") <= per_lang).select("text", "lang", "nth")
    return [(r.text, r.lang) for r in sorted(rows.collect(), key=lambda r: (r.lang, r.nth))]


def held_out(doc_id) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(3)) == 1


def trained(documents: DataFrame, per_lang: int = 400) -> Model | None:
    return fit(sample(documents.where(~held_out(F.col("doc_id"))).select("doc_id", "text", "lang"), per_lang))


def identified(documents: DataFrame, model: Model | None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score), one row a document."""
    holder = documents.sparkSession.sparkContext.broadcast(model)  # at most the n-grams of the landmarks
    rows = documents.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, BATCH):
                part = batch.slice(i, BATCH)
                langs, scores = predict(part.column(2).to_pylist(), holder.value)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return rows.mapInArrow(score, f"doc_id {dict(rows.dtypes)['doc_id']}, held_out boolean, lang_pred string, score double")


def accepted(documents: DataFrame, model: Model | None, least: float = 0.2) -> DataFrame:
    """The rows of documents that get a language with a score of at least `least`, all columns kept.

    Only texts go to Python, and only a flag comes back; the rows wait in the JVM."""
    holder = documents.sparkSession.sparkContext.broadcast(model)

    def told(texts: pa.Array) -> pa.Array:
        out = []
        for i in range(0, len(texts), BATCH):
            langs, scores = predict(texts.slice(i, BATCH).to_pylist(), holder.value)
            out += [l != "und" and s >= least for l, s in zip(langs, scores)]
        return pa.array(out, pa.bool_())

    told.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return documents.where(F.arrow_udf(told, "boolean")(F.col("text")))
