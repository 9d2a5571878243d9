"""Toxic documents by multiple-instance learning over sentences (operator 6).

A document is a bag of sentences. A sentence's probability is logistic in its words and their
beginnings, since inflected and compounded words share one; the document's is the noisy-or of its sentences and of a leak that stands for labels without
a visible cause. Only document labels are used to fit; the fitted sentence model then
locates the offending sentences.

Fitting takes at most MAX_LABELLED labelled documents (those with the smallest hash of
their id) and, of these in that order, at most MAX_CHARS characters of whole texts: bounds that make
their join a broadcast and their sentences fit the driver. Words come from counts over all
of these. Rows that share an id are fitted by the least of their texts. Scoring is one pass over whole texts.

A null or empty text has the leak's score and no sentences. Documents with several labels
count as toxic if any says so; labels that are null, or of unknown documents, are left out.
With no usable labels every score is about 0.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize
from termatlas.llm.tables import bounded_batches

MAX_LABELLED, MAX_CHARS, MAX_WORDS, LEAST_DOCS, LEAST_GAIN = 20_000, 48_000_000, 2_048, 3, 10.0
PREFIXES = range(4, 10)
SENTENCE, WORDS = re.compile(r"[^.!?\n]+[.!?]*"), re.compile(r"[^\W\d_]+").findall


def features(word: str) -> list[str]:
    """The word and its proper beginnings, marked as such."""
    return [word, *("^" + word[:k] for k in PREFIXES if k < len(word))]


class _Sums(dict):
    """Word -> sum of its features' weights, kept while small."""

    def __init__(self, weights: dict[str, float]):
        super().__init__()
        self.weights = weights

    def __missing__(self, word: str) -> float:
        if len(self) > 100_000:
            self.clear()
        z = sum(self.weights.get(f, 0.0) for f in features(word))
        if len(word) < 60:
            self[word] = z
        return z


@dataclass
class Model:
    bias: float = -20.0
    leak: float = 0.0
    weights: dict[str, float] = field(default_factory=dict)

    def chance(self, z: float) -> float:
        return 1 / (1 + math.exp(-min(max(self.bias + z, -60.0), 60.0)))


def held_out(key: str = "doc_id") -> Column:
    """Whether a row is kept from fitting: crc32 of its id as text, modulo 5, is 0."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 5 == 0, F.lit(False))


def _bag(text: str | None, known: dict[str, int]) -> tuple[list[list[int]], int]:
    """Known features of each sentence that has some, and the number of the other sentences."""
    bag, empty = [], 0
    for s in SENTENCE.findall((text or "").lower()):
        words = WORDS(s)
        if own := [known[f] for w in words for f in features(w) if f in known]:
            bag.append(own)
        else:
            empty += bool(words)
    return bag, empty


def labelled(docs: DataFrame, labels: DataFrame, label: str, most: int = MAX_LABELLED) -> DataFrame:
    """text, y of at most `most` labelled documents outside the holdout."""
    y = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    y = y.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(y), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.first("y").alias("y"))
    rows = materialize(rows.withColumn("n", F.coalesce(F.length("text"), F.lit(0))), "labelled")
    so_far = F.sum("n").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))
    kept = rows.select("doc_id", so_far.alias("so_far")).where(F.col("so_far") <= MAX_CHARS).select("doc_id")
    return rows.join(F.broadcast(kept), "doc_id").select("text", "y")


def _vocabulary(rows: DataFrame) -> list[str]:
    """Words whose document counts differ most between the classes, by likelihood-ratio gain."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen = (Counter(), Counter())
            for text, y in zip(batch.column(0), batch.column(1), strict=True):
                seen[int(y.as_py() > 0)].update({f for w in set(WORDS((text.as_py() or "").lower())) for f in features(w)})
            words = sorted(seen[0] | seen[1])
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array([seen[0][w] for w in words], pa.int64()), pa.array([seen[1][w] for w in words], pa.int64())], names=["word", "n0", "n1"])

    total = rows.agg(F.sum(F.when(F.col("y") > 0, 0).otherwise(1)), F.sum(F.when(F.col("y") > 0, 1).otherwise(0))).first()
    if not total[0] or not total[1]:
        return []
    n0, n1 = float(total[0]), float(total[1])
    words = rows.mapInArrow(count, "word string, n0 long, n1 long").groupBy("word").agg(F.sum("n0").alias("a"), F.sum("n1").alias("b")).where(F.col("b") >= LEAST_DOCS)

    def part(k: Column, expected: Column) -> Column:
        return F.when(k > 0, 2 * k * F.log(k / expected)).otherwise(F.lit(0.0))

    rate = (F.col("a") + F.col("b")) / (n0 + n1)
    gain = part(F.col("a"), rate * n0) + part(F.col("b"), rate * n1) + part(n0 - F.col("a"), (1 - rate) * n0 + 1e-12) + part(n1 - F.col("b"), (1 - rate) * n1 + 1e-12)
    best = words.withColumn("gain", gain).where(F.col("gain") >= LEAST_GAIN).orderBy(F.desc("gain"), "word").limit(MAX_WORDS)
    return [r.word for r in best.select("word").collect()]


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MAX_LABELLED, rounds: int = 400) -> Model:
    rows = materialize(labelled(docs, labels, label, most), "fitted")
    words = _vocabulary(rows)
    if not words:
        return Model()
    known = {w: i for i, w in enumerate(words)}

    def bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [_bag(t.as_py(), known) for t in batch.column(0)]
            sizes = [np.array([len(s) for s in b], np.int32).tobytes() for b, _ in found]
            own = [np.array([w for s in b for w in s], np.int16).tobytes() for b, _ in found]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(sizes, pa.binary()), pa.array(own, pa.binary()), pa.array([e for _, e in found], pa.int64())], names=["y", "sizes", "words", "empty"])

    got = rows.mapInArrow(bags, "y int, sizes binary, words binary, empty long").toPandas()
    return _descend(words, got.y.to_numpy(float), list(got.sizes), b"".join(got.words), got["empty"].to_numpy(float), rounds)


def _descend(words: list[str], y: np.ndarray, sizes: list[bytes], own: bytes, empty: np.ndarray, rounds: int) -> Model:
    """Adam on the penalised noisy-or likelihood; sizes of each document's sentences, and all their words, are packed numbers."""
    doc = np.repeat(np.arange(len(sizes), dtype=np.int32), [len(s) // 4 for s in sizes])
    length = np.frombuffer(b"".join(sizes), np.int32)
    sentence = np.repeat(np.arange(len(length), dtype=np.int32), length)
    word = np.frombuffer(own, np.int16)
    x = np.concatenate([np.full(len(words), 0.5), [-6.0, np.log(max(y.mean(), 1e-3) / 4)]])  # weights, bias, logit of the leak
    m = v = np.zeros_like(x)
    squash = lambda z: 1 / (1 + np.exp(-np.clip(z, -40, 40)))
    for t in range(1, rounds + 1):
        p = squash(x[-2] + np.bincount(sentence, x[word], len(length)))
        p0, leak = squash(x[-2]), squash(x[-1])
        keep = np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-9)), len(y)) + empty * np.log1p(-p0) + np.log1p(-leak)
        none = np.exp(keep)
        # d(log likelihood) / d(keep)
        g = (1 - y) - y * none / np.maximum(1 - none, 1e-9)
        at = -g[doc] * p
        grad = np.concatenate([np.bincount(word, at[sentence], len(words)) - 0.5 * x[:-2], [at.sum() - (g * empty).sum() * p0, -(g.sum()) * leak]])
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        x = x + 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
    return Model(float(x[-2]), float(squash(x[-1])), {w: float(b) for w, b in zip(words, x, strict=False) if abs(b) > 1e-3})


def _scorer(model: Model):
    """scorer(text, cut) -> score, sentences of at least cut (None: no sentences)."""
    sums, base, leak = _Sums(model.weights), math.log1p(-model.chance(0.0)), math.log1p(-model.leak)

    def scorer(text: str | None, cut: float | None) -> tuple[float, list[dict]]:
        keep, at = leak, []
        # lower() can change lengths; sentences are cut from the raw text
        for s in SENTENCE.finditer(text or ""):
            words = WORDS(s.group().lower())
            if not words:
                continue
            z = sum(map(sums.__getitem__, words))
            if z == 0:
                keep += base
                continue
            p = model.chance(z)
            keep += math.log1p(-min(p, 1 - 1e-12))
            if cut is not None and p >= cut:
                at.append({"start": s.start(), "end": s.end(), "score": p})
        return min(max(-math.expm1(keep), 0.0), 1.0), at

    return scorer


def clean(docs: DataFrame, model: Model, cut: float = 0.5, text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, whose score is under the cut."""
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = _scorer(model)
        for batch in batches:
            yield batch.filter(pa.array([scorer(v.as_py(), None)[0] < cut for v in batch.column(at)], pa.bool_()))

    return bounded_batches(docs).mapInArrow(run, docs.schema)


def score(docs: DataFrame, model: Model, locate: float | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, score; with locate also the sentences (start, end, score) of at least that probability, in code points."""
    kind = docs.schema[key].dataType.simpleString()
    spans = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = _scorer(model)
        for batch in batches:
            scores, found = [], []
            for value in batch.column(1):
                p, at = scorer(value.as_py(), locate)
                scores.append(p), found.append(at)
            out = [batch.column(0), pa.array(scores, pa.float64())]
            yield pa.RecordBatch.from_arrays(out + ([pa.array(found, spans)] if locate is not None else []), names=[key, "score"] + (["sentences"] if locate is not None else []))

    schema = f"`{key}` {kind}, score double" + (", sentences array<struct<start:int,end:int,score:double>>" if locate is not None else "")
    return bounded_batches(docs).select(key, text).mapInArrow(run, schema)


def toxicity(docs: DataFrame, labels: DataFrame, label: str = "toxic") -> DataFrame:
    """doc_id, held_out, score, predicted, sentences."""
    model = fit(docs, labels, label)
    out = score(docs, model, locate=0.5)
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "sentences")
