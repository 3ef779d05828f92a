"""Operator 10: toxicity by multiple-instance learning.

A document is a bag of sentences.  Sentence z has the probability s(z) = sigmoid(bias + sum of its words' weights), and
the document is toxic unless every sentence is clean: P = 1 - prod(1 - s(z)) (noisy-or).  The weights are learned from
document labels alone, by Adam on the noisy-or likelihood with an L1 step, from at most ``MAX_ROWS`` labelled rows of
at most ``MAX_CHARS`` characters (the smallest keyed hashes of doc_id, the same rows at any partitioning).  Scoring
reads every whole text; the sentence with the largest s(z) is the one to blame.

Only the text enters a score.  Defined results: null and empty texts get the score of no sentence; a label that is
null is not learned from; a text of any length is scored whole; sentences that tie share the blame with the first of
them; repeated rows score alike; an id with several labels is learned from with each; without a toxic and a clean labelled
row every score is 0; any integer type serves as doc_id; an empty table gives no rows; ``keep_clean`` returns all columns
of its rows, whatever their names.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.sources.tables import read_table

MAX_ROWS, MAX_CHARS, VOCABULARY, MIN_DOCS = 10_000, 100_000, 2000, 4
STEPS, RATE, L1, LEAN = 300, 0.1, 2e-5, 3.5

_SENTENCE = re.compile(r"[.!?\n\r]+")
_WORD = re.compile(r"[^\W_]+")


@dataclass
class Model:
    weights: dict[str, float] = field(default_factory=dict)
    bias: float = -30.0
    #: Added to the log-odds of a document, so that 0.5 is the best cut on the learned rows.
    shift: float = 0.0

    def sentences(self, text: str) -> list[tuple[int, int, float]]:
        """(start, end, s) of every sentence that holds a weighted word."""
        low, get, out, at = text.lower(), self.weights.get, [], 0
        if len(low) != len(text):  # lower-casing moved the places
            low = "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
        for m in [*_SENTENCE.finditer(low), None]:
            end = m.start() if m else len(low)
            z = [w for w in map(get, set(_WORD.findall(low, at, end))) if w is not None]
            if z:
                out.append((at, end, 1 / (1 + np.exp(-(self.bias + sum(z))))))
            at = m.end() if m else end
        return out

    def score(self, text: str | None) -> tuple[float, int, int, float]:
        """Document score, start and end of the worst sentence (-1 if none holds a weighted word), its s."""
        text = text or ""
        clean, worst, at = 0.0, 0.0, (-1, -1)
        found = self.sentences(text)
        for a, b, s in found:
            clean += np.log1p(-min(s, 1 - 1e-12))
            if s > worst:
                worst, at = s, (a, b)
        p = min(max(1 - np.exp(clean), 1e-9), 1 - 1e-9)
        return float(1 / (1 + np.exp(-(np.log(p / (1 - p)) + self.shift)))), at[0], at[1], float(worst)


def is_held_out(doc_id: Column) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5)) == 0


def learning_rows(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS, seed: int = 42) -> list[tuple[str, int]]:
    """Text and label of the bounded sample; the ids are drawn from the labels, so that texts are not shuffled."""
    known = labels.where(~is_held_out(F.col("doc_id")) & F.col("toxic").isNotNull()).select(F.col("doc_id").cast("long").alias("id"), F.col("toxic").alias("y"))
    drawn = known.orderBy(F.xxhash64("id", F.lit(seed)), "id", "y").limit(max_rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").alias("t")).where(F.col("t").isNotNull() & (F.length("t") <= MAX_CHARS))
    joined = texts.join(F.broadcast(drawn), "id")
    return [(r["t"], int(r["y"])) for r in joined.orderBy("id", "t", "y").collect()]


def fit(rows: list[tuple[str, int]]) -> Model:
    y = np.array([t for _, t in rows], dtype=float)
    if not len(rows) or y.min() == y.max():
        return Model()
    # the texts are read twice, so that no set of words outlives its document
    held: list[Counter] = [Counter(), Counter()]
    for text, label in rows:
        held[int(label)].update(set(_WORD.findall(text.lower())))
    n1, n0 = y.sum(), len(y) - y.sum()

    def lean(w: str) -> float:  # z-score of the log-odds of document counts
        a, b = held[1][w] + 0.5, held[0][w] + 0.5
        return abs(np.log(a / (n1 - a + 1)) - np.log(b / (n0 - b + 1))) / np.sqrt(1 / a + 1 / b)

    known = sorted((w for w in held[0].keys() | held[1].keys() if held[0][w] + held[1][w] >= MIN_DOCS), key=lambda w: (-lean(w), w))[:VOCABULARY]
    known = [w for w in known if lean(w) >= LEAN]
    place = {w: i for i, w in enumerate(known)}
    held.clear()
    doc, sent, word = [], [], []
    for d, (text, _) in enumerate(rows):
        for s in _SENTENCE.split(text.lower()):
            if hit := [place[w] for w in set(_WORD.findall(s)) if w in place]:
                sent += [len(doc)] * len(hit)
                word += hit
                doc.append(d)
    doc, sent, word = np.array(doc, dtype=int), np.array(sent, dtype=int), np.array(word, dtype=int)
    w, bias = np.zeros(len(known)), -4.0
    m, v = np.zeros(len(known) + 1), np.zeros(len(known) + 1)

    def forward():
        z = bias + np.bincount(sent, w[word], minlength=len(doc))
        clean = np.bincount(doc, np.logaddexp(0, z), minlength=len(y))
        return z, np.clip(-np.expm1(-clean), 1e-9, 1 - 1e-9)

    for step in range(1, STEPS + 1):
        z, p = forward()
        # d(-log likelihood)/dz: s for a clean document, -s (1 - P) / P for a toxic one
        g = np.where(y[doc] == 1, -(1 - p[doc]) / p[doc], 1.0) / (1 + np.exp(-z)) / len(y)
        grad = np.append(np.bincount(word, g[sent], minlength=len(known)), g.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        move = RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w, bias = w - move[:-1], min(bias - move[-1], 0.0)
        w = np.sign(w) * np.maximum(np.abs(w) - RATE * L1 / (np.sqrt(v[:-1] / (1 - 0.99**step)) + 1e-8) * 1e0, 0)
    _, p = forward()
    model = Model({k: float(x) for k, x in zip(known, w, strict=True) if abs(x) > 1e-3}, float(bias))
    order = np.argsort(-p, kind="stable")
    hits = np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(y) + 1) + n1)
    best = int(np.argmax(f1))
    low, high = p[order[min(best + 1, len(y) - 1)]], p[order[best]]
    odds = [np.log(x / (1 - x)) for x in (low, high)]
    model.shift = float(-(odds[0] + odds[1]) / 2)
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, worst_start, worst_end, worst_score for every row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "score", "worst_start", "worst_end", "worst_score"]
        for batch in batches:
            found = [model.score(t) for t in batch.column(1).to_pylist()]
            cols = list(zip(*found, strict=True)) if found else [[]] * 4
            kinds = (pa.float64(), pa.int64(), pa.int64(), pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, type=k) for c, k in zip(cols, kinds, strict=True))], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double, worst_start long, worst_end long, worst_score double")


def keep_clean(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of ``docs`` that the model learned from ``labels`` does not reject, with all their columns."""
    model = fit(learning_rows(docs, labels))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
            yield batch.filter(pa.array([model.score(t)[0] < 0.5 for t in texts], type=pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    model = fit(learning_rows(docs, read_table(spark, sf_dir, "labels", "doc_id", "toxic")))
    return score(docs, model).select(
        "doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "worst_start", "worst_end", "worst_score"
    )
