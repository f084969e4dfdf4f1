"""A quality classifier: hashed word n-grams, logistic regression, FTRL-proximal training.

Words are runs of letters and digits or runs of marks; unigrams and bigrams are
hashed. A text's score is the sparse dot product of its n-gram shares with the
weights, through a sigmoid.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from densegrid.llm._text import column, joined, mix, slices, span_hashes, sums_between
from densegrid.llm.langid import hash_share, held_out
from densegrid.plans.shipping import ship

BITS, SCALE = 18, 30.0
#: Labelled documents that the weights are fitted on, in expectation; twice that at most.
SAMPLE = 4000
THRESHOLD = 0.7

_KIND = np.full(256, 2, np.int8)  # 0 white space, 1 marks, 2 letters, digits and all beyond ASCII
_KIND[[9, 10, 11, 12, 13, 32]] = 0
_KIND[[c for c in range(33, 127) if not chr(c).isalnum()]] = 1


def ngrams(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed uni- and bigrams of the texts and where each text's begin (and all end).

    A bigram of twice the same word is one feature whatever the word.
    """
    buf, ends = joined(texts, low=False)
    kind = _KIND[buf]
    starts_here = np.flatnonzero((kind != 0) & (np.concatenate([[0], kind[:-1]]) != kind))
    ends_here = np.flatnonzero((kind != 0) & (np.concatenate([kind[1:], [0]]) != kind)) + 1
    word = span_hashes(buf, starts_here, ends_here)
    first = np.concatenate([[0], np.searchsorted(starts_here, ends)])
    before = np.concatenate([[np.uint64(0)], word[:-1]])
    before[first[:-1][first[:-1] < len(word)]] = 1  # a text's first word follows its start
    pair = np.where(before == word, np.uint64(12345), mix(before * np.uint64(3) + word))
    out = np.empty(2 * len(word), np.int64)
    out[0::2], out[1::2] = word >> np.uint64(64 - BITS), mix(pair) >> np.uint64(64 - BITS)
    return out, 2 * first


class Ftrl:
    """Follow-the-regularised-leader, proximal: per-coordinate rates, L1 and L2 penalties."""

    def __init__(self, size: int, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 1.0):
        self.z, self.n = np.zeros(size), np.zeros(size)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, y: float, weight: float = 1.0) -> None:
        w = self.weights(at)
        g = weight * (1 / (1 + np.exp(-np.clip(w @ x, -35, 35))) - y) * x
        self.z[at] += g - (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha * w
        self.n[at] += g * g


class QualityModel:
    """Weights by hashed n-gram; the last one is the bias."""

    def __init__(self, rows: list[tuple[int, np.ndarray, np.ndarray]], rounds: int = 5):
        learner = Ftrl((1 << BITS) + 1)
        bias = np.array([1 << BITS])
        rng = np.random.default_rng(11)
        for _ in range(rounds):
            for i in rng.permutation(len(rows)):
                y, at, n = rows[i]
                learner.learn(np.concatenate([at, bias]), np.concatenate([n * (SCALE / max(1, n.sum())), [1.0]]), float(y))
        self.weights = learner.weights().astype(np.float32)

    def predict(self, texts: list[bytes | None]) -> np.ndarray:
        out = []
        for s, e in slices(texts):
            h, first = ngrams(texts[s:e])
            dot = sums_between(self.weights[h], first) * (SCALE / np.maximum(1, np.diff(first))) + float(self.weights[-1])
            out.append(1 / (1 + np.exp(-np.clip(dot, -35, 35))))
        return np.concatenate([*out, np.zeros(0)])


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> QualityModel:
    """Fits on labelled documents outside the held-out fold, about ``most`` of them.

    Labels other than 0 and 1, null ids and repeated labels of one id don't count
    (of repeated ones the larger). No labels: every score is 0.5.
    """
    open_labels = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col("quality").cast("int").alias("y")).where(F.col("y").isin(0, 1) & F.col("_id").isNotNull() & ~held_out(F.col("_id"), 4, 2))
    total = open_labels.count()
    picked = open_labels.where(hash_share(F.col("_id"), "quality") < min(1.0, most / max(1, total))).groupBy("_id").agg(F.max("y").alias("y")).limit(2 * most)
    some = docs.select(F.col("doc_id").cast("long").alias("_doc"), F.col("text").cast("binary").alias("text")).join(F.broadcast(picked), F.col("_doc") == F.col("_id")).select("_doc", "y", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            idx, val = [], []
            for t in column(batch, "text"):
                at, n = np.unique(ngrams([t])[0], return_counts=True)
                idx.append(at.astype(np.int32).tobytes())
                val.append(n.astype(np.int32).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(idx, pa.binary()), pa.array(val, pa.binary())], ["_doc", "y", "idx", "val"])

    rows = some.mapInArrow(run, "_doc long, y int, idx binary, val binary").collect()
    rows = sorted(rows, key=lambda r: (r["_doc"], bytes(r["idx"]), bytes(r["val"])))
    return QualityModel([(r["y"], np.frombuffer(r["idx"], np.int32).astype(np.int64), np.frombuffer(r["val"], np.int32).astype(float)) for r in rows])


def score(docs: DataFrame, labels: DataFrame, model: QualityModel | None = None) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row; the whole text is read.

    Empty and null texts get the bias alone. A null doc_id is not held out and not
    learned from. Repeated rows stay; other columns are ignored.
    """
    shipped = ship(docs.sparkSession, model or train(docs, labels))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here = shipped()
        for batch in batches:
            s = here.predict(column(batch, "text"))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= THRESHOLD).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), 4, 2).alias("held_out"), F.col("text").cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
