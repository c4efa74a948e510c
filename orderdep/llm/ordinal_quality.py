"""Ordinal cumulative-link regression of a document's grade on hashed text features.

P(grade <= k) = 1 / (1 + exp(-(t_k - w.x))) with one weight vector w for all grades and thresholds t_0 < t_1 < ...
x marks the hashed features a text has: its words (lower-case ASCII, digits and non-ASCII characters) and its runs of
signs, and the words' beginnings of a few lengths.  Only features that go with the grade take part: in at least
``least_documents`` training documents, with a mean grade ``least_z`` standard errors off the overall mean.  Expected
grade and the probability of the highest grades follow from the thresholds.

Training uses at most ``sample`` labelled documents, those whose ids hash lowest, in one task, and returns one row;
scoring is a single pass over all documents with the weights (2**``bits`` floats of 4 bytes) sent to every task.
Null and empty texts have no features and get the prior of the thresholds.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .decontam import _WORD_BYTES, words_of

BITS = 20
SAMPLE = 12_000
LEAST_DOCUMENTS = 4
LEAST_Z = 5.0
PENALTY = 0.05
STEPS = 200
_SIGN_RUNS = bytes(0x20 if b in _WORD_BYTES or 0x41 <= b <= 0x5A or b <= 0x20 else b for b in range(256))
_SIGN_SALT, _HEAD_SALT = 0x5F356495, 0x3C6EF372
#: Lengths in bytes of the word beginnings that are features too: inflected and joined words share them.
HEADS = (4, 5, 6, 7, 8)


def features(text: bytes, bits: int = BITS) -> np.ndarray:
    """Different hashed features of a text, ascending."""
    words, signs = set(words_of(text)), set(text.translate(_SIGN_RUNS).split())
    kinds = [(0, words), (_SIGN_SALT, signs), *[(n * _HEAD_SALT & 0xFFFFFFFF, {w[:n] for w in words if len(w) > n}) for n in HEADS]]
    h = [np.fromiter(map(zlib.crc32, k), np.uint32, len(k)) ^ np.uint32(salt) for salt, k in kinds]
    return np.unique(np.concatenate(h) & np.uint32((1 << bits) - 1)).astype(np.int64)


@dataclass
class OrdinalModel:
    weights: np.ndarray
    thresholds: np.ndarray
    bits: int = BITS

    def score(self, text: bytes) -> float:
        return float(self.weights[features(text, self.bits)].sum())

    def probabilities(self, scores: np.ndarray) -> np.ndarray:
        """One row a score, one column a grade."""
        below = 1 / (1 + np.exp(-np.clip(self.thresholds[None, :] - scores[:, None], -40, 40)))
        return np.diff(np.concatenate([np.zeros((len(scores), 1)), below, np.ones((len(scores), 1))], axis=1), axis=1)


def fit(examples: list[np.ndarray], grades: np.ndarray, levels: int, *, bits: int = BITS, least_documents: int = LEAST_DOCUMENTS, least_z: float = LEAST_Z, penalty: float = PENALTY, steps: int = STEPS) -> OrdinalModel:
    """Maximum penalised likelihood by adaptive gradient steps over all examples.

    Thresholds are a first value and positive gaps, so their order always holds.  A grade that no example has gets a
    gap that the data do not move; without examples all grades are equally likely.
    """
    n = len(examples)
    share = np.clip(np.array([(grades <= k).mean() if n else (k + 1) / levels for k in range(levels - 1)]), 1e-3, 1 - 1e-3)
    first = np.maximum.accumulate(np.log(share / (1 - share)) + 1e-3 * np.arange(levels - 1))
    weights = np.zeros(1 << bits)
    if not n:
        return OrdinalModel(weights, first, bits)
    at = np.concatenate(examples)
    seen = np.bincount(at, minlength=1 << bits)
    owner = np.repeat(np.arange(n), [len(e) for e in examples])
    off = np.bincount(at, weights=(grades - grades.mean())[owner], minlength=1 << bits)
    used = np.flatnonzero((seen >= least_documents) & (np.abs(off) >= least_z * np.sqrt(seen) * max(grades.std(), 1e-9)))
    place = np.full(1 << bits, -1)
    place[used] = np.arange(len(used))
    ok = place[at] >= 0
    row, col = owner[ok], place[at][ok]
    w = np.zeros(len(used))
    base, gaps = first[0], np.log(np.maximum(np.diff(first), 1e-3))
    m = [np.zeros(len(used)), 0.0, np.zeros(levels - 2)]
    v = [np.zeros(len(used)), 0.0, np.zeros(levels - 2)]
    for step in range(1, steps + 1):
        t = base + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])
        x = np.bincount(row, weights=w[col], minlength=n)
        edges = np.concatenate([np.full((n, 1), -np.inf), t[None, :] - x[:, None], np.full((n, 1), np.inf)], axis=1)
        cdf = 1 / (1 + np.exp(-np.clip(edges, -40, 40)))
        cdf[:, 0], cdf[:, -1] = 0, 1
        pdf = cdf * (1 - cdf)
        k = np.arange(n)
        p = np.maximum(cdf[k, grades + 1] - cdf[k, grades], 1e-12)
        upper, lower = pdf[k, grades + 1] / p, pdf[k, grades] / p
        by_edge = np.zeros(levels + 1)
        np.add.at(by_edge, grades + 1, -upper)
        np.add.at(by_edge, grades, lower)
        by_t = by_edge[1:-1]  # gradient of the loss by threshold
        g = [np.bincount(col, weights=(upper - lower)[row], minlength=len(used)) + penalty * w, by_t.sum(), np.array([by_t[j + 1 :].sum() for j in range(levels - 2)]) * np.exp(gaps)]
        rate = 0.05 if step < 0.7 * steps else 0.01
        now = [w, base, gaps]
        for j in range(3):
            m[j] = 0.9 * m[j] + 0.1 * g[j]
            v[j] = 0.999 * v[j] + 0.001 * g[j] ** 2
            now[j] = now[j] - rate * (m[j] / (1 - 0.9**step)) / (np.sqrt(v[j] / (1 - 0.999**step)) + 1e-8)
        w, base, gaps = now
    weights[used] = w
    return OrdinalModel(weights, base + np.concatenate([[0.0], np.cumsum(np.exp(gaps))]), bits)


def train(docs: DataFrame, ratings: DataFrame, levels: int, *, bits: int = BITS, sample: int = SAMPLE, **parameters) -> OrdinalModel:
    """docs (doc_id, text), ratings (doc_id, grade 0 .. levels - 1; others and nulls are left out)."""
    chosen = ratings.where(F.col("grade").between(0, levels - 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("grade").alias("grade"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)  # a bounded table, so it can be broadcast
    texts = docs.select("doc_id", F.col("text").cast("string").cast("binary").alias("text")).join(F.broadcast(chosen), "doc_id")

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([features(t.as_py() or b"", bits).astype("<u4").tobytes() for t in b.column(2)], pa.binary())], names=["doc_id", "grade", "x"])

    def fitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted((i, g, x) for b in batches for i, g, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()))
        model = fit([np.frombuffer(x, "<u4").astype(np.int64) for *_, x in rows], np.array([g for _, g, _ in rows], np.int64), levels, bits=bits, **parameters)
        yield pa.RecordBatch.from_arrays([pa.array([model.weights.astype("<f4").tobytes()], pa.binary()), pa.array([model.thresholds.tolist()])], names=["weights", "thresholds"])

    got = texts.select("doc_id", F.col("grade").cast("int").alias("grade"), "text").mapInArrow(marked, "doc_id long, grade int, x binary").repartition(1).mapInArrow(fitted, "weights binary, thresholds array<double>").first()
    if got is None:
        return fit([], np.zeros(0, np.int64), levels, bits=bits)
    return OrdinalModel(np.frombuffer(bytes(got["weights"]), "<f4").astype(float), np.array(got["thresholds"]), bits)


def grade(docs: DataFrame, model: OrdinalModel, *, tail: int, least: float = 0.5) -> DataFrame:
    """One row per document: doc_id, score, expected_grade, tail_probability (of grade ``tail`` or more), grade (likeliest), kept."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            score = np.array([m.score(t.as_py() or b"") for t in b.column(1)], float)
            p = m.probabilities(score)
            above = p[:, tail:].sum(1)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score), pa.array(p @ np.arange(p.shape[1])), pa.array(above), pa.array(p.argmax(1).astype(np.int32)), pa.array(above >= least)], names=["doc_id", "score", "expected_grade", "tail_probability", "grade", "kept"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", F.col("text").cast("string").cast("binary").alias("text")).mapInArrow(run, f"doc_id {kind}, score double, expected_grade double, tail_probability double, grade int, kept boolean")


def graded(quality: Column, toxic: Column) -> Column:
    """0: toxic; 1: clean of low quality; 2: clean of good quality.  Null where a label is missing."""
    return F.when(toxic == 1, 0).when((toxic == 0) & (quality == 0), 1).when((toxic == 0) & (quality == 1), 2)
