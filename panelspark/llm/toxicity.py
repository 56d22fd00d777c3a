"""Toxicity: logistic regression by follow-the-regularised-leader with per-coordinate rates and L1 sparsity.

Features are the hashed words, word pairs and skip-pairs (one word between) of the text, present or not. The learner
reads a bounded sample of labelled rows (`sample_rows`, those with the smallest hash of doc_id) in a fixed order, and
the few weights that L1 leaves are broadcast to score every row.

Empty and null texts score as the bias alone. A table without labels gives every row the score 0. Repeated equal
labels of a document count once, and of documents with one id the smallest text counts, so that the driver never holds
more than sample_rows rows. Results depend on the text only, so ties cannot arise.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, byte_view, lowered, mix, range_hashes, shipped, slices, word_ranges

BITS = 20


def feature_ids(data: np.ndarray, offsets: np.ndarray):
    """Hashed features and the row of each, for a buffer of several texts. Punctuation at the ends of words is dropped."""
    data = lowered(data)
    letter = (data >= 128) | ((data >= 97) & (data <= 122)) | ((data >= 48) & (data <= 57)) | (data == 39)
    spaced = np.where(letter, data, 32).astype(np.uint8)
    starts, ends, row = word_ranges(spaced, offsets)
    h = range_hashes(spaced, starts, ends)
    out, rows = [h], [row]
    for gap, salt in ((1, 0x51), (2, 0x52)):
        same = row[gap:] == row[:-gap] if len(row) > gap else np.zeros(0, bool)
        pair = mix(h[:-gap] * U(3) + h[gap:] * U(5) + U(salt)) if len(row) > gap else np.zeros(0, np.uint64)
        out.append(pair[same])
        rows.append(row[:-gap][same] if len(row) > gap else np.zeros(0, np.int64))
    return (np.concatenate(out) >> U(64 - BITS)).astype(np.int64), np.concatenate(rows)


def featured(batches):
    for batch in batches:
        data, off = byte_view(batch.column(2))
        out = []
        for i in range(batch.num_rows):
            part = data[off[i] : off[i + 1]]
            out.append(np.unique(feature_ids(part, np.array([0, len(part)]))[0]).astype(np.int32))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.list_(pa.int32()))], ["doc_id", "label", "features"])


class ProximalLearner:
    """Per-coordinate follow-the-regularised-leader for the logistic loss."""

    def __init__(self, bits: int = BITS, alpha: float = 1.0, beta: float = 1.0, l1: float = 10.0, l2: float = 0.0):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z = np.zeros((1 << bits) + 1)
        self.n = np.zeros((1 << bits) + 1)

    def weights(self, at: np.ndarray) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        pull = np.where(at == len(self.z) - 1, 0.0, self.l1)  # the bias is not regularised away
        w = -(z - np.sign(z) * pull) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= pull, 0.0, w)

    def learn(self, at: np.ndarray, label: int) -> None:
        at = np.append(at, len(self.z) - 1)
        w = self.weights(at)
        p = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -35, 35)))
        g = p - label
        self.z[at] += g - (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha * w
        self.n[at] += g * g

    def compact(self) -> tuple[np.ndarray, np.ndarray, float]:
        w = self.weights(np.arange(len(self.z)))
        at = np.flatnonzero(w[:-1])
        return at, w[at], float(w[-1])


def fit(rows: list, epochs: int = 4) -> dict:
    # the penalty follows the number of toxic examples up to its full strength, so that small samples learn too
    learner = ProximalLearner(l1=float(np.clip(sum(label for label, _ in rows) / 20, 1.5, 10.0)))
    order = np.random.default_rng(11)
    for _ in range(epochs if rows else 0):
        for i in order.permutation(len(rows)):
            learner.learn(np.asarray(rows[i][1], np.int64), rows[i][0])
    at, w, bias = learner.compact()
    return {"at": at.astype(np.int32), "w": w, "bias": bias, "trained": bool(rows)}


def scored(batches, model: dict, threshold: float):
    dense = np.zeros(1 << BITS)
    dense[model["at"]] = model["w"]
    for batch in batches:
        data, off = byte_view(batch.column(1))
        total = np.zeros(batch.num_rows)
        for i, j in slices(off):
            part, rows = data[off[i] : off[j]], off[i : j + 1] - off[i]
            ids, row = feature_ids(part, rows)
            hot = np.flatnonzero(dense[ids])
            if len(hot):  # each feature counts once in a text
                seen = np.unique((row[hot].astype(np.int64) << BITS) | ids[hot])
                total[i:j] += np.bincount(seen >> BITS, dense[seen & ((1 << BITS) - 1)], minlength=j - i)
        p = 1.0 / (1.0 + np.exp(-np.clip(total + model["bias"], -35, 35))) if model["trained"] else total
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32), pa.int32())], ["doc_id", "score", "predicted"])


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = 12_000) -> dict:
    """The model from at most sample_rows labelled documents."""
    wanted = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", F.col("toxic").cast("int").alias("label")).distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(sample_rows)
    rows = docs.select("doc_id", "text").join(F.broadcast(wanted), "doc_id").groupBy("doc_id", "label").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))
    got = rows.mapInArrow(shipped("panelspark.llm.toxicity", "featured"), "doc_id long, label int, features array<int>").toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending")])
    return fit([(l, np.asarray(f.values)) for l, f in zip(got.column(1).to_pylist(), got.column(2), strict=True)])


def score(docs: DataFrame, model: dict, threshold: float = 0.3) -> DataFrame:
    """doc_id, score and predicted for each row of docs(doc_id, text); narrow."""
    return docs.select("doc_id", "text").mapInArrow(shipped("panelspark.llm.toxicity", "scored", model, threshold), "doc_id long, score double, predicted int")


def kept(docs: DataFrame, model: dict, threshold: float = 0.3) -> DataFrame:
    """The rows of docs that the model doesn't reject, with all their columns."""
    return docs.mapInArrow(shipped("panelspark.llm.toxicity", "passed", model, threshold, docs.columns.index("text")), docs.schema)


def passed(batches, model: dict, threshold: float, at: int, most: int = 1 << 22):
    for whole in batches:
        _, off = byte_view(whole.column(at))
        for i, j in slices(off, most):
            batch = whole.slice(i, j - i)
            one = pa.RecordBatch.from_arrays([pa.array(np.arange(batch.num_rows)), batch.column(at)], ["doc_id", "text"])
            for result in scored([one], model, threshold):
                yield batch.filter(pa.array(np.asarray(result.column(2)) == 0))
