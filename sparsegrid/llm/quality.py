"""Quality classifier: logistic regression over hashed word n-grams.

Tokens are runs of letters and digits and runs of other signs; a token equal to
the one before it forms one shared bigram "again".  Unigrams and bigrams are
hashed into a fixed number of slots, damped by the logarithm and scaled to
length one; the weights are learned with per-coordinate follow-the-regularised-
leader updates in one pass after another over a bounded sample and scored as
sparse dot products.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.llm.sampling import class_shares, labelled_sample
from sparsegrid.llm.textkernel import ALNUM, SPACED, mix64, words_of
from sparsegrid.plans.lineage import release

BITS = 18
_AGAIN = np.uint64(0x51ED270B4F6A2C11)
_LEFT = np.uint64(0x9FB21C651E98DF25)
_RIGHT = np.uint64(0xD6E8FEB86659FD93)


def slots_of(words: np.ndarray, signs: np.ndarray, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Slots and values of one text's features, from the hashes of its words and signs."""
    pairs = np.where(words[1:] == words[:-1], _AGAIN, mix64(words[:-1] * _LEFT + words[1:] * _RIGHT)) if len(words) > 1 else words[:0]
    grams = np.concatenate([words, signs, pairs])
    slot, count = np.unique((mix64(grams) >> np.uint64(64 - bits)).astype(np.int32), return_counts=True)
    value = np.log1p(count)
    return slot, (value / max(np.sqrt((value**2).sum()), 1e-12)).astype(np.float32)


#: Signs: bytes that are neither white space nor part of a word (after lower-casing).
_SIGNS = SPACED & ~ALNUM
_SIGNS[:0x20] = False


def features(column: pa.Array, bits: int = BITS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Sparse features of every text of an Arrow column."""
    for (_, wb, words), (_, sb, signs) in zip(words_of(column, ALNUM), words_of(column, _SIGNS), strict=True):
        for i in range(len(wb) - 1):
            yield slots_of(words[wb[i] : wb[i + 1]], signs[sb[i] : sb[i + 1]], bits)


@dataclass
class LinearModel:
    weights: np.ndarray
    bias: float

    def score(self, slot: np.ndarray, value: np.ndarray) -> float:
        return 1 / (1 + float(np.exp(-np.clip(self.bias + float(self.weights[slot] @ value), -60, 60))))


def fit_ftrl(rows: list[tuple[int, np.ndarray, np.ndarray]], bits: int = BITS, epochs: int = 25, alpha: float = 4.0, beta: float = 1.0, l1: float = 0.02, l2: float = 0.05, prior: float | None = None) -> LinearModel:
    """Weights from (label, slots, values) rows by follow-the-regularised-leader updates.

    ``prior`` is the share of label 1 among all labels; where the sample has
    another share, its rows are weighted so that scores stay probabilities.
    """
    z, n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)
    seen = sum(y for y, _, _ in rows) / max(1, len(rows))
    prior = seen if prior is None else prior
    weight = {1: prior / seen if seen else 1.0, 0: (1 - prior) / (1 - seen) if seen < 1 else 1.0}
    order = np.random.default_rng(7)

    def at(i: np.ndarray) -> np.ndarray:
        zi, l1s = z[i], np.where(i == 1 << bits, 0.0, l1)
        return np.where(np.abs(zi) <= l1s, 0.0, -(zi - np.sign(zi) * l1s) / ((beta + np.sqrt(n[i])) / alpha + l2))

    for _ in range(epochs):
        for k in order.permutation(len(rows)):
            y, slot, value = rows[k]
            i, x = np.append(slot, 1 << bits), np.append(value, np.float32(1)).astype(np.float64)
            w = at(i)
            g = (1 / (1 + np.exp(-np.clip(w @ x, -60, 60))) - y) * weight[y] * x
            z[i] += g - (np.sqrt(n[i] + g * g) - np.sqrt(n[i])) / alpha * w
            n[i] += g * g
    w = at(np.arange((1 << bits) + 1))
    return LinearModel(w[:-1].astype(np.float32), float(w[-1]))


def _featured(batches):
    for batch in batches:
        got = list(features(batch.column(2)))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array([s for s, _ in got], pa.list_(pa.int32())), pa.array([v for _, v in got], pa.list_(pa.float32()))],
            ["doc_id", "label", "slot", "value"],
        )


def train_quality(docs: DataFrame, labels: DataFrame, label: str = "quality", fold: tuple[int, int] = (5, 0), max_rows: int = 3000, max_bytes: int = 16 << 20) -> LinearModel:
    """Fits the classifier on at most ``max_rows`` labelled texts, together about ``max_bytes``, outside the held-out fold.

    Without any usable row the model is constant at 0.5.
    """
    sample = labelled_sample(docs, labels, label, fold, max_rows, max_bytes, 11).select("doc_id", "label", "text")
    rows = sample.mapInArrow(_featured, "doc_id long, label int, slot array<int>, value array<float>").toArrow().sort_by("doc_id")
    data = [(int(y), s, v) for y, s, v in zip(rows["label"].to_pylist(), rows["slot"].to_numpy(), rows["value"].to_numpy(), strict=True)]
    zero, one = class_shares(labels, label, fold)
    model = fit_ftrl(data, prior=one / (zero + one) if zero + one else None) if data else LinearModel(np.zeros(1 << BITS, np.float32), 0.0)
    del rows, data
    pa.default_memory_pool().release_unused()
    release(docs.sparkSession)
    return model


def _scored(model, keep: int):
    def run(batches):
        for batch in batches:
            scores = [model.value.score(s, v) for s, v in features(batch.column(keep))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:keep], pa.array(scores, pa.float64())], [*batch.schema.names[:keep], "score"])

    return run


def score_quality(docs: DataFrame, model: LinearModel) -> DataFrame:
    """(doc_id, score) for every row of ``docs``; null and empty texts get the score of no features.

    Rows with a null id keep it; repeated rows are scored as often as they are
    there; other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_scored(shared, 1), "doc_id long, score double")


def keep_good(docs: DataFrame, model: LinearModel, threshold: float) -> DataFrame:
    """The rows of ``docs`` (all columns) whose score is at least ``threshold``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns

    def run(batches):
        for batch in batches:
            scores = np.array([shared.value.score(s, v) for s, v in features(batch.column(names.index("text")))])
            yield batch.filter(pa.array(scores >= threshold)) if len(scores) else batch

    return docs.mapInArrow(run, docs.schema)
