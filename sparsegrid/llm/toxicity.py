"""Toxicity: averaged subword-bag embeddings under a linear softmax.

A word is the bag of its own slot and the slots of its character 3- to 5-grams
(with edge marks), so a misspelling that was never seen shares most vectors with
the word it comes from.  Embeddings and softmax are trained jointly in numpy.

The unit that is averaged is a window of a few words, and a text's score is that
of its most toxic window: a single insult in a long text is not averaged away.
Since the softmax is linear, a window's logit is a ratio of two sums over words,
so scoring needs two numbers for each word and two running sums for each text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.llm.sampling import class_shares, labelled_sample
from sparsegrid.llm.textkernel import mix64

SLOT_BITS = 16
_BASE = np.uint64(0x9FB21C651E98DF25)
WINDOW = 4
_EDGES = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_CACHE = 300_000


def plain(token: str) -> str:
    """A white-space separated token without case and without signs at its edges."""
    return token.lower().strip(_EDGES)


def subwords(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(slot, place in ``words``) of every subword: the word itself and its character 3- to 5-grams with edge marks.

    Hashes of code points, computed for all words at once; an empty word has none.
    """
    at = [k for k, w in enumerate(words) if w]
    if not at:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    marked = "".join(f"<{words[k]}>" for k in at)
    code = np.frombuffer(marked.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    size = np.array([len(words[k]) + 2 for k in at])
    start = np.cumsum(size) - size
    owner = np.repeat(np.arange(len(at)), size)
    step = np.cumprod(np.full(int(size.max()), _BASE, np.uint64), dtype=np.uint64)
    hashes = [mix64(np.add.reduceat(code * step[np.arange(len(code)) - start[owner]], start))]
    owners = [np.arange(len(at))]
    for n in (3, 4, 5):
        if len(code) >= n:
            h = np.full(len(code) - n + 1, np.uint64(n))
            for j in range(n):
                h = h * _BASE + code[j : len(code) - n + 1 + j]
            within = owner[: len(h)] == owner[n - 1 :]
            hashes.append(mix64(h[within]))
            owners.append(owner[: len(h)][within])
    return (np.concatenate(hashes) >> np.uint64(64 - SLOT_BITS)).astype(np.int64), np.array(at)[np.concatenate(owners)]


@dataclass
class SubwordModel:
    """``pull`` holds, for each slot, the softmax's evidence for label 1 in its embedding."""

    pull: np.ndarray
    bias: float
    window: int = WINDOW

    def scorer(self) -> TextScorer:
        return TextScorer(self)


class TextScorer:
    """Scores texts, remembering each distinct token's two numbers up to a bounded count."""

    def __init__(self, model: SubwordModel) -> None:
        self.model = model
        self._forget()

    def _forget(self) -> None:
        self.place: dict[str, int] = {}
        self.pull, self.size = np.zeros(1 << 12), np.zeros(1 << 12)

    def _learn(self, tokens: list[str]) -> None:
        first = len(self.place)
        if first + len(tokens) > len(self.pull):
            more = np.zeros(len(self.pull) + len(tokens))
            self.pull, self.size = np.append(self.pull, more), np.append(self.size, more)
        slot, owner = subwords([plain(t) for t in tokens])
        self.pull[first : first + len(tokens)] = np.bincount(owner, self.model.pull[slot], len(tokens))
        self.size[first : first + len(tokens)] = np.bincount(owner, minlength=len(tokens))
        self.place.update(zip(tokens, range(first, first + len(tokens)), strict=True))

    def score(self, text: str | None) -> float:
        tokens = (text or "").split()
        if len(self.place) > _CACHE:
            self._forget()
        ids = list(map(self.place.get, tokens))
        if None in ids:
            self._learn([t for t in set(tokens) if t not in self.place])
            ids = list(map(self.place.get, tokens))
        at = np.array(ids, np.int64)
        pull, size = (np.concatenate([[0.0], np.cumsum(x[at])]) for x in (self.pull, self.size))
        k = min(self.model.window, len(ids))
        mean = (pull[k:] - pull[:-k]) / np.maximum(size[k:] - size[:-k], 1.0) if k else np.zeros(1)
        return float(1 / (1 + np.exp(-np.clip(mean.max() + self.model.bias, -60, 60))))


def _windows(text: str, index: dict[str, int], k: int) -> np.ndarray:
    ids = [index.setdefault(plain(t), len(index)) for t in text.split()]
    ids += [-1] * (-len(ids) % k)
    return np.array(ids, np.int64).reshape(-1, k)


def fit_subwords(texts: list[str], labels: list[int], dim: int = 6, window: int = WINDOW, start_epochs: int = 15, epochs: int = 60, rate: float = 0.3, calm: float = 0.1, seed: int = 5, zero_share: float | None = None) -> SubwordModel:
    """Joint training of slot embeddings and softmax by full-batch adaptive gradients.

    Only whole texts are labelled.  At first every window of a text counts under
    the text's label, each text with the same weight.  Then the loss is that of
    the text's own score: of a text labelled 1 only its most toxic window
    counts, of a text labelled 0 every window that was ever its most toxic one.
    ``calm`` slows slots with little evidence, so words seen in a text or two
    are not learned by heart; ``zero_share`` is the share of label 0 among all
    labels, where the texts given have another.
    """
    index: dict[str, int] = {}
    blocks = [_windows(t, index, window) for t in texts]
    labels = [y for y, b in zip(labels, blocks, strict=True) if len(b)]
    blocks = [b for b in blocks if len(b)]
    if len(set(labels)) < 2:
        return SubwordModel(np.zeros(1 << SLOT_BITS, np.float32), 0.0, window)
    wins, doc = np.concatenate(blocks), np.repeat(np.arange(len(blocks)), [len(b) for b in blocks])
    first = np.concatenate([[0], np.cumsum([len(b) for b in blocks])[:-1]])
    label = np.array(labels, np.float64)
    zeros = 1 - label.mean()
    weight = np.where(label == 0, (zero_share or zeros) / zeros, (1 - (zero_share or zeros)) / (1 - zeros))
    flat, owner = subwords(list(index))
    order = np.argsort(owner, kind="stable")
    flat, owner = flat[order], owner[order]
    count = np.append(np.bincount(owner, minlength=len(index)), 0).astype(np.float64)  # the last stands for no word
    rng = np.random.default_rng(seed)
    emb, soft, bias = rng.normal(0, 0.05, (1 << SLOT_BITS, dim)), rng.normal(0, 0.5, dim), float(np.log((1 - zeros) / zeros))
    s_emb, s_soft, s_bias = np.full_like(emb, calm), np.full(dim, 1.0), 1.0

    def step(use: np.ndarray, w: np.ndarray) -> None:
        nonlocal emb, soft, bias, s_bias
        rows, y = wins[use], label[doc[use]]
        words, local = np.unique(rows, return_inverse=True)
        local = local.reshape(rows.shape)
        mine = np.zeros(len(count), bool)
        mine[words] = True
        at = np.flatnonzero(mine[owner])
        own, of = flat[at], np.searchsorted(words, owner[at]) if len(words) == 0 or words[0] >= 0 else 1 + np.searchsorted(words[1:], owner[at])
        vectors = np.stack([np.bincount(of, emb[own, d], len(words)) for d in range(dim)], 1)
        size = np.maximum(count[rows].sum(1), 1.0)
        mean = vectors[local].sum(1) / size[:, None]
        g = (1 / (1 + np.exp(-np.clip(mean @ soft + bias, -60, 60))) - y) * w
        per_word = np.bincount(local.ravel(), np.repeat(g / size, window), len(words))
        per_slot = np.bincount(own, per_word[of], 1 << SLOT_BITS)
        g_emb, g_soft, g_bias = per_slot[:, None] * soft[None, :], mean.T @ g, g.sum()
        s_emb[:] += g_emb**2
        s_soft[:] += g_soft**2
        s_bias += g_bias**2
        emb = emb - rate * g_emb / np.sqrt(s_emb)
        soft = soft - rate * g_soft / np.sqrt(s_soft)
        bias -= rate * g_bias / np.sqrt(s_bias)

    everything, even = np.arange(len(wins)), 1.0 / np.bincount(doc)[doc]
    for _ in range(start_epochs):
        step(everything, even * weight[doc] * 8)
    hard = np.zeros(len(wins), bool)
    for _ in range(epochs):
        strength = np.append(np.bincount(owner, (emb @ soft)[flat], len(index)), 0.0)
        logit = strength[wins].sum(1) / np.maximum(count[wins].sum(1), 1.0)
        best = np.flatnonzero(logit == np.maximum.reduceat(logit, first)[doc])
        best = best[np.unique(doc[best], return_index=True)[1]]
        hard[best[label[doc[best]] == 0]] = True
        use = np.concatenate([best[label[doc[best]] == 1], np.flatnonzero(hard)])
        step(use, weight[doc[use]])
    return SubwordModel((emb @ soft).astype(np.float32), float(bias), window)


def train_toxicity(docs: DataFrame, labels: DataFrame, label: str = "toxic", fold: tuple[int, int] = (3, 1), max_rows: int = 3000, max_bytes: int = 16 << 20) -> SubwordModel:
    """Fits on at most ``max_rows`` labelled texts, together about ``max_bytes``, outside the held-out fold."""
    rows = labelled_sample(docs, labels, label, fold, max_rows, max_bytes, 23).select("doc_id", "label", "text").toArrow().sort_by("doc_id")
    zero, one = class_shares(labels, label, fold)
    return fit_subwords(rows["text"].to_pylist(), rows["label"].to_pylist(), zero_share=zero / (zero + one) if zero and one else None)


def _scored(shared):
    def run(batches):
        scorer = shared.value.scorer()
        for batch in batches:
            scores = [scorer.score(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64())], ["doc_id", "score"])

    return run


def score_toxicity(docs: DataFrame, model: SubwordModel) -> DataFrame:
    """(doc_id, score) for every row of ``docs``, over the whole text.

    Null and empty texts get the score of a window without words; rows with a
    null id keep it; repeated rows are scored each; other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_scored(shared), "doc_id long, score double")
