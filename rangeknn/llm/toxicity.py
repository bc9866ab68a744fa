"""Toxicity scores: logistic regression over hashed words, word pairs and skip-grams,
trained by the follow-the-regularised-leader (proximal) rule.

Every coordinate has its own learning rate and an L1 threshold that keeps rare, uninformative
features at exactly zero; what is broadcast are the few weights that are left, at most
2 ** bits of them whatever the corpus.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import trimmed

_WORD = re.compile(r"\w+")
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)


@dataclass(frozen=True)
class Settings:
    """alpha, beta: learning rate; l1, l2: regularisation; skip: widest gap of a skip-gram;
    positive_weight: of the rarer label 1 in the loss.

    ``max_train`` bounds the labelled rows that are fitted (all of them are candidates; those
    with the smallest hash of their id are taken, the same at every size of the corpus). The other values
    have the least log loss of 72 settings under ``cross_validated`` on training rows (README).
    """

    bits: int = 20
    skip: int = 1
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 12.0
    l2: float = 0.5
    epochs: int = 4
    positive_weight: float = 2.0
    max_train: int = 20_000


class Hasher:
    """Feature numbers of a text: of its words, neighbours and pairs a few words apart."""

    def __init__(self, settings: Settings, limit: int = 120_000) -> None:
        self.settings, self.limit, self.memo = settings, limit, {}

    def features(self, text: str) -> np.ndarray:
        words, memo = _WORD.findall(text.lower()), self.memo
        try:
            h = np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))
        except KeyError:
            if len(memo) > self.limit:
                memo.clear()
            for w in words:
                if w not in memo:
                    memo[w] = xxhash.xxh3_64_intdigest(w)
            h = np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))
        parts = [h * _A]
        for gap in range(1, min(self.settings.skip + 2, len(h))):
            parts.append((h[:-gap] * _B) ^ (h[gap:] * _C + np.uint64(min(gap, 2))))
        mixed = np.concatenate(parts)
        return ((mixed ^ (mixed >> np.uint64(29))) * _A >> np.uint64(64 - self.settings.bits)).astype(np.int64)


class FtrlProximal:
    def __init__(self, settings: Settings) -> None:
        size = (1 << settings.bits) + 1  # the last is the intercept, which has no L1
        self.s, self.z, self.n = settings, np.zeros(size), np.zeros(size)
        self.l1 = np.full(size, settings.l1)
        self.l1[-1] = 0.0

    def weights(self, at: np.ndarray) -> np.ndarray:
        z, l1 = self.z[at], self.l1[at]
        w = -(z - np.sign(z) * l1) / ((self.s.beta + np.sqrt(self.n[at])) / self.s.alpha + self.s.l2)
        return np.where(np.abs(z) <= l1, 0.0, w)

    def update(self, features: np.ndarray, label: int) -> None:
        at = np.append(np.unique(features), len(self.z) - 1)
        w = self.weights(at)
        g = (_sigmoid(float(w.sum())) - label) * (self.s.positive_weight if label else 1.0)
        sigma = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.s.alpha
        self.z[at] += g - sigma * w
        self.n[at] += g * g

    def sparse(self) -> tuple[np.ndarray, np.ndarray]:
        w = self.weights(np.arange(len(self.z)))
        at = np.flatnonzero(w)
        return at, w[at]


def _sigmoid(x: float) -> float:
    return 1.0 / (1.0 + math.exp(-x)) if x >= 0 else 1.0 - 1.0 / (1.0 + math.exp(x))


def fitted(rows: list[tuple[np.ndarray, int]], settings: Settings) -> FtrlProximal:
    """The model after all epochs over rows of (distinct features, label), in their order."""
    model = FtrlProximal(settings)
    for _ in range(settings.epochs):
        for features, label in rows:
            model.update(features, label)
    return model


def cross_validated(texts: list[str], labels: list[int], folds: list[int], grid: list[Settings]) -> list[tuple[float, Settings]]:
    """(mean log loss, settings), best first: each fold is scored by a model of the others. For a bounded sample of
    training rows; held-out rows have no place in it."""
    out = []
    for settings in grid:
        hasher, loss = Hasher(settings), 0.0
        features = [np.unique(hasher.features(t)) for t in texts]
        for fold in sorted(set(folds)):
            at, w = fitted([(x, y) for x, y, f in zip(features, labels, folds, strict=True) if f != fold], settings).sparse()
            dense = np.zeros((1 << settings.bits) + 1)
            dense[at] = w
            for x, y, f in zip(features, labels, folds, strict=True):
                if f == fold:
                    margin = float(dense[x].sum() + dense[-1]) * (1 if y else -1)
                    loss += math.log1p(math.exp(-margin)) if margin > -30 else -margin
        out.append((loss / max(len(texts), 1), settings))
    return sorted(out, key=lambda x: x[0])


def train(docs: DataFrame, labels: DataFrame, settings: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> list[tuple[int, float]]:
    """Sparse weights (feature, weight) from labelled rows.

    Rows without label or text are left out; of several labels of an id the largest counts;
    ids without a document are ignored. No rows: no weights, and every score is one half.
    The sample of ids (``max_train`` at most) is broadcast, so documents are not shuffled.
    """
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).cast("int").alias("label"))
    order = F.xxhash64(F.col("id").cast("string"))
    sample = known.select("id", "label", order.alias("turn")).orderBy("turn", "id").limit(settings.max_train)
    texts = docs.where(F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    hasher = Hasher(settings)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [np.unique(hasher.features(x)).astype(np.int32) for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("turn"), batch.column("id"), batch.column("label"), pa.array(found, pa.list_(pa.int32()))], names=["turn", "id", "label", "features"])

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for batch in batches:
            at, flat = batch.column("features").offsets.to_numpy(), batch.column("features").values.to_numpy()
            rows += zip(batch.column("turn").to_pylist(), batch.column("id").to_pylist(), batch.column("label").to_pylist(), [flat[a:b] for a, b in zip(at[:-1], at[1:], strict=True)], strict=True)
        rows.sort(key=lambda r: r[:3])
        if rows:
            at, w = fitted([(features, label) for *_, label, features in rows], settings).sparse()
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(w, pa.float64())], names=["feature", "weight"])

    id_type = docs.schema[id_col].dataType.simpleString()
    rows = texts.join(F.broadcast(sample), "id").mapInArrow(lambda b: trimmed(hashed(b)), f"turn bigint, id {id_type}, label int, features array<int>")
    return [tuple(r) for r in rows.repartition(1).mapInArrow(lambda b: trimmed(fit(b)), "feature bigint, weight double").collect()]


class Scorer:
    def __init__(self, weights: list[tuple[int, float]], settings: Settings) -> None:
        self.dense = np.zeros((1 << settings.bits) + 1)
        for at, w in weights:
            self.dense[at] = w
        self.used, self.hasher = self.dense != 0, Hasher(settings)

    def score(self, text: str | None) -> float:
        found = self.hasher.features(text or "")
        found = np.unique(found[self.used[found]])
        return _sigmoid(float(self.dense[found].sum() + self.dense[-1]))


def score(docs: DataFrame, weights: list[tuple[int, float]], settings: Settings = Settings(), text_col: str = "text", score_col: str = "score") -> DataFrame:
    """docs with a column score_col (0 to 1); null and empty texts get the intercept's score.

    Every row keeps its columns; a column that already has the name score_col is replaced.
    """
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value, settings)
        for batch in batches:
            scores = pa.array([scorer.score(x) for x in batch.column(text_col).to_pylist()], pa.float64())
            keep = [n for n in batch.schema.names if n != score_col]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in keep), scores], names=[*keep, score_col])

    kept = [f for f in docs.schema.fields if f.name != score_col]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), f"`{score_col}` double"])
    return docs.select(*(F.col(f"`{f.name}`") for f in kept)).mapInArrow(lambda b: trimmed(run(b)), schema)
