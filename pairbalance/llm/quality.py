"""A quality classifier: logistic regression over hashed word n-grams, fitted by follow-the-regularised-leader updates.

A text is cut into words and runs of signs. Its features are hashed single tokens, neighbouring pairs of tokens,
and pairs of token shapes (capitals, digits, signs, a token like the one before), each weighted by its share among
the features; the score is the logistic of one sparse dot product over the whole text.

The model is fitted on the driver on at most ``most`` labelled rows, picked by a hash of their id among all
rows outside the held-out fold. Labels, language, source and id are never inputs of a score.

Defined results: null counts as empty; an empty text has the score of the bias alone; with no labelled row every
score is 0.5; texts of any length are scored whole; rows of repeated ids are scored each by its own text; an empty table
gives an empty result; other columns of the input are ignored, or pass through keep_good(), whatever their names.
"""

from __future__ import annotations

import re
import uuid

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from .common import Bounded, filled, filter_rows, fold_of, give_back, map_columns, once_per_worker, sample_rows
from .hashing import CACHED_BYTES, GOLDEN, mix, runs

SAMPLE_ROWS = 8_000
BITS = 18
SCALE = 24.0
THRESHOLD = 0.7
HELD_OUT_FOLDS, HELD_OUT = 4, 2
TOKEN = re.compile(r"\w+|[^\w\s]+")


def _packed(token: str) -> int:
    """A hash of the token, its shape in the lowest four bits."""
    if token.isalpha():
        shape = 1 if token.islower() else 2 if len(token) > 1 and token.isupper() else 3 if token[1:].islower() or len(token) == 1 else 4
    elif token[0].isalnum():
        shape = 5 if token.isdigit() else 6
    else:
        shape = 7 + min(len(token), 4) + 4 * (token[0] in ".,;:'\"-!?()") if len(token) < 5 else 15
    return xxhash.xxh3_64_intdigest(token) & ~15 | min(shape, 15)


class Featurizer:
    """Indexes of the features of a text, with repeats."""

    def __init__(self, bits: int = BITS):
        self.mask = np.uint64((1 << bits) - 1)
        self.known = Bounded(_packed, CACHED_BYTES)

    def __call__(self, text: str) -> np.ndarray:
        tokens = TOKEN.findall(text)
        h = np.fromiter(map(self.known.__getitem__, tokens), np.uint64, len(tokens))
        if not len(h):
            return np.zeros(0, np.int64)
        shape = h & np.uint64(15)
        with np.errstate(over="ignore"):
            pairs = (shape[:-1] * np.uint64(16) + shape[1:] + np.uint64(512) * (h[:-1] == h[1:])) * GOLDEN
        return (np.concatenate([mix(h), runs(h, 2), mix(pairs)]) & self.mask).astype(np.int64)


def fit(examples: list[tuple[str, int]], bits: int = BITS, epochs: int = 3, rate: float = 0.4, l1: float = 1e-4, l2: float = 1e-3) -> tuple[np.ndarray, float]:
    """Weights and bias. Each step adapts its rate to a coordinate's past gradients; weights are solved lazily."""
    features, size = Featurizer(bits), 1 << bits
    rows = []
    for text, label in examples:
        index, counts = np.unique(features(text), return_counts=True)
        index = np.append(index, size).astype(np.int32)  # the bias comes last
        value = np.append(counts * (SCALE / max(1, counts.sum())), 1.0).astype(np.float32)
        rows.append((index, value, float(label)))
    z, n = np.zeros(size + 1), np.zeros(size + 1)

    def weights(index: np.ndarray) -> np.ndarray:
        zi = z[index]
        return np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((1.0 + np.sqrt(n[index])) / rate + l2))

    order = np.random.default_rng(7)
    for _ in range(epochs):
        for k in order.permutation(len(rows)):
            index, value, label = rows[k]
            w = weights(index)
            gradient = (1.0 / (1.0 + np.exp(-np.clip(w @ value, -35, 35))) - label) * value
            grown = n[index] + gradient**2
            z[index] += gradient - (np.sqrt(grown) - np.sqrt(n[index])) / rate * w
            n[index] = grown
    solved = weights(np.arange(size + 1))
    return solved[:-1].astype(np.float32), float(solved[-1])


def training_sample(docs: DataFrame, labels: DataFrame, most: int = SAMPLE_ROWS, id_column: str = "doc_id", text_column: str = "text", label_column: str = "quality") -> list[tuple[str, int]]:
    """At most ``most`` labelled texts outside the held-out fold, by a hash of their ids."""
    known = labels.select(F.col(id_column).alias("id"), F.col(label_column).cast("int").alias("label")).where("id IS NOT NULL AND label IN (0, 1)")
    picked = known.where(fold_of("id", HELD_OUT_FOLDS) != HELD_OUT).orderBy(F.xxhash64("id"), "id", "label").limit(most)
    rows = sample_rows(docs, picked, id_column, text_column)
    return [(r[1], r[2]) for r in sorted(rows)]


class Scorer:
    """Scores texts in a worker with broadcast weights."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias
        self.features = Featurizer(int(np.log2(len(weights))))

    def __call__(self, text: str | None) -> float:
        index = self.features(text or "")
        logit = self.bias + (SCALE * float(self.weights[index].mean(dtype=np.float64)) if len(index) else 0.0)
        return float(1.0 / (1.0 + np.exp(-np.clip(logit, -35, 35))))


def _shared_scorer(docs: DataFrame, labels: DataFrame, most: int, id_column: str, text_column: str):
    model = docs.sparkSession.sparkContext.broadcast(fit(training_sample(docs, labels, most, id_column, text_column)))
    give_back()
    key = f"quality-{uuid.uuid4().hex}"
    return lambda: once_per_worker(key, lambda: Scorer(*model.value))


SCORES = StructType([StructField("doc_id", LongType()), StructField("fold", LongType()), StructField("score", DoubleType())])


def score_documents(docs: DataFrame, labels: DataFrame, most: int = SAMPLE_ROWS, threshold: float = THRESHOLD, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs."""
    scorer = _shared_scorer(docs, labels, most, id_column, text_column)

    def run(columns: list) -> list:
        score = scorer()
        return [columns[0], columns[1], [score(t) for t in columns[2].to_pylist()]]

    rows = docs.select(F.col(id_column).cast("long"), fold_of(id_column, HELD_OUT_FOLDS).cast("long"), filled(text_column))
    return map_columns(rows, SCORES, run).select(
        "doc_id", (F.col("fold") == HELD_OUT).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted")
    )


def keep_good(docs: DataFrame, labels: DataFrame, most: int = SAMPLE_ROWS, threshold: float = THRESHOLD, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, whose score reaches the threshold."""
    scorer = _shared_scorer(docs, labels, most, id_column, text_column)

    def keep(batch) -> list[bool]:
        score = scorer()
        return [score(t) >= threshold for t in batch.column(text_column).to_pylist()]

    return filter_rows(docs, keep)
