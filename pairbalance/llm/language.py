"""Language identification: averaged hashed subword embeddings under a linear softmax, with calibrated rejection.

Every word of letters gives its character n-grams of three to five, with word ends marked, and itself; each is
hashed to a row of an embedding table. A text is the mean of its rows, and a linear layer with a softmax gives the
languages. Both layers are fitted in numpy by stochastic gradient descent on a bounded sample: SAMPLE_ROWS rows, picked
by a hash of their ids, and of each SEGMENTS_PER_ROW segments of SEGMENT_WORDS words, picked at random; a temperature is then fitted on segments set aside, and the score below which a prediction counts as rejected
is the one that the surest ``1 - reject_share`` of the right predictions among them reach.

As scores are linear before the softmax, a word's share is a sum over its subwords, kept in a bounded cache, so a
whole text costs one look-up a word.

Defined results: null, empty and letterless texts are ``und`` with score 0; without a labelled row all are; ties go
to the language first in order; texts of any length are judged whole; rows of repeated ids are judged each by its own
text; an empty table gives an empty result; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import re
import uuid
from sys import getsizeof

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, LongType, StringType, StructField, StructType

from .common import Bounded, filled, fold_of, give_back, map_columns, once_per_worker, sample_rows
from .hashing import GOLDEN, mix, runs

SAMPLE_ROWS = 3_000
BITS = 15
WIDTH = 16
CACHED_BYTES = 32 << 20
SEGMENT_WORDS = 40
SEGMENTS_PER_ROW = 4
HELD_OUT_FOLDS = 5
WORD = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"


def subwords(words: list[str], bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the n-grams of each word and of the word itself, word after word, and how many each has."""
    codes = np.frombuffer("".join(f"<{w}>" for w in words).encode("utf-32-le"), np.uint32).astype(np.uint64)
    sizes = np.array([len(w) + 2 for w in words], np.int64)
    owner = np.repeat(np.arange(len(words)), sizes)
    starts = np.cumsum(sizes) - sizes
    within = (np.arange(len(codes)) - starts[owner]).astype(np.uint64)
    hashes = [np.add.reduceat(mix(codes + GOLDEN * (within + np.uint64(1))), starts)]
    owners = [np.arange(len(words))]
    for n in (3, 4, 5):
        first = owner[: max(0, len(codes) - n + 1)]
        inside = first == owner[n - 1 :][: len(first)]
        hashes.append(runs(codes, n)[inside] + np.uint64(n))
        owners.append(first[inside])
    owners = np.concatenate(owners)
    order = np.argsort(owners, kind="stable")
    rows = (mix(np.concatenate(hashes)[order]) & np.uint64((1 << bits) - 1)).astype(np.int64)
    return rows, np.bincount(owners, minlength=len(words))


class Model:
    """languages, the product of both layers for each row (rows x languages), the bias, temperature and rejection score."""

    def __init__(self, languages: list[str], table: np.ndarray, bias: np.ndarray, temperature: float, reject: float):
        self.languages, self.table, self.bias, self.temperature, self.reject = languages, table, bias, temperature, reject


def _segments(texts: list[str], rng: np.random.Generator, per_row: int) -> list[tuple[int, np.ndarray]]:
    out = []
    for k, text in enumerate(texts):
        words = WORD.findall(text.lower())
        starts = np.arange(0, len(words), SEGMENT_WORDS)
        for s in rng.permutation(starts)[:per_row]:
            out.append((k, subwords(words[s : s + SEGMENT_WORDS])[0]))
    return out


def fit(examples: list[tuple[str, str]], epochs: int = 4, rate: float = 0.5, batch: int = 16, reject_share: float = 0.01, segments_per_row: int = SEGMENTS_PER_ROW) -> Model:
    """Fit both layers, then the temperature and the rejection score on a tenth of the rows set aside."""
    languages = sorted({lang for _, lang in examples})
    rng = np.random.default_rng(11)
    size = 1 << BITS
    if not languages:
        return Model([], np.zeros((size, 0), np.float32), np.zeros(0), 1.0, 0.0)
    label = {lang: i for i, lang in enumerate(languages)}
    segments = _segments([t for t, _ in examples], rng, segments_per_row)
    y = np.array([label[examples[k][1]] for k, _ in segments], np.int64)
    aside = np.array([k % 10 == 0 for k, _ in segments], bool)
    if aside.all() or not aside.any():
        aside = np.zeros(len(segments), bool)
    table = rng.uniform(-1 / WIDTH, 1 / WIDTH, (size, WIDTH)).astype(np.float32)
    layer, bias = np.zeros((WIDTH, len(languages)), np.float32), np.zeros(len(languages), np.float32)
    chosen = np.flatnonzero(~aside)
    total, step = max(1, epochs * len(chosen)), 0
    for _ in range(epochs):
        for part in np.array_split(rng.permutation(chosen), max(1, len(chosen) // batch)):
            if not len(part):
                continue
            rows = np.concatenate([segments[i][1] for i in part])
            lengths = np.array([len(segments[i][1]) for i in part])
            starts = np.r_[0, np.cumsum(lengths)[:-1]]
            mean = np.add.reduceat(table[rows], starts, axis=0) / lengths[:, None]
            p = _softmax(mean @ layer + bias)
            p[np.arange(len(part)), y[part]] -= 1.0
            now = rate * (1 - step / total)
            back = p @ layer.T / lengths[:, None]
            layer -= now * mean.T @ p
            bias -= now * 0.1 * p.sum(0)
            np.add.at(table, rows, np.repeat((-now * back).astype(np.float32), lengths, axis=0))
            step += len(part)
    product = (table @ layer).astype(np.float32)
    judged = np.flatnonzero(aside) if aside.any() else chosen
    logits = np.array([product[segments[i][1]].mean(0) + bias for i in judged]) if len(judged) else np.zeros((0, len(languages)))
    temperature, reject = _calibrate(logits, y[judged], reject_share)
    return Model(languages, product, bias.astype(np.float64), temperature, reject)


def _softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def _calibrate(logits: np.ndarray, y: np.ndarray, share: float) -> tuple[float, float]:
    """The temperature of least log loss, and the score that all but a share of the right predictions reach."""
    if not len(y):
        return 1.0, 0.0
    tried = np.geomspace(0.1, 10, 41)
    loss = [-np.log(np.maximum(_softmax(logits / t)[np.arange(len(y)), y], 1e-12)).mean() for t in tried]
    t = float(tried[int(np.argmin(loss))])
    p = _softmax(logits / t)
    right = p.max(1)[p.argmax(1) == y]
    return t, float(np.quantile(right, share)) if len(right) else 0.0


class Predictor:
    """Predicts in a worker with a broadcast model; word sums are rows of a table that starts afresh after so many bytes."""

    def __init__(self, model: Model, most: int = CACHED_BYTES):
        self.model, self.most, self.held = model, most, 0
        self.row = Bounded.ENTRY + 8 * (len(model.languages) + 1)
        self.at: dict[str, int] = {}
        self.sums = np.zeros((1024, len(model.languages) + 1))

    def _learn(self, words: list[str]) -> None:
        """Sums of words that have none yet."""
        self.held += sum(map(getsizeof, words)) + self.row * len(words)
        first = len(self.at)
        while first + len(words) > len(self.sums):
            self.sums = np.vstack([self.sums, np.zeros_like(self.sums)])
        rows, counts = subwords(words)
        self.sums[first : first + len(words), :-1] = np.add.reduceat(self.model.table[rows], np.cumsum(counts) - counts, axis=0, dtype=np.float64)
        self.sums[first : first + len(words), -1] = counts
        self.at.update(zip(words, range(first, first + len(words)), strict=True))

    def __call__(self, texts: list[str | None]) -> list[tuple[str, float, bool]]:
        split = [WORD.findall((t or "").lower()) for t in texts]
        if not self.model.languages:
            return [(UNKNOWN, 0.0, True)] * len(texts)
        wanted = {w for words in split for w in words}
        if self.held > self.most:
            self.at.clear()
            self.sums, self.held = self.sums[:1024].copy(), 0
        if fresh := sorted(wanted - self.at.keys()):
            self._learn(fresh)
        at, out = self.at.__getitem__, []
        for words in split:
            if not words:
                out.append((UNKNOWN, 0.0, True))
                continue
            total = self.sums[np.fromiter(map(at, words), np.int64, len(words))].sum(0)
            p = _softmax((total[:-1] / total[-1] + self.model.bias)[None] / self.model.temperature)[0]
            best = int(p.argmax())
            out.append((self.model.languages[best], float(p[best]), bool(p[best] < self.model.reject)))
        return out


PREDICTIONS = StructType([StructField("doc_id", LongType()), StructField("held_out", BooleanType()), StructField("lang_pred", StringType()), StructField("score", DoubleType()), StructField("rejected", BooleanType())])


def training_sample(docs: DataFrame, most: int = SAMPLE_ROWS, id_column: str = "doc_id", text_column: str = "text", lang_column: str = "lang") -> list[tuple[str, str]]:
    """At most ``most`` texts with a language outside the held-out fold, by a hash of their ids."""
    known = docs.select(F.col(id_column).alias("id"), F.col(lang_column).alias("label")).where("id IS NOT NULL AND label IS NOT NULL")
    picked = known.where(fold_of("id", HELD_OUT_FOLDS) != 0).orderBy(F.xxhash64("id"), "id", "label").limit(most)
    return [(r[1], r[2]) for r in sorted(sample_rows(docs, picked, id_column, text_column))]


def identify(docs: DataFrame, most: int = SAMPLE_ROWS, id_column: str = "doc_id", text_column: str = "text", lang_column: str = "lang") -> DataFrame:
    """doc_id, held_out, lang_pred, score and rejected for every row of docs."""
    model = docs.sparkSession.sparkContext.broadcast(fit(training_sample(docs, most, id_column, text_column, lang_column)))
    give_back()
    key = f"language-{uuid.uuid4().hex}"

    def run(columns: list) -> list:
        predict = once_per_worker(key, lambda: Predictor(model.value))
        found = predict(columns[2].to_pylist())
        return [columns[0], columns[1], *map(list, zip(*found, strict=True))]

    rows = docs.select(F.col(id_column).cast("long"), fold_of(id_column, HELD_OUT_FOLDS) == 0, filled(text_column))
    return map_columns(rows, PREDICTIONS, run)
