"""Benchmark decontamination by random-walk embedding and bit sampling.

A document holds an item if some passage of it is within ``share`` of the item's words in edits of words (deleted,
inserted or changed). Candidates come from windows of an item's size. A window's words are spelled out along a random
walk: at each step the current word is written down and a random bit of (step, word) says whether to go on to the
next. Two similar sequences fall into step again soon after an edit, so a few edits leave most places of the
walk equal. Each of the repetitions samples a few places of its own walk and looks them up among the same places of
the items of that size. The number of repetitions follows from the recall that is asked for at a given share of
places that differ. A candidate is verified by the exact edit distance between the item and the best passage of the
whole document.

Only windows that can match are embedded: an item of n words with k edits keeps a run of at least
ceil((n - k) / (k + 1)) of its words, so each window starts where such a run of words of an item would place it, and
up to k words to either side. This leaves no passage out.

Words are runs of letters and digits of the lower-case text. The benchmark travels to the tasks in blocks of about
``block_items`` items or BLOCK_BYTES of text, one pass over the documents for each block; with several blocks each pass
is written before the next block is fetched.

Defined results: null and empty texts and items hold nothing; equal items are each reported, an item without an id with
a null one; for each document and item the least distance and the first place where such a passage ends; texts of any
length are searched whole; repeated rows are searched each; an empty benchmark finds nothing, and empty documents give
an empty result; other columns pass through or are ignored, whatever their names.
"""

from __future__ import annotations

import math
import re
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, filled, filter_rows, once_per_worker, over_batches
from .hashing import GOLDEN, mix, runs

WORD = re.compile(r"[^\W_]+")
SHARE = 0.2
SAMPLED = 3
RECALL, DIFFERING = 0.99, 0.5
BLOCK_ITEMS = 20_000
BLOCK_BYTES = 32 << 20
LONGEST_RUN = 4


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def edits_allowed(n: int, share: float = SHARE) -> int:
    return math.floor(n * share)


def repetitions(recall: float = RECALL, differing: float = DIFFERING, sampled: int = SAMPLED) -> int:
    """How often to sample so that windows that differ in such a share of places meet with this chance."""
    return math.ceil(math.log(1 - recall) / math.log(1 - (1 - differing) ** sampled))


class BestPassage:
    """The least edit distance between a pattern and any passage of a text, by bit-parallel columns."""

    def __init__(self, pattern: list[int]):
        self.n = len(pattern)
        self.places: dict[int, int] = {}
        for i, c in enumerate(pattern):
            self.places[c] = self.places.get(c, 0) | 1 << i

    def __call__(self, text: list[int]) -> tuple[int, int]:
        """(distance, end) of the best passage that ends first."""
        full, top = (1 << self.n) - 1, 1 << (self.n - 1)
        up, down, score, best = full, 0, self.n, (self.n, 0)
        get = self.places.get
        for end, c in enumerate(text, 1):
            equal = get(c, 0)
            across = (((equal & up) + up) ^ up) | equal
            plus, minus = down | (full & ~(across | up)), up & across
            if plus & top:
                score += 1
            elif minus & top:
                score -= 1
            plus, minus = plus << 1 & full, minus << 1 & full
            keep = equal | down
            up, down = minus | (full & ~(keep | plus)), plus & keep
            if score < best[0]:
                best = (score, end)
        return best


class Benchmark:
    """A block of items in a worker: vocabulary, seeds, and the table of sampled walks."""

    def __init__(self, items: list[tuple[int, str]], share: float = SHARE, repeats: int | None = None, sampled: int = SAMPLED, seed: int = 5):
        split = [(i, words_of(t)) for i, t in items]
        split = [(i, w) for i, w in split if w]
        self.ids = [i for i, _ in split]
        self.vocabulary: dict[str, int] = {}
        self.items = [np.array([self.vocabulary.setdefault(x, len(self.vocabulary) + 1) for x in w], np.int64) for _, w in split]
        self.sizes = np.array([len(w) for w in self.items], np.int64)
        self.edits = np.array([edits_allowed(n, share) for n in self.sizes], np.int64)
        self.repeats = repetitions(sampled=sampled) if repeats is None else repeats
        rng = np.random.default_rng(seed)
        longest = int(self.sizes.max(initial=1))
        self.steps = rng.integers(1, 2**63, (self.repeats, 3 * longest), dtype=np.uint64)
        self.samples = rng.random((self.repeats, sampled))
        self.seeds = self._seeds()
        keys = self.walk_keys(self.items)
        owner = np.tile(np.arange(len(self.items)), (self.repeats, 1)).ravel()
        order = np.argsort(keys.ravel(), kind="stable")
        self.keys, self.owner = keys.ravel()[order], owner[order]
        self.checkers: dict[int, BestPassage] = {}

    def _seeds(self) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """By length of run: sorted hashes of the items' runs, with the item and the place of each."""
        found: dict[int, list] = {}
        for k, w in enumerate(self.items):
            n, e = len(w), int(self.edits[k])
            q = max(1, min(LONGEST_RUN, math.ceil((n - e) / (e + 1))))
            h = runs(w.astype(np.uint64), q)
            found.setdefault(q, []).append((h, np.full(len(h), k), np.arange(len(h))))
        out = {}
        for q, parts in found.items():
            h, item, place = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(h, kind="stable")
            out[q] = (h[order], item[order], place[order])
        return out

    def walk_keys(self, windows: list[np.ndarray]) -> np.ndarray:
        """repeats x windows: the hash of the sampled places of each walk; the window's size is part of it."""
        sizes = np.array([len(w) for w in windows], np.int64)
        keys = np.broadcast_to((sizes.astype(np.uint64) * GOLDEN)[None], (self.repeats, len(windows))).copy()
        if not len(windows):
            return keys
        grid = np.zeros((len(windows), int(sizes.max()) + 1), np.uint64)  # 0 stands behind the end
        for k, w in enumerate(windows):
            grid[k, : len(w)] = w.astype(np.uint64)
        at = np.zeros((self.repeats, len(windows)), np.int64)
        rows = np.arange(len(windows))[None]
        taken = np.sort((self.samples[:, :, None] * (3 * sizes)[None, None]).astype(np.int64), axis=1)
        with np.errstate(over="ignore"):
            keys += np.arange(1, self.repeats + 1, dtype=np.uint64)[:, None] * np.uint64(0xD6E8FEB86659FD93)
            for j in range(int(taken.max()) + 1):
                symbol = grid[rows, at]
                hit = (taken == j).any(axis=1)
                if hit.any():
                    times = (taken == j).sum(axis=1)
                    for t in range(1, int(times.max()) + 1):
                        keys = np.where(times >= t, mix(keys * GOLDEN + symbol), keys)
                bit = mix(symbol + self.steps[:, j][:, None]) & np.uint64(1)
                at = np.minimum(at + bit.astype(np.int64), sizes[None])
        return keys

    def placed(self, words: np.ndarray) -> list[tuple[int, int]]:
        """(start, size) of the windows of a document that some run of an item's words points at."""
        out: set[tuple[int, int]] = set()
        for q, (hashes, item, place) in self.seeds.items():
            if len(words) < q:
                continue
            inside = words > 0
            whole = np.flatnonzero(np.convolve(inside, np.ones(q, np.int64), "valid") == q)
            if not len(whole):
                continue
            h = runs(words.astype(np.uint64), q)[whole]
            low, high = np.searchsorted(hashes, h), np.searchsorted(hashes, h, "right")
            for p, a, b in zip(whole[high > low].tolist(), low[high > low].tolist(), high[high > low].tolist(), strict=True):
                for i in range(a, b):
                    n, e = int(self.sizes[item[i]]), int(self.edits[item[i]])
                    start = p - int(place[i])
                    out.update((s, n) for s in range(max(0, start - e), start + e + 1) if s < len(words))
        return sorted(out)

    def hits(self, texts: list[str | None]) -> list[list[tuple[int, int, int, int]]]:
        """For each text: (item id, distance, end word, item words), by item."""
        get = self.vocabulary.get
        docs = []
        for t in texts:
            split = words_of(t)
            docs.append(np.fromiter((get(x, 0) for x in split), np.int64, len(split)))
        windows = [(k, s, n) for k, w in enumerate(docs) for s, n in (self.placed(w) if self.items else [])]
        pairs: set[tuple[int, int]] = set()
        for at in range(0, len(windows), 4000):
            part = windows[at : at + 4000]
            keys = self.walk_keys([self._window(docs[k], s, n) for k, s, n in part])
            low, high = np.searchsorted(self.keys, keys), np.searchsorted(self.keys, keys, "right")
            for r, c in zip(*np.nonzero(high > low), strict=True):
                pairs.update((part[c][0], int(i)) for i in self.owner[low[r, c] : high[r, c]])
        found: list[list] = [[] for _ in texts]
        for k, i in sorted(pairs):
            if i not in self.checkers:
                self.checkers[i] = BestPassage(self.items[i].tolist())
            distance, end = self.checkers[i](docs[k].tolist())
            if distance <= self.edits[i]:
                found[k].append((self.ids[i], distance, end, int(self.sizes[i])))
        return found

    @staticmethod
    def _window(words: np.ndarray, start: int, n: int) -> np.ndarray:
        part = words[start : start + n]
        return part if len(part) == n else np.concatenate([part, np.zeros(n - len(part), np.int64)])


HITS = "doc_id long, item_id long, distance long, end_word long, item_words long"


def _blocks(benchmark: DataFrame, item_column: str, text_column: str, most: int) -> Iterator[tuple[str, Broadcast, bool]]:
    """A key, the broadcast items of a block, and whether it is the only one; blocks are made by a hash of the item.
    A block is fetched when the one before has been used and destroyed, so the driver holds one at a time."""
    rows = benchmark.select(F.col(item_column).cast("long").alias("id"), filled(text_column).alias("text"))
    n, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    count = max(1, math.ceil(n / most), math.ceil(size / BLOCK_BYTES))
    for b in range(count):
        part = rows if count == 1 else rows.where(F.pmod(F.xxhash64("id", "text"), F.lit(count)) == b)
        items = sorted(((r.id, r.text) for r in part.collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1]))
        yield f"benchmark-{uuid.uuid4().hex}", benchmark.sparkSession.sparkContext.broadcast(items), count == 1


def contaminated(docs: DataFrame, benchmark: DataFrame, id_column: str = "doc_id", text_column: str = "text", item_column: str = "item_id", item_text: str = "text", block_items: int = BLOCK_ITEMS, share: float = SHARE) -> DataFrame:
    """One row for each document and item it holds: doc_id, item_id, distance, end_word, item_words."""
    rows = docs.select(F.col(id_column).cast("long"), filled(text_column))
    out = None
    for key, items, alone in _blocks(benchmark, item_column, item_text, block_items):

        def find(batch: pa.RecordBatch, key: str = key, items: Broadcast = items) -> pa.RecordBatch:
            found = once_per_worker(key, lambda: Benchmark(items.value, share)).hits(batch.column(1).to_pylist())
            flat = [(d, *hit) for d, hits in zip(batch.column(0).to_pylist(), found, strict=True) for hit in hits]
            return pa.RecordBatch.from_arrays([pa.array([f[i] for f in flat], pa.int64()) for i in range(5)], ["doc_id", "item_id", "distance", "end_word", "item_words"])

        part = over_batches(rows, HITS, find)
        if not alone:
            part = cut(part, "hits")
            items.destroy()
        out = part if out is None else out.unionByName(part)
    return out


def without_contaminated(docs: DataFrame, benchmark: DataFrame, text_column: str = "text", item_column: str = "item_id", item_text: str = "text", block_items: int = BLOCK_ITEMS, share: float = SHARE) -> DataFrame:
    """The rows of docs that hold no item, with all their columns."""
    for key, items, alone in _blocks(benchmark, item_column, item_text, block_items):

        def keep(batch: pa.RecordBatch, key: str = key, items: Broadcast = items) -> list[bool]:
            known = once_per_worker(key, lambda: Benchmark(items.value, share))
            return [not found for found in known.hits(batch.column(text_column).to_pylist())]

        docs = filter_rows(docs, keep)
        if not alone:
            docs = cut(docs, "clean")
            items.destroy()
    return docs
