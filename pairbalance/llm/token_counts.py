"""Token counts by rank-synchronous merging of ragged arrays.

Distinct pre-tokens of a batch become one flat array of symbols with the bounds of each. In every round each
sequence finds the lowest rank among its neighbouring pairs and merges all pairs of that rank at once; only
pairs beside a merge are looked up again. When no sequence has a pair left, the surviving symbols are counted.

Merging equal pairs at once equals merging them one by one from the left unless a fresh pair has a lower rank
than the one just merged, or the rank is shared by different pieces; such sequences are finished one by one.

Defined results: null counts as empty with no bytes and no tokens; texts of any length are counted whole; repeated rows
are counted each; an empty table gives an empty result; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import heapq
from sys import getsizeof

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .common import Bounded, filled, map_columns
from .pieces import Pieces, model_bytes, per_worker, pretokens

CACHED_WORDS = 32 << 20  # bytes
LIMIT = 4096
NONE = np.iinfo(np.int64).max


class RankMerger:
    """Counts the pieces of pre-tokens with a model given as bytes."""

    def __init__(self, model: bytes):
        v = self.vocabulary = Pieces(model)
        pairs = sorted(
            (v.ids[p[:i]] << 32 | v.ids[p[i:]], v.rank[piece], piece)
            for p, piece in v.ids.items()
            for i in range(1, len(p))
            if p[:i] in v.ids and p[i:] in v.ids
        )
        self.keys = np.array([x[0] for x in pairs], np.int64)
        self.ranks = np.array([x[1] for x in pairs], np.int64)
        self.joined = np.array([x[2] for x in pairs], np.int64)
        self.counts: dict[str, int] = {}
        self.held = 0

    def look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and piece of each pair; NONE where there is no such piece or a symbol is no piece (-1)."""
        key = np.where((left < 0) | (right < 0), -1, left << 32 | right)
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], NONE), self.joined[at]

    def count(self, words: list[str]) -> list[int]:
        """Tokens of each word; a character that is no piece counts as its bytes."""
        ids = self.vocabulary.ids
        extra = np.zeros(len(words), np.int64)
        flat: list[int] = []
        bounds = [0]
        for k, word in enumerate(words):
            for ch in word:
                piece = ids.get(ch, -1)
                if piece < 0:
                    extra[k] += len(ch.encode()) - 1
                flat.append(piece)
            bounds.append(len(flat))
        symbols, owner = np.array(flat, np.int64), np.repeat(np.arange(len(words)), np.diff(bounds))
        result = np.diff(bounds)
        shared = np.array(sorted(self.vocabulary.shared), np.int64)
        rank, joined = self._pairs(symbols, owner)
        while len(symbols):
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            lengths = np.diff(np.r_[starts, len(owner)])
            best = np.repeat(np.minimum.reduceat(rank, starts), lengths)
            ends = best == NONE
            one_by_one = np.isin(best, shared)
            take = (rank == best) & ~ends & ~one_by_one
            # of pairs that overlap, the leftmost, third, fifth ... are merged
            runs = np.flatnonzero(take & ~np.r_[False, take[:-1]])
            if len(runs):
                take &= self._behind(take, runs) % 2 == 0
            into = np.flatnonzero(take)
            symbols[into] = joined[into]
            keep = ~np.r_[False, take[:-1]]
            touched = take | np.r_[take[1:], False]
            touched |= np.r_[take[2:], False, False][: len(take)]
            old = best
            symbols, owner, rank, joined, touched, ends, one_by_one, old = (x[keep] for x in (symbols, owner, rank, joined, touched, ends, one_by_one, old))
            at = np.flatnonzero(touched)
            if len(at):
                rank[at], joined[at] = self._pairs(symbols, owner, at)
                undone = np.zeros(len(words), bool)
                undone[owner[at][(rank[at] < old[at])]] = True
                one_by_one |= undone[owner]
            if ends.any():
                done, sizes = np.unique(owner[ends], return_counts=True)
                result[done] = sizes
            if one_by_one.any():
                for k in np.unique(owner[one_by_one]):
                    result[k] = len(self.one_by_one(words[k]))
            live = ~(ends | one_by_one)
            if not live.all():
                symbols, owner, rank, joined = symbols[live], owner[live], rank[live], joined[live]
        return (result + extra).tolist()

    @staticmethod
    def _behind(take: np.ndarray, runs: np.ndarray) -> np.ndarray:
        """How far each place is behind the start of the run of merges before it."""
        out = np.zeros(len(take), np.int64)
        out[runs[0] :] = np.arange(runs[0], len(take)) - np.repeat(runs, np.diff(np.r_[runs, len(take)]))
        return out

    def _pairs(self, symbols: np.ndarray, owner: np.ndarray, at: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        at = np.arange(len(symbols)) if at is None else at
        after = np.minimum(at + 1, len(symbols) - 1)
        rank, joined = self.look_up(symbols[at], symbols[after])
        rank[(owner[at] != owner[after]) | (after == at)] = NONE
        return rank, joined

    def one_by_one(self, word: str) -> list[str]:
        """The same by a heap of pairs, the best rank first and then the leftmost."""
        ids, rank = self.vocabulary.ids, self.vocabulary.rank
        parts: list = list(word)
        after = list(range(1, len(parts) + 1))
        before = list(range(-1, len(parts) - 1))
        heap: list = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] < len(parts):
                piece = ids.get(text := parts[i] + parts[after[i]])
                if piece is not None:
                    heapq.heappush(heap, (rank[piece], i, text))

        for i in range(len(parts)):
            offer(i)
        while heap:
            _, i, text = heapq.heappop(heap)
            if parts[i] is None or (j := after[i]) >= len(parts) or parts[i] + parts[j] != text:
                continue
            parts[i], parts[j] = text, None
            after[i] = after[j]
            if after[i] < len(parts):
                before[after[i]] = i
            offer(before[i])
            offer(i)
        return [p for p in parts if p is not None]

    def totals(self, texts: list[str]) -> list[int]:
        """Tokens of each text."""
        split = [pretokens(t) for t in texts]
        known = self.counts
        if self.held > CACHED_WORDS:
            known.clear()
            self.held = 0
        fresh = list({w for words in split for w in words if w not in known})
        self.held += sum(getsizeof(w) + Bounded.ENTRY for w in fresh)
        for i in range(0, len(fresh), 20_000):
            part = fresh[i : i + 20_000]
            known.update(zip(part, self.count(part), strict=True))
        return [sum(map(known.__getitem__, words)) for words in split]


COUNTS = StructType([StructField("doc_id", LongType()), StructField("n_bytes", LongType()), StructField("n_tokens", LongType())])


def count_tokens(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", model_path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens and whether the count is over the limit, for every row of docs."""
    model = model_bytes(model_path)

    def run(columns: list) -> list:
        merger = per_worker(RankMerger, model)
        return [columns[0], columns[1], merger.totals(columns[2].to_pylist())]

    text = filled(text_column)
    out = map_columns(docs.select(F.col(id_column).cast("long"), F.octet_length(text).cast("long"), text), COUNTS, run)
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
