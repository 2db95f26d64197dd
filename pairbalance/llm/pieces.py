"""The vocabulary of a sentence-piece BPE model, and the pre-tokens within which all its merges stay."""

from __future__ import annotations

import re
from pathlib import Path

import sentencepiece

from .common import once_per_worker

MARK = "▁"  # stands for a space
#: No piece of such a model has a mark behind another character, so no merge crosses the start of a pre-token.
_RUNS = re.compile(f"{MARK}+[^{MARK}\n]*|\n|[^{MARK}\n]+")


def model_bytes(path: str | None = None) -> bytes:
    """The model file, read on the driver; it is a few hundred KB and travels with the tasks."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    return Path(path).read_bytes()


class Pieces:
    """Pieces, merge ranks and byte pieces of a model. Pieces of equal score share a rank and merge leftmost first."""

    def __init__(self, model: bytes):
        m = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.eos = m.eos_id()
        self.text = [m.id_to_piece(i) for i in range(m.get_piece_size())]
        ordinary = [i for i in range(len(self.text)) if not (m.is_byte(i) or m.is_control(i) or m.is_unknown(i))]
        self.ids = {self.text[i]: i for i in ordinary}
        levels = {s: k for k, s in enumerate(sorted({m.get_score(i) for i in ordinary}, reverse=True))}
        self.rank = {i: levels[m.get_score(i)] for i in ordinary}
        self.byte_ids = [m.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.control = {i for i in range(len(self.text)) if m.is_control(i)}
        count: dict[int, int] = {}
        for i in ordinary:
            if len(self.text[i]) > 1:
                count[self.rank[i]] = count.get(self.rank[i], 0) + 1
        self.shared = {r for r, n in count.items() if n > 1}
        inner = [p for p in self.ids if MARK in p.lstrip(MARK) or "\n" in p or len(p) > 1 and self.rank[self.ids[p]] in self.shared and p.strip(MARK)]
        if inner or m.is_unused(0) or any(m.is_unused(i) for i in ordinary):
            raise ValueError(f"not a model whose merges stay within words: {inner[:3]}")

    def merge(self, text: str) -> list[str]:
        """The pieces of a short text by merging the best pair, leftmost first, again and again; quadratic."""
        parts, ids, rank = list(text), self.ids, self.rank
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                piece = ids.get(parts[i] + parts[i + 1])
                if piece is not None and (best is None or rank[piece] < best):
                    best, at = rank[piece], i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts


def pretokens(text: str) -> list[str]:
    """The text with its spaces marked and a mark in front, cut into pre-tokens; an empty text has none."""
    if not text:
        return []
    marked = MARK + text.replace(" ", MARK)
    if MARK * 2 in marked:
        return _RUNS.findall(marked)
    return [x for x in marked.replace(MARK, f" {MARK}").replace("\n", " \n ").split(" ") if x]


def per_worker(kind, model: bytes):
    """One instance of kind(model) in each Python worker, kept from task to task."""
    return once_per_worker(f"{kind.__name__}-{hash(model)}", lambda: kind(model))
