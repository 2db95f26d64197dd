"""SentencePiece encoding by a prefix table, and decoding.

The pieces of any prefix of a text end in one last piece that depends on the prefix alone. An automaton
over all pieces lists the pieces that end at each character; the last piece is the one whose predecessor,
the last piece of the shorter prefix, stands beside it without a merge across their border. The ids are
then read backwards from the end of the table, in time linear in the text however long a word is.

Two pieces stand side by side when merging their joined text would give just these two. The test undoes
the merges of both, latest first, and looks at each pair of pieces that met at the border.

Defined results: null counts as empty; an empty text has the end id alone and decodes to an empty text; texts of any
length are encoded whole; repeated rows are encoded each; an empty table gives an empty result; other columns of the
input are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib

import ahocorasick
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from .common import Bounded, filled, map_columns
from .pieces import MARK, Pieces, model_bytes, per_worker, pretokens

#: Bytes of a half of each cache.
CACHED_WORDS = 24 << 20
CACHED_PAIRS = 16 << 20


class PrefixEncoder:
    """Encodes texts with a model given as bytes."""

    def __init__(self, model: bytes):
        v = self.vocabulary = Pieces(model)
        self.left: dict[int, int | None] = {}
        self.right: dict[int, int | None] = {}
        self.plain: set[int] = set()
        self.reachable(v)
        self.automaton = ahocorasick.Automaton()
        for piece in self.left:
            self.automaton.add_word(v.text[piece], (len(v.text[piece]), piece))
        self.automaton.make_automaton()
        self.fits = Bounded(self._fits, CACHED_PAIRS)
        self.word_ids = Bounded(lambda w: " ".join(map(str, self.encode_word(w))), CACHED_WORDS)
        self.surface = {str(i): b"" if i in v.control else p.replace(MARK, " ").encode() for i, p in enumerate(v.text)}
        self.surface |= {str(i): bytes([b]) for b, i in enumerate(v.byte_ids)}

    def reachable(self, v: Pieces) -> None:
        """The last merge of each piece that merging its own text gives; plain: ranks rise from merge to merge."""
        ids, rank = v.ids, v.rank
        for piece in sorted(ids.values(), key=lambda i: len(v.text[i])):
            text = v.text[piece]
            if len(text) == 1:
                self.left[piece] = self.right[piece] = None
                self.plain.add(piece)
                continue
            parts, last = list(text), ("", "")
            while len(parts) > 1:
                best, at = None, -1
                for i in range(len(parts) - 1):
                    found = ids.get(parts[i] + parts[i + 1])
                    if found is not None and (best is None or rank[found] < best):
                        best, at = rank[found], i
                if best is None:
                    break
                last = (parts[at], parts[at + 1])
                parts[at : at + 2] = ["".join(last)]
            if len(parts) == 1:
                a, b = (ids.get(x) for x in last)
                self.left[piece], self.right[piece] = a, b
                halves = [x for x in (a, b) if x is not None]
                if rank[piece] not in v.shared and all(x in self.plain and (len(v.text[x]) == 1 or rank[x] < rank[piece]) for x in halves):
                    self.plain.add(piece)

    def _fits(self, pair: int) -> bool:
        a, b = pair >> 32, pair & 0xFFFFFFFF
        v = self.vocabulary
        text, rank = v.text, v.rank
        if a not in self.plain or b not in self.plain:
            return v.merge(text[a] + text[b]) == [text[a], text[b]]
        eats_a = eats_b = 1 << 40  # ranks of the merges that take the bordering pieces away
        while True:
            joined = v.ids.get(text[a] + text[b])
            if joined is not None and rank[joined] < eats_a and rank[joined] <= eats_b:
                return False
            time_a = rank[a] if self.right[a] is not None else -1
            time_b = rank[b] if self.left[b] is not None else -1
            if time_a < 0 and time_b < 0:
                return True
            if time_a > time_b:
                a, eats_a = self.right[a], time_a
            else:
                b, eats_b = self.left[b], time_b

    def encode_word(self, word: str) -> list[int]:
        """The ids of a pre-token."""
        n, known = len(word), self.vocabulary.ids
        if word in known and known[word] in self.left:
            return [known[word]]
        last: list = [None] * n
        fits = self.fits
        for end, (size, piece) in self.automaton.iter(word):
            if last[end] is None:
                start = end - size
                if start < 0 or type(before := last[start]) is not tuple or fits[before[1] << 32 | piece]:
                    last[end] = (size, piece)
        out: list[int] = []
        end = n - 1
        while end >= 0:
            if last[end] is None:
                out.extend(self.vocabulary.byte_ids[x] for x in reversed(word[end].encode()))
                end -= 1
            else:
                out.append(last[end][1])
                end -= last[end][0]
        out.reverse()
        return out

    def encode_text(self, text: str) -> str:
        """All ids of a text with the end id, as decimals with single spaces."""
        ids = list(map(self.word_ids.__getitem__, pretokens(text)))
        ids.append(str(self.vocabulary.eos))
        return " ".join(ids)

    def decode(self, ids: str) -> str:
        """The text of such a line of ids."""
        data = b"".join(map(self.surface.__getitem__, ids.split(" "))) if ids else b""
        return decoded(data[1:] if data[:1] == b" " else data)


def decoded(data: bytes) -> str:
    """UTF-8 as text; each byte that belongs to no character becomes U+FFFD."""
    try:
        return data.decode()
    except UnicodeDecodeError:
        out = []
        while data:
            try:
                out.append(data.decode())
                break
            except UnicodeDecodeError as e:
                out.append(data[: e.start].decode() + "�")
                data = data[e.start + 1 :]
        return "".join(out)


def _sha(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


ENCODED = StructType([StructField("doc_id", LongType()), StructField("n_tokens", LongType()), StructField("ids_sha256", StringType()), StructField("decoded_sha256", StringType())])
TOKENS = StructType([StructField("doc_id", LongType()), StructField("ids", StringType()), StructField("decoded", StringType())])


def _inputs(docs: DataFrame, id_column: str, text_column: str) -> DataFrame:
    return docs.select(F.col(id_column).cast("long"), filled(text_column))


def encode_documents(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", model_path: str | None = None) -> DataFrame:
    """(doc_id, ids, decoded) of every text; ids are decimals with single spaces and end in the end id."""
    model = model_bytes(model_path)

    def run(columns: list) -> list:
        encoder = per_worker(PrefixEncoder, model)
        ids = [encoder.encode_text(t) for t in columns[1].to_pylist()]
        return [columns[0], ids, [encoder.decode(x) for x in ids]]

    return map_columns(_inputs(docs, id_column, text_column), TOKENS, run)


def encode_digests(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", model_path: str | None = None) -> DataFrame:
    """Token counts and digests of the ids and of the decoded text; the ids themselves stay in the worker."""
    model = model_bytes(model_path)

    def run(columns: list) -> list:
        encoder = per_worker(PrefixEncoder, model)
        counts, first, second = [], [], []
        for text in columns[1].to_pylist():
            ids = encoder.encode_text(text)
            counts.append(ids.count(" ") + 1)
            first.append(_sha(ids))
            second.append(_sha(encoder.decode(ids)))
        return [columns[0], counts, first, second]

    return map_columns(_inputs(docs, id_column, text_column), ENCODED, run)
