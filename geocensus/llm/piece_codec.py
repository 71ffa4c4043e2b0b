"""SentencePiece encoding and decoding through tables of distinct chunks."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import numpy as np
import sentencepiece
from pyspark.sql import DataFrame

from geocensus.llm.shared import map_texts

_MARK = "▁"
_CHUNK = re.compile(f"{_MARK}+[^{_MARK}]*")
#: Distinct chunks that a Python worker keeps before it starts its table anew.
TABLE_ROWS = 150_000


class PieceCodec:
    """Encodes and decodes whole texts as the library does, segmenting each distinct marked word once.

    Holds if no piece of the model crosses from another character to a white-space marker, which the constructor checks;
    models that fail the check are used text by text.  The table belongs to one worker and is bounded.
    """

    def __init__(self, model_path: str, rows: int = TABLE_ROWS):
        self.sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
        size = self.sp.get_piece_size()
        pieces = [self.sp.id_to_piece(i) for i in range(size)]
        probe = " a  b\tc\n d "
        self.by_chunk = not any(_MARK in p.lstrip(_MARK) for p in pieces) and self.sp.decode(self.sp.encode(probe)) == probe
        self.starts = np.array([p.startswith(_MARK) for p in pieces])
        self.names = [str(i) for i in range(size)]
        self.mark, self.lead, self.rows = self.sp.piece_to_id(_MARK), self.sp.piece_to_id("a"), rows
        self.table: dict[str, str] = {}  # a chunk's ids, joined by commas
        self.odd: dict[str, str] = {}  # chunks that don't decode to themselves

    def _learn(self, chunks: set[str]) -> None:
        new = [c for c in chunks if c not in self.table]
        plain = [c for c in new if len(c) > 1 and c[1] != _MARK]
        # The library puts a marker before a text, so a text goes in without its first one.
        text = "".join(plain)[1:].replace(_MARK, " ")
        ids = self.sp.encode(text)
        cuts = np.flatnonzero(self.starts[ids]).tolist() if ids else []
        if len(cuts) == len(plain) and self.sp.decode(ids) == text:
            names = [self.names[i] for i in ids]
            for c, lo, hi in zip(plain, cuts, [*cuts, len(ids)][1:], strict=True):
                self.table[c] = ",".join(names[lo:hi])
            new = [c for c in new if c not in self.table]
        for c in new:
            got = self.sp.encode(c[1:].replace(_MARK, " ")) if c != _MARK else [self.mark]
            self.table[c] = ",".join([self.names[i] for i in got])
            back = self.sp.decode([self.lead, *got])[1:]
            if back != c.replace(_MARK, " "):
                self.odd[c] = back

    def coded(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """Per text the number of ids, the ids joined by commas, and the decoded text."""
        if not self.by_chunk:
            ids = [self.sp.encode(t) for t in texts]
            return [(len(x), ",".join([self.names[i] for i in x]), self.sp.decode(x)) for x in ids]
        if len(self.table) > self.rows:
            self.table.clear()
            self.odd.clear()
        chunks = [_CHUNK.findall(_MARK + t.replace(" ", _MARK)) if t else [] for t in texts]
        self._learn(set().union(*chunks))
        out = []
        for text, own in zip(texts, chunks, strict=True):
            ids = ",".join([self.table[c] for c in own])  # by position
            back = "".join([self.odd.get(c) or c.replace(_MARK, " ") for c in own])[1:] if self.odd else text.replace(_MARK, " ")
            out.append((ids.count(",") + 1 if ids else 0, ids, back))
        return out


_made: dict[str, PieceCodec] = {}


def codec(model_path: str) -> PieceCodec:
    """The worker's codec, kept over tasks."""
    if model_path not in _made:
        _made.clear()
        _made[model_path] = PieceCodec(model_path)
    return _made[model_path]


def _map(docs: DataFrame, model_path: str, id_col: str, text_col: str, columns: str, row) -> DataFrame:  # noqa: ANN001
    n = columns.count(", ") + 1

    def make() -> Callable[[list[str]], list]:
        c = codec(model_path)
        return lambda texts: list(zip(*[row(g) for g in c.coded(texts)], strict=True)) or [[]] * n

    return map_texts(docs, id_col, text_col, columns, make)


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, ids, decoded`` of every whole text, its null, empty and very long ones included; null counts as empty, which
    has no ids.  Rows are independent, so repeated ids and null ids pass through."""
    return _map(docs, model_path, id_col, text_col, "ids array<int>, decoded string", lambda g: ([int(x) for x in g[1].split(",") if x], g[2]))


def _sha(x: str) -> str:
    return hashlib.sha256(x.encode()).hexdigest()


def encode_digest(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of every whole text, from the same tables."""
    return _map(docs, model_path, id_col, text_col, "n_tokens long, ids_sha256 string, decoded_sha256 string", lambda g: (g[0], _sha(g[1]), _sha(g[2])))
