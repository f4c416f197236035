"""Exact token ids from a public tokenizer file, with a cache of word pieces.

The ``tokenizers`` library runs its merge loop for each word. Texts repeat words, so
this class cuts a text only where the library's own pre-tokenizer always cuts, looks
the pieces up in a bounded cache and calls the library for pieces not seen yet. A
text in which a cut would not be certain (runs of white space, a special token's string) goes
to the library whole. Ids are the library's in every case: as it comes, the string of a special
token in a text gives that token's id; with ``specials_as_text`` it is ordinary text.
"""

from __future__ import annotations

import re
from array import array
from operator import attrgetter, itemgetter

import numpy as np
import pyarrow as pa

#: Letters that are their own NFC form and whose lower case is one of them.
_LATIN = "A-Za-zÀ-ÖØ-Þß-öø-ÿ"
_PLAIN = re.compile(rf"([{_LATIN}]+)([!-&(-/:-@\[-`{{-~]*)\Z")
_FIRST = "\0"
_GAPS = (_FIRST, "\n")
_NONE = np.zeros(0, np.int64)
_ID = attrgetter("id")


def byte_chars() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    keep = set(printable)
    return [chr(b) if b in keep else chr(next(rest)) for b in range(256)]


class PieceTokenizer:
    """``space_joins``: a space belongs to the word after it (byte-level) or is dropped (word-end)."""

    def __init__(self, path: str, space_joins: bool, max_pieces: int = 800_000, specials_as_text: bool = False):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = specials_as_text
        added = [] if specials_as_text else [t.content for t in self.tok.get_added_tokens_decoder().values()]
        #: A text that holds none of these strings holds no special token: case does not matter to them.
        self.hints = {max(re.split("[A-Za-z]+", c), key=len) or c for c in added}
        self.space_joins, self.max_pieces = space_joins, max_pieces
        self.chars = dict(enumerate(byte_chars()))
        #: Latin letters as the characters of their bytes.
        self.letters = {k: "".join(self.chars[b] for b in chr(k).encode()) for k in range(33, 256)}
        self.model = self.tok.model
        self.parts: dict[str, list[int]] = {}
        self.table = self._table()
        self.index: dict[str, int] = self.table()
        self.flat, self.ends = array("I"), array("q", [0])  # the ids of piece k: flat[ends[k] : ends[k + 1]]
        self.lead, self.tail = [], []  # pieces that begin or end with white space
        self.used = np.zeros(0, bool)  # pieces met again in a later run of texts than their first, since the last turn

    def _turn(self) -> None:
        """Makes room: only pieces in use stay, and at most half of the cache."""
        used = self.used
        kept = [(piece, k) for piece, k in self.index.items() if used[k]][-(self.max_pieces // 2) :]
        self.parts = {}
        self.index = self.table()  # the pieces that go are freed before the new table fills
        at = np.array([k for _, k in kept], np.int64)
        flat, ends = np.frombuffer(self.flat, np.uint32), np.frombuffer(self.ends, np.int64)
        start, n = ends[at], ends[at + 1] - ends[at]
        stops = np.cumsum(n)
        ids = flat[np.repeat(start - (stops - n), n) + np.arange(n.sum())]
        edge = np.zeros((2, len(ends)), bool)
        edge[0, self.lead], edge[1, self.tail] = True, True
        self.lead, self.tail = (np.flatnonzero(e[at]).tolist() for e in edge)
        del flat, ends
        self.flat, self.ends = array("I", ids.tobytes()), array("q", np.append(0, stops).tobytes())
        self.index = self.table((piece, k) for k, (piece, _) in enumerate(kept))
        self.used = np.zeros(len(kept), bool)

    def _table(self) -> type:
        """Tables of pieces that take in what they lack."""
        mine, tokenize, plain, letters = self, self.model.tokenize, _PLAIN.match, self.letters
        spaced = self.space_joins
        gap = self.chars[32] if spaced else ""

        class Index(dict):
            def __missing__(self, piece):
                flat, ends = mine.flat, mine.ends
                if piece.isascii() and piece.isalpha():
                    flat.extend(map(_ID, tokenize(gap + piece if spaced else piece.lower())))
                    ends.append(len(flat))
                    k = len(ends) - 2
                elif m := plain(piece):  # a word, perhaps with marks after it
                    word, marks = m.groups()
                    if marks:
                        k = self[word]
                        flat.extend(flat[ends[k] : ends[k + 1]])
                        flat.extend(mine._part(marks))
                    else:
                        s = word if spaced else word.lower()
                        flat.extend(map(_ID, tokenize(gap + (s if s.isascii() else s.translate(letters)))))
                    ends.append(len(flat))
                    k = len(ends) - 2
                else:
                    k = mine._add(piece)
                self[piece] = k
                return k

        return Index

    def _model(self, s: str) -> list[int]:
        if not self.space_joins:
            s = s.lower()
        s = s.replace(" ", self.chars[32]).replace("\n", self.chars[10]) if s.isascii() else s.encode().decode("latin-1").translate(self.chars)
        return [t.id for t in self.model.tokenize(s)]

    def _part(self, s: str) -> list[int]:
        got = self.parts.get(s)
        if got is None:
            got = self.parts[s] = self._model(s)
        return got

    def _known(self, word: str):
        k = self.index[word]
        return self.flat[self.ends[k] : self.ends[k + 1]]

    def _push(self, ids) -> int:
        self.flat.extend(ids)
        self.ends.append(len(self.flat))
        return len(self.ends) - 2

    def _edge(self, ids, lead: bool, tail: bool) -> int:
        k = self._push(ids)
        if lead:
            self.lead.append(k)
        if tail:
            self.tail.append(k)
        return k

    def _add(self, piece: str) -> int:
        gap = piece[0] if piece and piece[0] in _GAPS else ""
        body = piece[1:] if gap else piece
        if m := _PLAIN.match(body):
            word, marks = m.groups()
            if gap == "\n" and self.space_joins:
                ids = self._part("\n") + self._part(word)
            elif gap == _FIRST and self.space_joins:
                ids = self._part(word)
            else:
                ids = self._known(word) if marks or gap else self._model(" " + word if self.space_joins else word)
            return self._push([*ids, *self._part(marks)] if marks else ids)
        if not body and (gap == _FIRST or not self.space_joins):
            return self._edge([], not gap, not gap)
        literal = body if gap == _FIRST else piece if gap else " " + piece
        lead = gap != _FIRST and (not body or body[0].isspace())
        return self._edge(self.tok.encode(literal, add_special_tokens=False).ids, lead, not body or body[-1].isspace())

    def _whole(self, text: str) -> np.ndarray:
        return np.array([self._push(self.tok.encode(text, add_special_tokens=False).ids)], np.int64)

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids end to end (uint32), and the number of ids of each text. Null counts as empty."""
        if max(len(self.index), len(self.parts)) > self.max_pieces or len(self.flat) > 16 * self.max_pieces:
            self._turn()
        index, before = self.index, len(self.used)
        rows = []
        for text in texts:
            if not text:
                rows.append(_NONE)
            elif _FIRST in text or any(h in text for h in self.hints):
                rows.append(self._whole(text))
            else:
                pieces = text.replace("\n", " \n").split(" ")
                pieces[0] = _FIRST + pieces[0]
                rows.append(np.array(itemgetter(*pieces)(index) if len(pieces) > 1 else [index[pieces[0]]], np.int64))
        if self.space_joins and texts:
            lead, tail = np.zeros(len(self.ends), bool), np.zeros(len(self.ends), bool)
            lead[self.lead], tail[self.tail] = True, True
            row = np.concatenate(rows)
            unsure = np.flatnonzero(tail[row[:-1]] & lead[row[1:]]) + 1  # a text's first piece is never a lead
            for k in np.unique(np.searchsorted(np.cumsum([len(r) for r in rows]), unsure, "right")):
                rows[k] = self._whole(texts[k])
        if not texts or not sum(map(len, rows)):
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        row = np.concatenate(rows)
        self.used[row[row < before]] = True
        self.used = np.append(self.used, np.zeros(len(self.ends) - 1 - before, bool))
        flat, edges = np.frombuffer(self.flat, np.uint32), np.frombuffer(self.ends, np.int64)
        start = edges[row]
        n = edges[row + 1] - start
        ends = np.cumsum(n)
        ids = flat[np.repeat(start - (ends - n), n) + np.arange(ends[-1])]
        del flat, edges  # else the arrays cannot grow
        at = np.concatenate([[0], ends])
        stops = np.cumsum([len(r) for r in rows])
        return ids, np.diff(at[stops], prepend=0)


_open: dict[tuple, PieceTokenizer] = {}


def opened(path: str, space_joins: bool) -> PieceTokenizer:
    """One tokenizer for each Python worker."""
    if (path, space_joins) not in _open:
        _open[path, space_joins] = PieceTokenizer(path, space_joins)
    return _open[path, space_joins]


def encoded_docs(texts: pa.Array, path: str, space_joins: bool, end_id: int, step: int = 512):
    """Yields, for runs of ``step`` texts of a column, the ids with ``end_id`` after each text, and each text's number of ids."""
    tok = opened(path, space_joins)
    for at in range(0, len(texts), step):
        ids, n = tok.encode(texts.slice(at, step).to_pylist())
        stops = np.cumsum(n)
        yield np.insert(ids, stops, end_id).astype(np.uint32), n + 1
