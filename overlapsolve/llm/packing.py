"""Sum-of-squares online packing of tokenised documents into windows.

Each task packs its own rows as they come: a document's ids are cut into full windows and a rest, and the rest goes to the
fill level that makes the sum over levels of (number of windows at that level)^2 least; the numbers are kept in one array
with an entry for each level. What is still open at the end of a task is topped up: pieces of the emptiest windows are cut to
fill the fullest, and the last window is cut into lengths that are powers of two, which need no padding. No row leaves its
task, so nothing is shuffled; memory holds the open windows only, and at MAX_OPEN of them they are topped up early.

Edge cases: a null or empty text is its end token alone; repeated rows are packed each; an empty table gives no pieces; a
row without doc_id keeps a null id in its pieces.
"""

from __future__ import annotations

import os
import re
import unicodedata
import zlib
from array import array
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from overlapsolve.llm.common import id_and_text

CAPACITY = 4096
END = 2
#: Windows that a task holds open at most, with their ids: 64 MB at 4096 ids of 4 bytes.
MAX_OPEN = 4096


class WordTokenizer:
    """Ids of a text as little-endian unsigned 32-bit bytes, equal to those of the library for the whole text.

    The normaliser and the splitting pattern of this vocabulary never join what white space parts, so words between ASCII
    white space are encoded alone and kept, up to `words` of them and from their second sight on. A text that may hold a
    special token's string is encoded whole.
    """

    def __init__(self, path: str, words: int = 1_000_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark's tasks are the parallelism
        from tokenizers import Tokenizer

        self.inner, self.words, self.known = Tokenizer.from_file(path), words, {}
        self.seen = bytearray(1 << 23)

    def _encoded(self, texts: list[bytes]) -> list[bytes]:
        found = self.inner.encode_batch_fast([t.decode() for t in texts], add_special_tokens=False)
        return [array("I", x.ids).tobytes() for x in found]

    def _new(self, words: set[bytes]) -> dict[bytes, bytes]:
        # Signs after a letter or digit are a part of their own in the splitting pattern, unless there are marks, which the normaliser may join.
        # Only words that end in an ASCII sign are looked at: most don't, and whole words are right too.
        split = {w: (m[1].encode(), m[2].encode()) for w in words if w[-1] in _ENDS and (m := _SIGNS.fullmatch(w.decode())) and not _marked(m[1][-1].lower() + m[2])}
        parts = {p for w in words for p in split.get(w, (w,))}
        known = self.known
        need = [p for p in parts if p not in known]
        new = dict(zip(need, self._encoded(need), strict=True))
        of = lambda p: new[p] if p in new else known[p]
        new.update([(w, of(a) + of(b)) for w, (a, b) in split.items()])
        return new

    def _keep(self, new: dict[bytes, bytes]) -> None:
        if len(self.known) + len(new) > self.words:
            self.known.clear()
        seen, last = self.seen, len(self.seen) - 1
        for w, ids in new.items():
            place = hash(w) & last
            if seen[place]:
                self.known[w] = ids
            else:
                seen[place] = 1

    def ids(self, text: bytes) -> bytes:
        if b"<|" in text:
            return self._encoded([text])[0]
        words, known = text.lower().split(), self.known
        try:
            return b"".join(map(known.__getitem__, words))
        except KeyError:
            new = self._new({w for w in words if w not in known})
            out = b"".join([new[w] if w in new else known[w] for w in words])
            self._keep(new)
            return out


def _marked(part: str) -> bool:
    return not part.isascii() and any(unicodedata.category(c)[0] == "M" for c in part)


_SIGNS = re.compile(r"(.*[^\W_])([^\w\s']+)", re.DOTALL)
_ENDS = frozenset(c for c in range(33, 127) if not chr(c).isalnum() and chr(c) not in "_'")
_KEPT: dict[str, WordTokenizer] = {}


def tokenizer_for(path: str) -> WordTokenizer:
    """One a process: Spark's Python workers serve many tasks, and the words they have seen stay."""
    if path not in _KEPT:
        _KEPT[path] = WordTokenizer(path)
    return _KEPT[path]


@dataclass
class Piece:
    doc_id: int | None
    start: int
    ids: bytes
    doc_tokens: int

    @property
    def length(self) -> int:
        return len(self.ids) // 4

    def cut(self, n: int) -> tuple[Piece, Piece]:
        return Piece(self.doc_id, self.start, self.ids[: 4 * n], self.doc_tokens), Piece(self.doc_id, self.start + n, self.ids[4 * n :], self.doc_tokens)


class SumOfSquares:
    """Windows of `capacity`, at each moment counted by fill level."""

    def __init__(self, capacity: int = CAPACITY):
        self.capacity = capacity
        self.count = np.zeros(capacity + 1, np.int64)
        self.at: dict[int, list[list[Piece]]] = {}

    def level_for(self, n: int) -> int:
        """The level to put n on: 0 for a new window. Ties go to the fullest window."""
        c, room = self.count, self.capacity - n
        rise = 2 * (c[n : self.capacity + 1] - c[: room + 1]) + 2  # by level before: one window leaves it, one comes to level + n
        rise[0] = 2 * c[n] + 1
        rise[room] = 1 - 2 * c[room]
        rise[1:][c[1 : room + 1] == 0] = np.iinfo(np.int64).max
        return int(room - np.argmin(rise[::-1]))

    def put(self, piece: Piece) -> list[Piece] | None:
        """The window's pieces if it is now full."""
        n = piece.length
        if n == self.capacity:
            return [piece]
        level = self.level_for(n)
        window = self.at[level].pop() if level else []
        self.count[level] -= level > 0
        window.append(piece)
        if level + n == self.capacity:
            return window
        self.at.setdefault(level + n, []).append(window)
        self.count[level + n] += 1
        return None

    @property
    def open(self) -> int:
        return int(self.count.sum())

    def drain(self) -> Iterator[list[Piece]]:
        """Full windows made of what is open, and last a few whose lengths are powers of two."""
        windows = [w for level in sorted(self.at, reverse=True) for w in self.at[level]]
        self.at, self.count = {}, np.zeros_like(self.count)
        spare: list[Piece] = []
        low, high = 0, len(windows)
        window, room = [], self.capacity
        while low < high or spare:
            if not window and low < high:
                window, low = windows[low], low + 1
                room = self.capacity - sum(p.length for p in window)
            if not spare and low < high:
                high -= 1
                spare = windows[high]
            if not spare:
                break
            piece = spare.pop()
            if piece.length > room:
                piece, rest = piece.cut(room)
                spare.append(rest)
            window.append(piece)
            room -= piece.length
            if not room:
                yield window
                window, room = [], self.capacity
        rest = window + spare[::-1]
        left = sum(p.length for p in rest)
        while left:
            size, part = 1 << (left.bit_length() - 1), []
            left -= size
            while size:
                piece = rest.pop(0)
                if piece.length > size:
                    piece, more = piece.cut(size)
                    rest.insert(0, more)
                part.append(piece)
                size -= piece.length
            yield part


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end: int = END, with_ids: bool = False) -> DataFrame:
    """One row a piece, as in SCHEMA, and its ids too if with_ids; sequences are gapless from offset 0."""
    names = [x.split()[0] for x in SCHEMA.split(", ")]
    types = [pa.int64()] * len(names) + [pa.list_(pa.int64())] * with_ids

    def rows(windows: list[list[Piece]], first: int) -> pa.RecordBatch:
        out: list[list] = [[] for _ in types]
        for k, window in enumerate(windows):
            offset = 0
            for p in window:
                values = [p.doc_id, p.start, p.length, zlib.crc32(p.ids), p.doc_tokens, first + k, offset] + [np.frombuffer(p.ids, "<u4").astype(np.int64)] * with_ids
                for column, v in zip(out, values, strict=True):
                    column.append(v)
                offset += p.length
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], names=names + ["ids"] * with_ids)

    def packed(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, packer = tokenizer_for(tokenizer_path), SumOfSquares(capacity)
        last = np.asarray([end], "<u4").tobytes()
        sequence, done = TaskContext.get().partitionId() << 33, []
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()), strict=True):
                ids = tokenizer.ids(text.as_py()) + last
                total = len(ids) // 4
                for start in range(0, total, capacity):
                    full = packer.put(Piece(doc_id, start, ids[4 * start : 4 * (start + capacity)], total))
                    done += [full] if full else []
                if packer.open >= MAX_OPEN:
                    done += packer.drain()
                if len(done) >= 256:
                    yield rows(done, sequence)
                    sequence, done = sequence + len(done), []
        done += packer.drain()
        if done:
            yield rows(done, sequence)

    return id_and_text(docs).mapInArrow(packed, SCHEMA + ", ids array<long>" * with_ids)
