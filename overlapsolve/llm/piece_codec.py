"""Encoding with the pieces of a merge-type SentencePiece vocabulary, with seeded merge-dropout, and decoding.

A chunk starts as single characters; an agenda holds the adjacent pairs that form a piece, best score first. A pair that
is taken from the agenda is merged unless a keyed hash says to skip it (with probability `dropout`); a skipped pair stays
apart. The hash is keyed by the seed, the document's id, the chunk's place in it, and how many pairs of the chunk were
considered before. So each occurrence of a word is drawn anew, but a rerun gives the same. Characters
without a piece become byte pieces, so decoding is lossless: spaces are written as the vocabulary's mark, and a mark in the
text itself goes into bytes.

Texts are cut before runs of spaces, which no piece spans, so chunks can be encoded alone. Those of many texts go in step, in
arrays with a column for each: the n-th pass considers the n-th pair of every chunk. Nothing is kept from one to another, so what
a worker has seen before changes neither results nor costs. Chunks over SHORT characters have an agenda of their own.

Edge cases: a null or empty text has no pieces; very long texts are encoded whole, chunk by chunk; repeated rows get the same
pieces; a row without doc_id is keyed like id 0; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterable, Iterator
from itertools import repeat
from operator import add

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from overlapsolve.llm.common import SLICE, id_and_text, sliced

MARK = "▁"


class Pieces:
    """The vocabulary: ids and scores by piece, byte pieces, and what each id stands for."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        names = [model.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        self.ids = {names[i]: i for i in plain}
        #: By piece: 0 for the best score, and so on; equal scores have equal ranks.
        rank = {x: k for k, x in enumerate(sorted({model.get_score(i) for i in plain}, reverse=True))}
        self.ranks = {names[i]: rank[model.get_score(i)] for i in plain}
        self.byte_ids = {int(names[i][3:-1], 16): i for i in range(n) if model.is_byte(i)}
        if len(self.byte_ids) != 256:
            raise ValueError("the vocabulary has no byte pieces")
        self.bytes = [b""] * n
        for i in plain:
            self.bytes[i] = names[i].replace(MARK, " ").encode()
        for b, i in self.byte_ids.items():
            self.bytes[i] = bytes([b])
        lengths = np.array([len(b) for b in self.bytes])
        self._lengths, self._first = lengths, np.cumsum(lengths) - lengths
        self._joined = np.frombuffer(b"".join(self.bytes), np.uint8)
        self.spans = any(MARK in p.lstrip(MARK) for p in self.ids)
        # A chunk is a run of spaces and what follows up to the next one, or the whole text if pieces span spaces.
        self.chunks = re.compile(r".+" if self.spans else r" +[^ ]*|[^ ]+", re.DOTALL)

    def decode(self, ids: Iterable[int]) -> bytes:
        at = np.asarray(ids, np.int64)
        lengths = self._lengths[at]
        ends = np.cumsum(lengths)
        return self._joined[np.repeat(self._first[at] - ends + lengths, lengths) + np.arange(lengths.sum())].tobytes()


_WORD = (1 << 64) - 1
_STEP, _MIX = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F
DECIDED = 24


def _mixed(h: int) -> int:
    h = (h ^ h >> 32) * _MIX & _WORD
    h = (h ^ h >> 29) * _STEP & _WORD
    return h ^ h >> 32


def skipped(key: int, n: int, limit: int) -> bool:
    """Whether the n-th pair considered in the chunk with this key is skipped: 32 bits of a hash, below the limit."""
    return (_mixed(key + (n // 2 + 1) * _STEP & _WORD) >> (32 * (n % 2)) & 0xFFFFFFFF) < limit


def decisions(keys: np.ndarray, limit: int) -> list[int]:
    """The first DECIDED decisions of each chunk as bits, as skipped() makes them."""
    out: list[int] = []
    with np.errstate(over="ignore"):
        for block in np.array_split(keys, len(keys) // 8192 + 1):
            h = block[:, None] + np.arange(1, DECIDED // 2 + 1, dtype=np.uint64) * np.uint64(_STEP)
            h = (h ^ h >> np.uint64(32)) * np.uint64(_MIX)
            h = (h ^ h >> np.uint64(29)) * np.uint64(_STEP)
            h ^= h >> np.uint64(32)
            bits = h.astype("<u8").view("<u4").reshape(len(block), DECIDED) < limit
            out += (np.packbits(bits, axis=1, bitorder="little") @ np.array([1, 1 << 8, 1 << 16])).tolist()
    return out


def chunk_keys(doc_id: int, seed: int, n: int) -> np.ndarray:
    """A key for each chunk of a document, by its place."""
    start = np.uint64(xxhash.xxh64_intdigest(str(doc_id), seed))
    with np.errstate(over="ignore"):
        return (start + np.arange(n, dtype=np.uint64)) * np.uint64(_MIX)


def segment(chunk: str, pieces: Pieces, limit: int = 0, key: int = 0, mask: int = 0) -> tuple[list[int], int]:
    """Ids of one chunk, spaces being marks, and the number of pairs considered. mask: the first decisions; later ones come from the key."""
    symbols = list(chunk.replace(" ", MARK))
    literal = {i for i, c in enumerate(chunk) if c == MARK} if MARK in chunk else ()
    n = len(symbols)
    left, right, size = list(range(-1, n - 1)), list(range(1, n + 1)), [1] * n
    rank_of, push, pop = pieces.ranks.get, heapq.heappush, heapq.heappop
    # An entry is one number: the rank, the left symbol's place, and the sizes of both symbols.
    w = n.bit_length()
    most = (1 << w) - 1
    ones = 1 << w | 1
    agenda = []
    before = symbols[0] if n else ""
    for b in range(1, n):
        here = symbols[b]
        rank = rank_of(before + here)
        if rank is not None and not (literal and (b in literal or b - 1 in literal)):
            agenda.append((rank << w | b - 1) << 2 * w | ones)
        before = here
    heapq.heapify(agenda)
    considered = 0
    while agenda:
        entry = pop(agenda)
        a, first, second = entry >> 2 * w & most, entry >> w & most, entry & most
        b = right[a]
        if size[a] != first or b >= n or size[b] != second:
            continue  # one of the two has grown or gone since
        considered += 1
        if considered > DECIDED:
            if limit and skipped(key, considered - 1, limit):
                continue
        elif mask >> (considered - 1) & 1:
            continue
        symbols[a] = whole = symbols[a] + symbols[b]
        both = first + second
        size[a], size[b] = both, 0
        right[a] = b = right[b]
        if b < n:
            left[b] = a
            if not literal or b not in literal:
                rank = rank_of(whole + symbols[b])
                if rank is not None:
                    push(agenda, ((rank << w | a) << w | both) << w | size[b])
        c = left[a]
        if c >= 0 and (not literal or c not in literal):
            rank = rank_of(symbols[c] + whole)
            if rank is not None:
                push(agenda, ((rank << w | c) << w | size[c]) << w | both)
    out: list[int] = []
    i = 0
    while i < n:
        found = None if literal and i in literal else pieces.ids.get(symbols[i])
        if found is not None:
            out.append(found)
        else:
            out += [pieces.byte_ids[b] for b in (" " if symbols[i] == MARK and i not in literal else symbols[i]).encode()]
        i += size[i]
    return out, considered


#: Characters of a chunk up to which finding the agenda's least entry anew is quicker than a heap.
SHORT = 48
_APART = 1 << 62


def segment_short(chunk: str, pieces: Pieces, limit: int = 0, key: int = 0, mask: int = 0) -> tuple[list[int], int]:
    """The same as segment(), for a chunk without marks of its own: one rank for each adjacent pair, the leftmost least first."""
    text = chunk.replace(" ", MARK)
    symbols = list(text)
    rank_of = pieces.ranks.get
    agenda = list(map(rank_of, map(add, text, text[1:]), repeat(_APART)))
    agenda.append(_APART)  # the last symbol has no right neighbour
    considered = 0
    while (least := min(agenda)) != _APART:
        at = agenda.index(least)
        considered += 1
        if considered <= DECIDED:
            skip, mask = mask & 1, mask >> 1
        else:
            skip = limit and skipped(key, considered - 1, limit)
        if skip:
            agenda[at] = _APART
            continue
        del agenda[at]
        symbols[at] = whole = symbols[at] + symbols.pop(at + 1)
        if at + 1 < len(symbols):
            agenda[at] = rank_of(whole + symbols[at + 1], _APART)
        if at:
            agenda[at - 1] = rank_of(symbols[at - 1] + whole, _APART)
    ids = pieces.ids
    try:
        return [ids[x] for x in symbols], considered
    except KeyError:
        out: list[int] = []
        for x in symbols:
            found = ids.get(x)
            out += [found] if found is not None else [pieces.byte_ids[b] for b in (" " if x == MARK else x).encode()]
        return out, considered


PLACE_BITS, SYMBOL_BITS = 6, 20  # of a place in a chunk of up to SHORT characters, of a symbol
APART = (1 << 31) - (1 << PLACE_BITS)
#: Cells of the arrays that chunks of about one length are segmented in, characters of text that are encoded at once, and the number
#: of chunks from which on arrays pay.
CELLS, GROUP, MANY = 1 << 16, SLICE, 32


class Merges:
    """What two neighbouring symbols make, for whole arrays of them. A symbol is a piece's id or, from `others` on, a character without a piece."""

    def __init__(self, pieces: Pieces):
        symbols = dict(pieces.ids)
        self.others = len(pieces.bytes)
        for k, c in enumerate(sorted({c for p in pieces.ids for c in p} - symbols.keys())):
            symbols[c] = self.others + k
        #: `other`: a character that no piece holds; `none`: no symbol, also what a pair makes that is no piece.
        self.other = self.others + sum(s >= self.others for s in symbols.values())
        self.none = self.other + 1
        if self.none >> SYMBOL_BITS:
            raise ValueError("the vocabulary is too large")
        self.of_char = np.full(0x110000, self.other, np.int32)
        for p, s in symbols.items():
            if len(p) == 1:
                self.of_char[ord(p)] = s
        self.of_char[ord(" ")], self.of_char[ord(MARK)] = self.of_char[ord(MARK)], self.other
        self.rank = np.full(self.none + 1, APART >> PLACE_BITS, np.int64)
        for p, i in pieces.ids.items():
            self.rank[i] = pieces.ranks[p]
        self.rank = (self.rank << PLACE_BITS).astype(np.int32)
        made = [(symbols[p[:k]] * (self.none + 1) + symbols[p[k:]], i) for p, i in pieces.ids.items() for k in range(1, len(p)) if p[:k] in symbols and p[k:] in symbols]
        self._place(*np.array(made, np.int64).reshape(-1, 2).T)

    def _place(self, keys: np.ndarray, values: np.ndarray) -> None:
        """A table in which each key has a slot of its own: the keys of a bucket share a shift, drawn until none of their slots is taken."""
        few = max(1, (len(keys) // 2).bit_length())
        bits = few + 3
        self.down, self.low, self.mask = np.uint64(64 - few), np.uint64(64 - few - bits), np.uint64((1 << bits) - 1)
        draw = np.random.default_rng(0)
        while True:
            self.odd = np.uint64(int(draw.integers(1 << 62)) * 2 + 1)
            h = keys.view(np.uint64) * self.odd
            bucket, base = (h >> self.down).view(np.int64), (h >> self.low & self.mask).view(np.int64)
            if len(np.unique(bucket << bits | base)) == len(keys):
                break  # a shift can't part two keys of a bucket with the same base
        self.shift = np.zeros(1 << few, np.int64)
        self.entry = np.full(1 << bits, -1, np.int64)
        todo = np.arange(len(keys))
        while len(todo):
            at = bucket[todo]
            self.shift[at] = draw.integers(1 << bits, size=1 << few)[at]
            slot = base[todo] ^ self.shift[at]
            clash = np.zeros(1 << few, bool)
            clash[at[(self.entry[slot] >= 0) | (np.bincount(slot)[slot] > 1)]] = True
            placed = ~clash[at]
            self.entry[slot[placed]] = keys[todo[placed]] << SYMBOL_BITS | values[todo[placed]]
            todo = todo[~placed]

    def made(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The piece that each pair makes, or `none`."""
        key = a.astype(np.int64) * (self.none + 1) + b
        h = key.view(np.uint64) * self.odd
        found = self.entry[(h >> self.low & self.mask).view(np.int64) ^ self.shift[(h >> self.down).view(np.int64)]]
        return np.where(found >> SYMBOL_BITS == key, found & (1 << SYMBOL_BITS) - 1, self.none)


def segment_many(symbols: np.ndarray, starts: np.ndarray, sizes: np.ndarray, keys: np.ndarray, merges: Merges, limit: int, out: np.ndarray) -> None:
    """The same as segment() for many chunks at once, each of up to SHORT characters, from symbols[start] on. Chunks go in step: the n-th
    pass considers the n-th pair of each. A symbol that is left is written to out, at the place of its first character."""
    width, n = int(sizes.max()), len(starts)
    rows = np.arange(n)
    place = np.arange(width + 1)[:, None]
    # One column a chunk; the last row takes what is written for neighbours that aren't there.
    inside = place < sizes
    now = np.where(inside, symbols[np.minimum(starts + place, len(symbols) - 1)], merges.none)
    makes = np.full((width + 1, n), merges.none, np.int64)
    makes[:-1] = merges.made(now[:-1], now[1:])
    agenda = (merges.rank[makes] | place).astype(np.int32)
    after, before = np.where(place + 1 < sizes, place + 1, width), np.broadcast_to(np.where(place, place - 1, width), now.shape).copy()
    considered = 0
    while True:
        least = agenda[:-1].min(axis=0)
        live = np.flatnonzero(least < APART)
        if 4 * len(live) < 3 * n:
            left = np.ones(n, bool)
            left[live] = False
            ended = now[:-1, left].T
            kept = ended != merges.none
            out[(starts[rows[left]][:, None] + np.arange(width))[kept]] = ended[kept]
            if not len(live):
                return
            rows, least, n = rows[live], least[live], len(live)
            now, makes, agenda, after, before = (x.take(live, 1) for x in (now, makes, agenda, after, before))
            live = np.arange(n)
        now_, makes_, agenda_, after_, before_ = (x.reshape(-1) for x in (now, makes, agenda, after, before))
        least = least[live]
        at = (least & (1 << PLACE_BITS) - 1).astype(np.int64)
        cell = at * n + live
        if limit:
            h = keys[rows[live]] + np.uint64((considered // 2 + 1) * _STEP & _WORD)
            h = (h ^ h >> np.uint64(32)) * np.uint64(_MIX)
            h = (h ^ h >> np.uint64(29)) * np.uint64(_STEP)
            h ^= h >> np.uint64(32)
            skip = (h >> np.uint64(32 * (considered % 2)) & np.uint64(0xFFFFFFFF)) < np.uint64(limit)
            agenda_[cell[skip]] = APART
            go = np.flatnonzero(~skip)
            at, cell, live = at[go], cell[go], live[go]
        considered += 1
        whole = makes_[cell]
        gone = after_[cell] * n + live
        right, left = after_[gone], before_[cell]
        right_cell, left_cell = right * n + live, left * n + live
        now_[cell], now_[gone], agenda_[gone] = whole, merges.none, APART
        after_[cell], before_[right_cell] = right, at
        made = merges.made(np.concatenate([whole, now_[left_cell]]), np.concatenate([now_[right_cell], whole]))
        cells = np.concatenate([cell, left_cell])
        makes_[cells] = made
        agenda_[cells] = merges.rank[made] | np.concatenate([at, left])


class Encoder:
    """Encodes texts, many at once: all chunks of about one length are segmented in step."""

    def __init__(self, pieces: Pieces, dropout: float = 0.1, seed: int = 0):
        self.pieces, self.seed = pieces, seed
        self.limit = int(dropout * 2**32)
        self.merges = Merges(pieces)
        self.of_byte = np.array([pieces.byte_ids[b] for b in range(256)], np.uint32)

    def _group(self, texts: list[str], starts: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
        """Ids of each text, and its number of chunks. starts: by text, what the keys of its chunks count from."""
        chars = np.frombuffer("".join(texts).encode("utf-32-le"), "<u4")
        ends = np.cumsum([len(t) for t in texts])
        begins = np.concatenate([[0], ends[:-1]])
        cut = np.zeros(len(chars) + 1, bool)
        if not self.pieces.spans:
            space = chars == 32
            cut[1:-1] = space[1:] & ~space[:-1]
        cut[begins] = True
        first = np.flatnonzero(cut[:-1])
        by_text = np.searchsorted(first, np.concatenate([begins, [len(chars)]]))
        counts = np.diff(by_text)
        sizes = np.diff(np.concatenate([first, [len(chars)]]))
        with np.errstate(over="ignore"):
            keys = (np.repeat(starts, counts) + (np.arange(len(first)) - np.repeat(by_text[:-1], counts)).astype(np.uint64)) * np.uint64(_MIX)
        out = np.full(len(chars), self.merges.none, np.int32)
        symbols = self.merges.of_char[chars]
        order = np.argsort(np.minimum(sizes, SHORT + 1).astype(np.uint8), kind="stable")
        split = np.searchsorted(sizes[order] > SHORT, True) if len(order) >= MANY else 0
        order, alone = order[:split], order[split:]
        with np.errstate(over="ignore"):
            while len(order):
                some = order[: CELLS // (int(sizes[order[0]]) + 1)]
                # As many as fit if all are as long as the longest, but enough that rare lengths share their arrays.
                some = some[: max(64, CELLS // (int(sizes[some[-1]]) + 1))]
                segment_many(symbols, first[some], sizes[some], keys[some], self.merges, self.limit, out)
                order = order[len(some) :]
        # Some symbols stand for several ids: characters without a piece for their bytes, the first one of a chunk taken alone for all of it.
        whole = self.merges.none + 1
        masks = decisions(keys[alone], self.limit) if self.limit else [0] * len(alone)
        ids_of = {}
        for k, mask in zip(alone.tolist(), masks, strict=True):
            chunk = chars[first[k] : first[k] + sizes[k]].tobytes().decode("utf-32-le")
            quick = len(chunk) <= SHORT and MARK not in chunk
            ids_of[int(first[k])] = (segment_short if quick else segment)(chunk, self.pieces, self.limit, int(keys[k]), mask)[0]
        out[first[alone]] = whole
        at = np.flatnonzero(out != self.merges.none)
        found = out[at]
        times = np.ones(len(at), np.int64)
        bare = (found >= self.merges.others) & (found < whole)
        code = chars[at[bare]]
        times[bare] = 1 + (code >= 0x80) + (code >= 0x800).astype(np.int64) + (code >= 0x10000)
        inserted = [ids_of[p] for p in at[found == whole].tolist()]
        times[found == whole] = [len(x) for x in inserted]
        last = np.concatenate([[0], np.cumsum(times)])
        ids = np.repeat(found, times).astype(np.uint32)
        if len(code):
            ids[np.repeat(bare, times)] = self.of_byte[np.frombuffer(code.tobytes().decode("utf-32-le").encode(), np.uint8)]
        if inserted:
            ids[np.repeat(found == whole, times)] = np.concatenate(inserted)
        return np.split(ids, last[np.searchsorted(at, ends[:-1])]), counts

    def _long(self, text: str, start: int) -> np.ndarray:
        """Ids of a text that is taken in parts, cut between chunks."""
        parts, at = [], 0
        while at < len(text):
            cut = None if self.pieces.spans else _BETWEEN.search(text, at + GROUP - 1)
            end = cut.start() + 1 if cut else len(text)
            found, counts = self._group([text[at:end]], np.array([start & _WORD], np.uint64))
            parts += found
            start, at = start + int(counts[0]), end
        return np.concatenate(parts)

    def encode_all(self, texts: list[str], doc_ids: list[int]) -> list[np.ndarray]:
        starts = [xxhash.xxh64_intdigest(str(i), self.seed) for i in doc_ids]
        out: list[np.ndarray] = []
        at = 0
        while at < len(texts):
            end, held = at, 0
            while end < len(texts) and held + len(texts[end]) <= GROUP:
                held += len(texts[end])
                end += 1
            if end == at:
                out.append(self._long(texts[at], starts[at]))
                end += 1
            elif held:
                out += self._group(texts[at:end], np.array(starts[at:end], np.uint64))[0]
            else:
                out += [np.zeros(0, np.uint32)] * (end - at)
            at = end
        return out

    def encode(self, text: str, doc_id: int = 0) -> np.ndarray:
        return self.encode_all([text], [doc_id])[0]


_BETWEEN = re.compile("[^ ] ")
_KEPT: dict[tuple, Encoder] = {}


def encoder_for(path: str, dropout: float, seed: int) -> Encoder:
    """The last one a process used: Spark's Python workers serve many tasks, and the chunks they have seen stay."""
    key = (path, dropout, seed)
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = Encoder(Pieces(path), dropout, seed)
    return _KEPT[key]


SCHEMA = "doc_id long, n_ids long, ids_crc32 long, n_bytes long, restored boolean"


def encode_documents(docs: DataFrame, path: str, dropout: float = 0.1, seed: int = 0, with_ids: bool = False) -> DataFrame:
    """One row a document, as in SCHEMA, and its ids if asked for; restored tells whether decoding gave the text back."""
    names = [x.split()[0] for x in SCHEMA.split(", ")] + ["ids"] * with_ids
    types = [pa.int64()] * 4 + [pa.bool_()] + [pa.list_(pa.int64())] * with_ids

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = encoder_for(path, dropout, seed)
        for b in sliced(batches, GROUP):
            rows, doc_ids, texts = [], b.column(0).to_pylist(), b.column(1).to_pylist()
            for doc_id, text, ids in zip(doc_ids, texts, encoder.encode_all(texts, [i or 0 for i in doc_ids]), strict=True):
                raw = text.encode()
                rows.append((doc_id, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), len(raw), encoder.pieces.decode(ids) == raw) + (ids.astype(np.int64),) * with_ids)
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    return id_and_text(docs).mapInArrow(of, SCHEMA + ", ids array<long>" * with_ids)


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([pieces.decode(x or []).decode() for x in b.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(of, "doc_id long, text string")
