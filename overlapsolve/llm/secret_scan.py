"""Secret scan: base patterns, and a linear-chain conditional random field that tags tokens as begin, inside or outside.

Tokens, their shapes and their hashes are found for a whole batch of texts at once, from arrays of code points. A token's
emission scores are sums of table entries: its own shape and make-up, the two words before it, the shape after it, and what kind of
file it is in. The field is trained on windows of a bounded sample of documents: around the values that the base patterns
find, plain ones, and ones into which secrets of unlisted kinds under unlisted or no names are put, or else harmless numbers,
addresses, paths and names. So it finds what the base patterns can't see.

Viterbi decoding is exact and local: where outside leads by more than any change of transitions could win back, the best
path must be outside, so texts fall apart into short stretches that are decoded one by one.

Edge cases: a null or empty text has no spans; very long texts are scanned whole; repeated rows are scanned each; with no
training rows, or none that hold a secret, the field adds nothing; other columns aren't looked at.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.llm.common import SLICE, id_and_text, sliced, small_batches
from overlapsolve.session import checkpoint, discard

#: The base patterns, the least length of what each must match, and the order of kinds.
ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 8, "access": 16, "hex": 32}
KINDS = ("assign", "access", "hex", "crf")
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")

Span = tuple[int, int, str]


def base_spans(text: str) -> list[Span]:
    """(start, end, kind) of the base matches, leftmost and non-overlapping per kind, ordered by start and kind."""
    found: list[Span] = []
    lowered = text.lower()
    if any(k in lowered for k in KEYWORDS):
        found += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if len(m[0]) >= LEAST["access"]]
    found += [(m.start(), m.end(), "hex") for m in LONG_HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


#: Runs of hexadecimal digits are maximal, so those that are long enough can be asked for directly.
LONG_HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{32,}")


def _char_table() -> np.ndarray:
    """Class of each code point below 128, and of all others at 128: 0 space, 1 a-f, 2 g-z, 3 upper, 4 digit, 5 joiner, 6 quote or sign of assignment, 7 the rest."""
    t = np.full(129, 7, np.uint8)
    for chars, k in ((" \t\n\x0b\f\r", 0), ("abcdef", 1), ("ghijklmnopqrstuvwxyz", 2), ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 3), ("0123456789", 4), ("+/_.-", 5), ("\"'=:", 6)):
        t[[ord(c) for c in chars]] = k
    return t


_CLASS = _char_table()
_GROUP = np.array([0, 1, 1, 1, 1, 1, 2, 3], np.uint8)  # tokens are runs of one group; group 0 parts them
SHAPES, WORDS, FILES, MADE = 8 * 10 * 4 + 2, 1 << 12, 16, 6 * 4 * 4
_VOWEL = np.isin(np.arange(129), [ord(c) for c in "aeiouAEIOU"])


@dataclass
class Tokens:
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    shape: np.ndarray
    word: np.ndarray
    file: np.ndarray
    made: np.ndarray

    @property
    def features(self) -> np.ndarray:
        """Column indices into one weight table: own shape, words before, shape after, file, make-up."""
        n = len(self.start)
        prev = lambda k: np.concatenate([np.zeros(min(k, n), np.int64), self.word[: max(0, n - k)]])
        same = lambda k: np.concatenate([np.zeros(min(k, n), bool), self.doc[k:] == self.doc[: max(0, n - k)]])
        after = np.concatenate([self.shape[1:], [0]]) if n else self.shape
        after = np.where(np.concatenate([self.doc[1:] == self.doc[:-1], [False]]) if n else np.zeros(0, bool), after, 0)
        parts = (self.shape, np.where(same(1), prev(1), 0), np.where(same(2), prev(2), 0), after, self.file, self.made)
        return np.stack([p + o for p, o in zip(parts, OFFSETS, strict=True)], axis=1)


OFFSETS = np.cumsum([0, SHAPES, WORDS, WORDS, SHAPES, FILES])
FEATURES = int(OFFSETS[-1]) + MADE


def tokenize(texts: list[str]) -> Tokens:
    """Tokens of all texts; starts and ends are code points within the own text."""
    codes = [np.frombuffer(t.encode("utf-32-le"), np.uint32) for t in texts]
    first = np.cumsum([0] + [len(c) + 1 for c in codes])[:-1]
    whole = np.full(int(sum(len(c) + 1 for c in codes)), 32, np.uint32)
    for c, f in zip(codes, first, strict=True):
        whole[f : f + len(c)] = c
    kind = _CLASS[np.minimum(whole, 128)]
    group = _GROUP[kind]
    edge = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1], [True]])) if len(group) else np.zeros(1, np.int64)
    start, end = edge[:-1], edge[1:]
    real = group[start] > 0 if len(start) else np.zeros(0, bool)
    start, end = start[real], end[real]
    doc = np.searchsorted(first, start, side="right") - 1
    n = len(start)
    if not n:
        z = np.zeros(0, np.int64)
        return Tokens(z, z, z, z, z, z, z)
    length = end - start

    def within(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
        return total[end] - total[start]

    hexes, others, upper, digit, joiner = (within(kind == k) for k in (1, 2, 3, 4, 5))
    change = np.zeros(len(kind), bool)
    sort = np.where(kind == 1, 2, kind)
    change[1:] = sort[1:] != sort[:-1]
    changes = within(change) - 1
    lower = hexes + others
    mix = np.select(
        [digit == length, (others + upper + joiner == 0), (upper + digit == length) & (digit > 0), (digit > 0) & (upper > 0), digit > 0, (upper > 1) & (lower > 0), joiner > 0],
        [1, 2, 3, 4, 5, 6, 7],
        0,
    )
    size = np.searchsorted([2, 4, 6, 8, 12, 16, 24, 32, 48], length, side="right")
    turn = np.minimum(3, 8 * np.maximum(changes, 0) // np.maximum(length, 1))
    shape = np.where(group[start] == 1, 2 + (mix * 10 + size) * 4 + turn, group[start] - 2)
    letters = np.maximum(1, hexes + others + upper)
    parts = (np.searchsorted([0.01, 0.2, 0.4, 0.7, 0.99], digit / length, side="right"), np.minimum(3, joiner), np.searchsorted([0.08, 0.2, 0.32], within(_VOWEL[np.minimum(whole, 128)]) / letters, side="right"))
    made = np.where(group[start] == 1, (parts[0] * 4 + parts[1]) * 4 + parts[2], 0)
    # A word's hash: code points, in lower case, weighed by powers; only the first 16 of a token count.
    folded = (whole | np.where(kind == 3, 32, 0).astype(np.uint32)).astype(np.uint64)
    place = np.arange(len(kind)) - np.repeat(np.concatenate([[0], edge[1:-1]]), np.diff(edge))
    powers = np.array([pow(1_000_003, k, 1 << 64) if k < 16 else 0 for k in range(17)], np.uint64)
    with np.errstate(over="ignore"):
        sums = np.add.reduceat(folded * powers[np.minimum(place, 16)], start)  # what lies between tokens is space
        word = ((sums * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 12)).astype(np.int64)
    per = lambda x: np.bincount(doc, weights=x, minlength=len(texts))
    chars = np.maximum(1, per(length))
    share = lambda x: np.searchsorted([0.02, 0.08, 0.2], per(x) / chars, side="right")
    file = share(digit)[doc] * 4 + share(np.where(group[start] != 1, length, joiner))[doc]
    return Tokens(start - first[doc], end - first[doc], doc, shape.astype(np.int64), word, file.astype(np.int64), made.astype(np.int64))


@dataclass
class Field:
    """Weights: a row of three (begin, inside, outside) for each feature, and transitions; outside to inside is barred."""

    weights: np.ndarray
    moves: np.ndarray

    @staticmethod
    def empty() -> Field:
        w = np.zeros((FEATURES, 3))
        w[: SHAPES, 2] = 5.0
        return Field(w, _barred(np.zeros((3, 3))))

    def emissions(self, features: np.ndarray) -> np.ndarray:
        out = np.zeros((len(features), 3))
        for k in range(features.shape[1]):
            out += self.weights[features[:, k]]
        return out

    def decode(self, tokens: Tokens) -> list[list[tuple[int, int]]]:
        """Spans of each document that the best tag sequence marks, as (start, end) of tokens."""
        n = len(tokens.start)
        docs = int(tokens.doc[-1]) + 1 if n else 0
        out: list[list[tuple[int, int]]] = [[] for _ in range(docs)]
        if not n:
            return out
        e = self.emissions(tokens.features)
        open_moves = self.moves[self.moves > BAR]
        reach = 3 * float(open_moves.max() - open_moves.min())
        swap = np.maximum(0, np.concatenate([(e[1:, 1] - e[1:, 0]), [0]]))
        sure = e[:, 2] - np.maximum(e[:, 0], e[:, 1]) > reach + swap
        doubt = np.flatnonzero(~sure)
        if not len(doubt):
            return out
        breaks = np.flatnonzero((np.diff(doubt) > 1) | (np.diff(tokens.doc[doubt]) > 0)) + 1
        for run in np.split(doubt, breaks):
            a, b = int(run[0]), int(run[-1]) + 1
            after = b < n and tokens.doc[b] == tokens.doc[a]
            before = a > 0 and tokens.doc[a - 1] == tokens.doc[a]
            tags = viterbi(e[a:b], self.moves, before, after)
            begun = -1
            for i, tag in enumerate([*tags, 2]):
                if begun >= 0 and tag != 1:
                    out[tokens.doc[a]].append((int(tokens.start[a + begun]), int(tokens.end[a + i - 1])))
                    begun = -1
                if tag == 0:
                    begun = i
        return out


BAR = -1e8


def _barred(moves: np.ndarray) -> np.ndarray:
    moves = moves.copy()
    moves[2, 1] = 10 * BAR
    return moves


def viterbi(e: np.ndarray, moves: np.ndarray, before: bool, after: bool) -> list[int]:
    """The best tags of one stretch; `before` and `after` tell whether a token that is outside stands at that end."""
    score = e[0] + (moves[2] if before else np.array([0, 10 * BAR, 0]))
    back = []
    for row in e[1:]:
        step = score[:, None] + moves
        back.append(step.argmax(axis=0))
        score = step.max(axis=0) + row
    if after:
        score = score + moves[:, 2]
    tags = [int(score.argmax())]
    for b in reversed(back):
        tags.append(int(b[tags[-1]]))
    return tags[::-1]


def value_spans(text: str) -> list[tuple[int, int]]:
    """What the field learns from: the values that the base patterns find."""
    found = [m.span(2) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    return found + [(a, b) for a, b, k in base_spans(text) if k != "assign"]


def tags_for(tokens: Tokens, gold: list[list[tuple[int, int]]]) -> np.ndarray:
    """0 begin, 1 inside, 2 outside, from the spans of each text."""
    tags = np.full(len(tokens.start), 2)
    for d, spans in enumerate(gold):
        if spans:
            lo, hi = np.searchsorted(tokens.doc, [d, d + 1])
            for a, b in spans:
                inside = lo + np.flatnonzero((tokens.start[lo:hi] >= a) & (tokens.end[lo:hi] <= b))
                tags[inside] = 1
                tags[inside[:1]] = 0
    return tags


#: Names under which secrets and harmless values are put into training windows; none of the first is one that the base patterns list.
SECRET_NAMES = "pwd pass auth credential credentials bearer key private_key access_key signing_key passphrase session sas jwt authorization auth_key conn cert".split()
PLAIN_NAMES = "id name user host port path file count size version date width url title color order phone ip mail card ref sku page width height code".split()
_ALNUM = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"


def _secret(rng: np.random.Generator) -> str:
    of = lambda chars, a, b: "".join(rng.choice(list(chars), rng.integers(a, b)))
    kind = rng.integers(6)
    if kind == 0:
        return of("0123456789abcdef", 20, 65)
    if kind == 1:
        return of(_ALNUM + "+/", 20, 65)
    if kind == 2:
        return of("abcdefghijklmnopqrstuvwxyz", 2, 5) + rng.choice(["_", "-"]) + of(_ALNUM, 16, 41)
    if kind == 3:
        return of("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 16, 33)
    if kind == 4:
        return of("abcdefghijklmnopqrstuvwxyz0123456789", 16, 41)
    return of(_ALNUM, 20, 33) + "." + of(_ALNUM + "_-", 20, 49)


def _harmless(rng: np.random.Generator, words: list[str]) -> str:
    n = lambda a, b: int(rng.integers(a, b))
    w = lambda: words[n(0, len(words))] if words else "word"
    kinds = [
        lambda: str(n(10**15, 10**16)), lambda: f"+{n(1, 99)} ({n(100, 999)}) {n(100, 999)}-{n(1000, 9999)}", lambda: ".".join(str(n(0, 256)) for _ in range(4)),
        lambda: f"{w()}.{n(0, 99):02d}@mail{n(0, 9)}.{w()}.com", lambda: f"https://www.{w()}.org/{w()}/{w()}-{n(1, 9999)}.html", lambda: f"20{n(0, 30):02d}-{n(1, 13):02d}-{n(1, 29):02d}T{n(0, 24):02d}:{n(0, 60):02d}:00",
        lambda: f"{n(0, 20)}.{n(0, 20)}.{n(0, 20)}-{w()}", lambda: f"/usr/lib/{w()}{n(2, 20)}.{n(0, 20)}/{w()}-{w()}/{w()}.py", lambda: w().capitalize() + w().capitalize() + w().capitalize() + str(n(1, 99)),
        lambda: f"{w()}_{w()}_{w()}_{n(1, 99)}", lambda: "".join(w() for _ in range(n(3, 7))), lambda: (w() + w()).upper() + str(n(1, 999)), lambda: f"{w()} {w()}", lambda: str(n(1, 10**12)), lambda: "-".join(str(n(10, 99999)) for _ in range(n(2, 5))),
        lambda: f"{n(0, 16**7):07x}", lambda: f"{w()}={w()}&{w()}={n(1, 999)}",
    ]
    return str(kinds[n(0, len(kinds))]())


def put_in(texts: list[str], count: int, rng: np.random.Generator, around: int = 120) -> tuple[list[str], list[list[tuple[int, int]]]]:
    """Stretches of the texts with something put in at a break between words: (texts, spans of secrets). Half the somethings are harmless."""
    made, gold = [], []
    long = [t for t in texts if len(t) > around]
    for k in range(count if long else 0):
        t = long[int(rng.integers(len(long)))]
        at = int(rng.integers(0, len(t) - around))
        cut = t[at : at + around]
        places = [m.start() for m in re.finditer(r"\s", cut)]
        place = places[len(places) // 2] if places else around // 2
        secret = k % 2 == 0
        value = _secret(rng) if secret else _harmless(rng, [w for w in cut.split() if w.isalpha()])
        name = str(rng.choice(SECRET_NAMES if secret or rng.random() < 0.1 else PLAIN_NAMES))
        name = (name, name.upper(), name.capitalize(), f"{rng.choice(PLAIN_NAMES)}_{name}")[int(rng.integers(4))]
        before, after = [(f'{name} = "', '"'), (f"{name}: ", ""), (f"{name}=", ""), (f'"{name}": "', '"'), ("", ""), (f"{name} ", ""), (f"{name}='", "'")][int(rng.integers(7))]
        head = cut[:place] + " " + before
        made.append(head + value + after + cut[place:])
        gold.append([(len(head), len(head) + len(value))] if secret else [])
    return made, gold


def fit(texts: list[str], span: int = 12, rounds: int = 120, rate: float = 0.5, seed: int = 7, ridge: float = 1e-4, put: int = 3000) -> Field:
    """Maximum likelihood over windows of `span` tokens, by forward-backward sums and adaptive steps. `put` windows are made up."""
    rng = np.random.default_rng(seed)
    more, known = put_in(texts, put, rng)
    gold = [value_spans(t) for t in texts] + known
    texts = texts + more
    tokens = tokenize(texts)
    n = len(tokens.start)
    if n < span:
        return Field.empty()
    tags, features = tags_for(tokens, gold), tokens.features
    begun = np.flatnonzero(tags == 0)
    if not len(begun):
        return Field.empty()
    middles = np.array([(a + b) // 2 for a, b in zip(*(np.searchsorted(tokens.doc, np.arange(len(texts) - len(more), len(texts)), side=x) for x in ("left", "right")), strict=True)], np.int64)
    real = begun[tokens.doc[begun] < len(texts) - len(more)]
    times = int(np.clip(put // max(1, 2 * len(real)), 1, 20))  # few real ones are seen from several places each
    near = np.concatenate([np.repeat(real, times), begun, middles])
    first = np.concatenate([near - rng.integers(1, span - 1, len(near)), rng.integers(0, n - span + 1, 4000)])
    first = first[(first >= 0) & (first <= n - span)]
    first = first[tokens.doc[first] == tokens.doc[first + span - 1]]
    first = first[tags[first] != 1]
    at = first[:, None] + np.arange(span)
    x, y = features[at], tags[at]
    w, m = np.zeros((FEATURES, 3)), np.zeros((3, 3))
    w[:SHAPES, 2] = 1.0
    gw, gm = np.full_like(w, 1e-3), np.full_like(m, 1e-3)
    gold_moves = np.zeros((3, 3))
    np.add.at(gold_moves, (y[:, :-1].ravel(), y[:, 1:].ravel()), 1)
    eye = np.eye(3)
    for _ in range(rounds):
        e = w[x].sum(axis=2)
        moves = _barred(m)
        alpha = [np.where(np.arange(3) == 1, 10 * BAR, 0.0) + e[:, 0]]
        for t in range(1, span):
            alpha.append(np.logaddexp.reduce(alpha[-1][:, :, None] + moves, axis=1) + e[:, t])
        beta = [np.zeros((len(x), 3))]
        for t in range(span - 1, 0, -1):
            beta.append(np.logaddexp.reduce(moves + (e[:, t] + beta[-1])[:, None, :], axis=2))
        beta = beta[::-1]
        z = np.logaddexp.reduce(alpha[-1], axis=1)
        mass = np.stack([np.exp(alpha[t] + beta[t] - z[:, None]) for t in range(span)], axis=1)
        slope = eye[y] - mass
        dw = np.zeros_like(w)
        for k in range(x.shape[2]):
            for c in range(3):
                dw[:, c] += np.bincount(x[:, :, k].ravel(), weights=slope[:, :, c].ravel(), minlength=FEATURES)
        expected = sum(np.exp(alpha[t][:, :, None] + moves + (e[:, t + 1] + beta[t + 1])[:, None, :] - z[:, None, None]).sum(axis=0) for t in range(span - 1))
        dw -= ridge * len(x) * w
        dm = gold_moves - expected
        dm[2, 1] = 0
        gw += dw**2
        gm += dm**2
        w += rate * dw / np.sqrt(gw)
        m += rate * dm / np.sqrt(gm)
    return Field(w, _barred(m))


def train(docs: DataFrame, rows: int = 600, longest: int = 50_000, key: str = "doc_id", text: str = "text") -> Field:
    """Fit on at most `rows` documents that hold a base match and a quarter as many that needn't: those with the smallest hashed ids.

    Texts of over `longest` characters are no training rows. Ids are chosen first, so only the chosen texts reach the driver.
    """
    likely = F.col(text).rlike(r"(?i)password|passwd|secret|token|api_?key|AKIA[A-Z0-9]{12}|[0-9a-f]{32}")
    able = id_and_text(docs, key, text).where(F.col(key).isNotNull() & (F.length(text) <= longest))
    marked = checkpoint(able.select(F.col(key).alias("id"), likely.alias("likely")))
    first = lambda df, n: [r[0] for r in df.orderBy(F.xxhash64("id", F.lit(1)), "id").limit(n).select("id").collect()]
    ids = sorted({*first(marked.where("likely"), rows), *first(marked, rows // 4)})
    discard(marked)
    taken = able.where(F.col(key).isin(ids)).collect() if ids else []
    return fit([t for _, t in sorted(map(tuple, taken))])


def spans_of(texts: list[str], field: Field, least: int = 8) -> list[list[Span]]:
    """Base spans and those the field adds: of `least` code points at least, and not within or across a base span."""
    return [s for s, _ in spans_and_marks(texts, field, least)]


def spans_and_marks(texts: list[str], field: Field, least: int = 8) -> list[tuple[list[Span], int]]:
    """The spans, and how many stretches the field marks, those within base spans included."""
    base = [base_spans(t) for t in texts]
    tagged = field.decode(tokenize(texts))
    out = []
    for i, spans in enumerate(base):
        marked = [(a, b) for a, b in (tagged[i] if i < len(tagged) else []) if b - a >= least]
        new = [(a, b, "crf") for a, b in marked if all(b <= x or a >= y for x, y, _ in spans)]
        out.append((sorted(spans + new, key=lambda s: (s[0], KINDS.index(s[2]))), len(marked)))
    return out


def joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_crf long, n_marked long"


def scan(docs: DataFrame, field: Field, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document, as in SCHEMA: n_crf counts spans that the field adds, n_marked all that it marks."""
    shared = docs.sparkSession.sparkContext.broadcast(field)  # the size of the weight tables, whatever the data
    types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()] * 2
    names = [x.split()[0] for x in SCHEMA.split(", ")]

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, SLICE, text):
            both = spans_and_marks(b.column(1).to_pylist(), shared.value)
            found = [s for s, _ in both]
            base = [[s for s in x if s[2] != "crf"] for x in found]
            count = lambda kind: [sum(s[2] == kind for s in x) for x in found]  # noqa: E731, B023
            digests = [hashlib.sha256(joined(x).encode()).hexdigest() for x in base]
            columns = [b.column(0).to_pylist(), count("assign"), count("access"), count("hex"), digests, [joined(x) for x in found], count("crf"), [n for _, n in both]]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=names)

    return id_and_text(docs, key, text).mapInArrow(of, SCHEMA)


def redacted(text: str, spans: list[Span], mark: str = "[secret]") -> str:
    """The text with each stretch that spans cover replaced once."""
    out, at = [], 0
    for a, b, _ in spans:
        if b <= at:
            continue
        if a >= at:
            out += [text[at:a], mark]
        at = b
    return "".join(out) + text[at:]


def redact(docs: DataFrame, field: Field, text: str = "text", length: str = "n_chars") -> DataFrame:
    """docs, all columns, with secrets in the text replaced and the length column, if there is one, renewed; a null text stays null."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, SLICE, text):
            at = b.schema.get_field_index(text)
            texts = b.column(at).to_pylist()
            found = spans_of([t or "" for t in texts], shared.value)
            new = [t if t is None else redacted(t, s) for t, s in zip(texts, found, strict=True)]
            b = b.set_column(at, b.schema.field(at), pa.array(new, b.schema.field(at).type))
            if length in b.schema.names:
                k = b.schema.get_field_index(length)
                b = b.set_column(k, b.schema.field(k), pa.array([len(t) if t is not None and s else v for t, s, v in zip(new, found, b.column(k).to_pylist(), strict=True)], b.schema.field(k).type))
            yield b

    return small_batches(docs).mapInArrow(of, docs.schema)
