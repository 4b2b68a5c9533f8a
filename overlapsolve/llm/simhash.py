"""SimHash near-duplicates by covering locality-sensitive hashing.

A fingerprint's bits carry labels 1 to 2^(r+1) - 1 in turn. Table v keeps the bits whose label has an odd number of bits in
common with v. The labels of r differing bits span a space of dimension r at most, so some v is orthogonal to all of them:
in that table the two fingerprints agree. Every pair within radius r thus meets in a bucket, without false negatives.

Equal fingerprints are merged first. A bucket of two is compared directly. The members of larger buckets are compared
through keys: two fingerprints are within 2 bits if and only if some key is within 1 bit of both, and a key has at most 65
fingerprints within 1 bit, so no bucket is ever expanded into pairs, however many copies it holds. (For another radius than
2 the same holds with keys at half the radius.) Links are joined into components on the executors.

Edge cases: a null or empty text has fingerprint zero and is linked like any other; repeated rows get the same result; an
empty table gives an empty result; a row without doc_id keeps its fingerprint, and its component comes from the others.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import partial
from itertools import combinations
from math import ceil

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapsolve.llm.common import SLICE, id_and_text, sliced, small_batches
from overlapsolve.llm.hashing import word_hashes
from overlapsolve.operators.components import connected_components
from overlapsolve.session import checkpoint, discard

SEED = 42
BITS = 64


def shingle_hashes(text: bytes, words: int = 3) -> np.ndarray:
    """XXH64 of each space-joined shingle of the lower-cased words, repeats included."""
    w = text.lower().split()  # for bytes: A-Z only, and the six ASCII white-space characters
    if not w:
        return np.zeros(0, np.uint64)
    shingles = map(b" ".join, zip(*(w[i:] for i in range(words)), strict=False)) if len(w) >= words else [b" ".join(w)]
    return np.fromiter(map(partial(xxhash.xxh64_intdigest, seed=SEED), shingles), np.uint64)


def fingerprint(text: bytes, words: int = 3) -> int:
    """Bit k is set if it is set in over half the shingle hashes."""
    return _majority(shingle_hashes(text, words))


def _majority(h: np.ndarray) -> int:
    """The bits that over half the hashes have; 0 without hashes."""
    total = np.zeros(BITS, np.int64)
    for i in range(0, len(h), 1 << 14):
        part = h[i : i + (1 << 14)]
        total += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * total > len(h), bitorder="little").view("<u8")[0]) if len(h) else 0


def fingerprints(docs: DataFrame, words: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp as a signed long) of every row."""

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).cast(pa.binary())
            fps = np.fromiter((fingerprint(t.as_py(), words) for t in texts), np.uint64, len(texts))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=[key, "fp"])

    return id_and_text(docs, key, text).mapInArrow(of, f"{key} long, fp long")


def table_masks(radius: int = 2) -> list[int]:
    """One mask a table, as signed longs; over 2^(radius + 1) - 1 tables every pair within the radius agrees once at least."""
    labels = 2 ** (radius + 1) - 1
    kept = [sum(1 << i for i in range(BITS) if ((i % labels + 1) & v).bit_count() % 2) for v in range(1, labels + 1)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in kept]


def ball_flips(radius: int) -> list[int]:
    """Bit patterns of up to `radius` bits, as signed longs."""
    flips = [sum(1 << i for i in c) for k in range(radius + 1) for c in combinations(range(BITS), k)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in flips]


def _longs(values: list[int]) -> Column:
    return F.array(*[F.lit(v).cast("long") for v in values])


def links(points: DataFrame, radius: int = 2) -> DataFrame:
    """From distinct (fp, rep): edges (u, v) between reps that join all fingerprints within the radius of each other.

    Edges only join fingerprints within the radius, and two such fingerprints are always joined by one edge or by two
    through a common one. radius is 1 or 2: larger ones need larger balls.
    """
    if radius not in (1, 2):
        raise ValueError("radius must be 1 or 2")
    tables = points.select("fp", "rep", F.posexplode(_longs(table_masks(radius))).alias("tab", "mask")).select("tab", F.col("fp").bitwiseAND(F.col("mask")).alias("key"), "fp", "rep")
    point = F.struct("fp", "rep")
    buckets = checkpoint(tables.groupBy("tab", "key").agg(F.count("*").alias("n"), F.min(point).alias("a"), F.max(point).alias("b")).where("n > 1"))
    direct = buckets.where("n = 2").where(F.bit_count(F.col("a.fp").bitwiseXOR(F.col("b.fp"))) <= radius).select(F.col("a.rep").alias("u"), F.col("b.rep").alias("v"))
    crowded = buckets.where("n > 2").select("tab", "key")
    members = tables.join(crowded, ["tab", "key"], "left_semi").select("fp", "rep").distinct()
    keys = members.select("rep", F.explode(F.transform(_longs(ball_flips(1)), lambda m: F.col("fp").bitwiseXOR(m))).alias("key"))
    balls = keys.groupBy("key").agg(F.collect_set("rep").alias("reps")).where("size(reps) > 1")  # 65 at most
    near = balls.select(F.array_min("reps").alias("u"), F.explode("reps").alias("v"))
    return direct.union(near).where("u <> v").distinct()


def near_duplicates(docs: DataFrame, radius: int = 2, words: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp, component_id) of every row; component_id is the smallest doc_id that links lead to."""
    printed = checkpoint(fingerprints(docs, words, key, text))
    points = checkpoint(printed.groupBy("fp").agg(F.min(key).alias("rep")))
    found = connected_components(links(points.where("rep is not null"), radius))
    classes = checkpoint(points.join(found, points.rep == found.node, "left").select("fp", F.coalesce("component", "rep").alias("component_id")))
    return printed.join(classes, "fp").select(key, "fp", "component_id")


def hex_digits(fp: str = "fp") -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


#: Bits of a set's signature, in longs: |x and y| is at most |x| less the number of bits that x sets and y doesn't.
SIGNATURE = 16
WIDE = 512
_ODD = np.array([pow(0x9E3779B97F4A7C15, 2 * k + 1, 1 << 64) for k in range(64)], np.uint64)


def _windows(texts: list[bytes], words: int) -> list[np.ndarray]:
    """64-bit hashes of each text's word windows, A-Z in lower case, repeats included; of a shorter text its whole."""
    doc, h = word_hashes(texts)
    first = np.searchsorted(doc, np.arange(len(texts) + 1))
    with np.errstate(over="ignore"):
        rolled = sum((h[k : max(0, len(h) - words + 1 + k)] * _ODD[k] for k in range(words)), np.uint64(0))
        rolled = (rolled ^ rolled >> np.uint64(31)) * _ODD[words]
        rolled = rolled ^ rolled >> np.uint64(29)
        out = []
        for a, b in zip(first[:-1], first[1:], strict=True):
            if b - a >= words or b == a:
                out.append(rolled[a : max(a, b - words + 1)] if b > a else np.zeros(0, np.uint64))
            else:
                out.append(np.atleast_1d((h[a:b] * _ODD[: b - a]).sum() * _ODD[words + int(b - a)]))
    return out


def _texts(docs: DataFrame, key: str, text: str) -> DataFrame:
    """(id, text) of the rows with an id, whatever else docs holds."""
    return small_batches(docs).select(F.col(key).cast("long").alias("id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text")).where("id is not null")


def _sketches(texts: DataFrame, words: int) -> DataFrame:
    """(id, same, n, fp, s0, ..., wide): a digest of the words; of the distinct windows the number, SimHash fingerprint and signature.

    Sets of more than WIDE windows, which fill the signature, have another one of a power of two of bits, from their number on.
    """
    names = ["id", "same", "n", "fp", *[f"s{k}" for k in range(SIGNATURE)], "wide"]

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, SLICE):
            raw = b.column(1).cast(pa.binary()).to_pylist()
            same = [xxhash.xxh3_128_intdigest(b" ".join(t.lower().split())).to_bytes(16, "big") for t in raw]
            n, fp, signs = np.zeros(len(raw), np.int32), np.zeros(len(raw), np.uint64), np.zeros((len(raw), 64 * SIGNATURE), np.uint8)
            wide: list[bytes | None] = [None] * len(raw)
            for i, h in enumerate(_windows(raw, words)):
                h = np.unique(h)
                n[i], fp[i] = len(h), _majority(h)
                if len(h) > WIDE:
                    bits = np.zeros(1 << (len(h) - 1).bit_length(), np.uint8)
                    bits[(h % np.uint64(len(bits))).astype(np.int64)] = 1
                    wide[i] = np.packbits(bits, bitorder="little").tobytes()
                signs[i, (h % np.uint64(64 * SIGNATURE)).astype(np.int64)] = 1
            longs = np.packbits(signs, axis=1, bitorder="little").view("<i8")
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(same, pa.binary()), pa.array(n), pa.array(fp.view(np.int64)), *[pa.array(np.ascontiguousarray(longs[:, k])) for k in range(SIGNATURE)], pa.array(wide, pa.binary())], names=names)

    return texts.mapInArrow(of, "id long, same binary, n int, fp long, " + ", ".join(f"s{k} long" for k in range(SIGNATURE)) + ", wide binary")


def _grams(texts: DataFrame, words: int, pick=None) -> DataFrame:
    """(id, grams): the distinct window hashes, or those that pick(hashes) leaves."""

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, SLICE):
            grams = [np.unique(h) for h in _windows(b.column(1).cast(pa.binary()).to_pylist(), words)]
            grams = [(h if pick is None else pick(h)).view(np.int64) for h in grams]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(grams, pa.list_(pa.int64()))], names=["id", "grams"])

    return texts.mapInArrow(of, "id long, grams array<long>")


def _common_windows(texts: DataFrame, words: int, share: int = 10, most: int = 200_000) -> np.ndarray:
    """Hashes of the windows that recur in a sample of one in `share` ids, commonest last; which these are only decides how much is compared."""
    sample = texts.where(F.pmod(F.xxhash64("id", F.lit(SEED)), F.lit(share)) == 0)
    counted = _grams(sample, words).select(F.explode("grams").alias("gram")).groupBy("gram").agg(F.count("*").alias("n")).where("n > 1")
    top = counted.orderBy(F.desc("n"), "gram").limit(most).select("gram").toArrow()  # `most` numbers
    return top.column("gram").to_numpy()[::-1].view(np.uint64).copy()


def _size_classes(n: int, similarity: float, start: int = WIDE + 1) -> list[int]:
    """Where classes of sizes begin, up to the first beyond n: of two similar sets, the larger is in the smaller one's class or the next."""
    begins = [start]
    while begins[-1] <= n:
        begins.append(int((begins[-1] + 1e-6) / similarity) + 1)
    return begins


def _block_keys(h: np.ndarray, similarity: float, often: np.ndarray) -> tuple[np.ndarray, bool]:
    """Keys of a set of more than WIDE windows, and whether any similar set of more than WIDE shares one of them.

    If the smaller of two similar sets is in class c, they differ by at most `most` windows. The windows are dealt over some
    more blocks than that; a difference spoils one block, so if the set fills more than `most` blocks, one of them is the same
    in both. A block has a key by all its windows: a passage that two long texts share doesn't make them meet, as a single
    window would. Blocks of common windows only (often, by window) are left out where over `most` others are filled: as equal
    blocks are left out on both sides, one of these is the same in both. Each set has keys for its own class and, being perhaps
    the larger one, for the class before.
    """
    begins = _size_classes(len(h), similarity)
    keys, sure = [], True
    with np.errstate(over="ignore"):
        mixed = (h ^ h >> np.uint64(31)) * _ODD[40]
        for c in range(max(0, len(begins) - 3), len(begins) - 1):
            most = int((1 - similarity + 1e-6) / similarity * begins[c + 1]) + 1
            blocks = most + most // 4 + 8
            of = (h % np.uint64(blocks)).astype(np.int64)
            order = np.argsort(of, kind="stable")
            filled, first = np.unique(of[order], return_index=True)
            total = np.add.reduceat(mixed[order], first) + filled.astype(np.uint64) * _ODD[41] + np.uint64(c) * _ODD[42]
            rare = ~np.logical_and.reduceat(often[order], first)
            total = (total ^ total >> np.uint64(29)) * _ODD[43]
            keys.append(total[rare] if rare.sum() > most else total)
            sure &= len(filled) > most
    return np.concatenate(keys), sure


def _prefixes(texts: DataFrame, common: np.ndarray, similarity: float, words: int, long_blocks: bool = False) -> DataFrame:
    """(id, grams): what similar texts share at least one of: the first of the distinct windows in an order that all texts share.
    With long_blocks, long texts have keys of blocks instead (see _block_keys), but for those that may be similar to one of WIDE
    windows or less, or for which the blocks are no guarantee.

    Of n windows, one of the first n - ceil(similarity n) + 1 is also among the first ones of any text that is similar: if
    none were, over n (1 - similarity) would be missing there. This holds in any order; here the common windows come last.
    """
    order = np.argsort(common)
    shared = texts.sparkSession.sparkContext.broadcast((common[order], order))

    def first(h: np.ndarray) -> np.ndarray:
        known, rank = shared.value
        at = np.minimum(np.searchsorted(known, h), max(0, len(known) - 1))
        often = known[at] == h if len(known) else np.zeros(len(h), bool)
        blocks, sure = _block_keys(h, similarity, often) if long_blocks and len(h) > WIDE else (h[:0], False)
        if sure and len(h) * similarity > WIDE + 1:
            return blocks
        if len(known):
            h = np.concatenate([h[~often], h[often][np.argsort(rank[at[often]])]])
        return np.concatenate([h[: len(h) - ceil(similarity * len(h) - 1e-9) + 1], blocks])

    return _grams(texts, words, first)


def _enough(similarity: float, x: str, y: str) -> Column:
    """Whether the sets x and y can be similar, by their sizes and signatures: never false for two that are."""
    part = lambda t, c: F.col(f"{t}.{c}") if t else F.col(c)
    missing = lambda u, v: sum((F.bit_count(part(u, f"s{k}").bitwiseAND(F.bitwise_not(part(v, f"s{k}")))) for k in range(SIGNATURE)), F.lit(0))
    nx, ny = part(x, "n"), part(y, "n")
    common = F.least(nx - missing(x, y), ny - missing(y, x))
    return (F.least(nx, ny) >= F.lit(similarity - 1e-9) * F.greatest(nx, ny)) & (common >= F.lit(similarity - 1e-9) * (nx + ny - common))


def _overlap(similarity: float, nx: Column, ny: Column) -> Column:
    """How many windows two similar sets of these sizes share at least."""
    return F.ceil(F.lit(similarity / (1 + similarity)) * (nx + ny) - F.lit(1e-6))


#: Ratio of the sizes within a class of sizes.
CLASS = 1.1


def _by_size(rows: DataFrame, similarity: float) -> DataFrame:
    """From (gram, pos, n, ...): a row for each class of sizes (cls) of the smaller partners that may first meet a text in this window.

    Two similar sets share _overlap() windows, so the first one that both have, in the order of all texts, has at most
    n - _overlap() others before it in either. For partners of about its size a text thus needs little over half of its
    prefix: copies with more own windows than that, which come first, don't meet. small tells whether the row can also be the
    smaller one's.
    """
    at = lambda n: F.floor(F.log(n) / F.lit(float(np.log(CLASS)))).cast("int")
    least = F.greatest(F.lit(1), F.ceil(F.lit(similarity) * F.col("n") - F.lit(1e-6)))
    spread = rows.withColumn("own", at(F.col("n"))).withColumn("cls", F.explode(F.sequence(at(least), at(F.col("n")))))
    begin = F.greatest(least, F.floor(F.pow(F.lit(CLASS), F.col("cls"))) - 1)  # one less, as powers are rounded
    spread = spread.where(F.col("pos") <= F.col("n") - _overlap(similarity, F.col("n"), F.least("n", begin)))
    return spread.withColumn("small", (F.col("cls") == F.col("own")) & (F.col("pos") <= F.col("n") - _overlap(similarity, F.col("n"), F.col("n")))).drop("own")


def _first_meetings(x: str, y: str, similarity: float) -> Column:
    """Whether y is the smaller one, or the earlier of two equal ones, and the window can be the first that both have."""
    nx, ny = F.col(f"{x}.n"), F.col(f"{y}.n")
    most = _overlap(similarity, nx, ny)
    return ((ny < nx) | ((ny == nx) & (F.col(f"{y}.id") < F.col(f"{x}.id")))) & (F.col(f"{x}.pos") <= nx - most) & (F.col(f"{y}.pos") <= ny - most)


def _possible(pairs: DataFrame, reps: DataFrame, similarity: float) -> DataFrame:
    """Of distinct pairs (a, b), those that sizes and signatures allow."""
    x, y = reps.drop("fp").alias("x"), reps.drop("fp").alias("y")
    both = pairs.alias("p").join(x, F.col("p.a") == F.col("x.id")).join(y, F.col("p.b") == F.col("y.id"))
    return both.where(_enough(similarity, "x", "y")).select("p.a", "p.b")


def _missing(x: bytes, y: bytes) -> tuple[int, int]:
    """Bits of each that the other one hasn't; the longer is folded to the length of the shorter."""
    u, v = np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")
    while len(u) > len(v):
        u = u[: len(u) // 2] | u[len(u) // 2 :]
    while len(v) > len(u):
        v = v[: len(v) // 2] | v[len(v) // 2 :]
    return int(np.bitwise_count(u & ~v).sum()), int(np.bitwise_count(v & ~u).sum())


def _still_possible(pairs: DataFrame, sketches: DataFrame, similarity: float) -> DataFrame:
    """Of distinct pairs (a, b), those that the wide signatures of large sets allow, where both have one."""
    wide = sketches.where("wide is not null").select("id", "n", "wide").dropDuplicates(["id"])
    x, y = wide.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("wide").alias("wa")), wide.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("wide").alias("wb"))

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            able = []
            for na, wa, nb, wb in zip(*(b.column(c).to_pylist() for c in ("na", "wa", "nb", "wb")), strict=True):
                if na is None or nb is None:
                    able.append(True)
                else:
                    mx, my = _missing(wa, wb)
                    common = min(na - mx, nb - my)
                    able.append(common >= (similarity - 1e-9) * (na + nb - common))
            yield b.select(["a", "b"]).filter(pa.array(able, pa.bool_()))

    return checkpoint(pairs.join(x, "a", "left").join(y, "b", "left").select("a", "b", "na", "wa", "nb", "wb").mapInArrow(of, "a long, b long"))


def _alike(texts: DataFrame, pairs: DataFrame, similarity: float, words: int) -> DataFrame:
    """Of the pairs (a, b), those with a Jaccard index of at least `similarity`, as edges (u, v). Window sets are made for these texts only."""
    ends = pairs.select(F.explode(F.array(F.struct(F.col("a").alias("id"), F.lit(True).alias("left")), F.struct(F.col("b").alias("id"), F.lit(False).alias("left")))).alias("e")).select("e.*")
    wanted = checkpoint(ends.groupBy("id").agg(F.max("left").alias("left"), F.min("left").alias("only")))
    sets = checkpoint(_grams(texts.join(wanted, "id", "left_semi"), words))
    one = sets.join(wanted.where("left").select("id"), "id", "left_semi").select(F.col("id").alias("a"), F.col("grams").alias("ga"))
    two = sets.join(wanted.where("not only").select("id"), "id", "left_semi").select(F.col("id").alias("b"), F.col("grams").alias("gb"))
    shared = F.size(F.array_intersect("ga", "gb"))
    alike = shared >= F.lit(similarity - 1e-9) * (F.size("ga") + F.size("gb") - shared)
    found = checkpoint(pairs.join(two, "b").join(one, "a").where(alike).select(F.col("a").alias("u"), F.col("b").alias("v")).distinct())
    discard(wanted, sets)
    return found


def similar_copies(docs: DataFrame, similarity: float = 0.8, words: int = 5, radius: int = 2, key: str = "doc_id", text: str = "text", long_blocks: bool = False) -> DataFrame:
    """(doc_id, component_id) of documents that have an equal or a similar one; component_id is the smallest id of the group.

    Similar is a Jaccard index of at least `similarity` between sets of word windows, which is computed exactly. Candidates
    are pairs whose SimHash fingerprints of these windows lie within `radius`, by the covering tables. An index of
    `similarity` bounds no number of differing bits, so texts are also gathered by their first windows (see _prefixes), of which
    every similar pair shares one. Members of a gathering are first compared with its smallest id. Where that leaves more
    than one component in it, its pairs across components are compared whose sizes let them first meet in this window (see
    _by_size): nothing is left out, and large groups of copies, near or exact, make few pairs. Pairs that sizes and signatures
    exclude are dropped before any set of windows is moved. long_blocks: gather texts of over WIDE windows by blocks of
    windows, which have no order; better only where long texts share much that is in few of them.
    """
    texts = _texts(docs, key, text)
    sketches = checkpoint(_sketches(texts, words))
    firsts = [F.first(c).alias(c) for c in sketches.columns[2:-1]]
    same = checkpoint(sketches.groupBy("same").agg(F.min("id").alias("id"), F.count("*").alias("copies"), *firsts))
    reps = same.drop("same", "copies")
    rows = _prefixes(texts, _common_windows(texts, words), similarity, words, long_blocks).join(reps.select("id"), "id", "left_semi").select("id", F.posexplode("grams").alias("pos", "gram"))
    if long_blocks:
        rows = rows.withColumn("pos", F.lit(0))
    here = Window.partitionBy("gram")
    met = checkpoint(rows.withColumn("low", F.min("id").over(here)).withColumn("high", F.max("id").over(here)).where("low < high").drop("high"))

    points = checkpoint(reps.where("n > 0").groupBy("fp").agg(F.min("id").alias("rep")))
    printed = reps.join(points, "fp").where("id <> rep").select(F.col("rep").alias("u"), F.col("id").alias("v")).union(links(points, radius))
    stars = met.where("id > low").select(F.col("low").alias("a"), F.col("id").alias("b")).union(printed.select(F.least("u", "v"), F.greatest("u", "v"))).distinct()
    able = _still_possible(_possible(stars, reps, similarity), sketches, similarity)
    edges = _alike(texts, able, similarity, words)
    found = checkpoint(connected_components(edges))

    of = met.join(found, met.id == found.node, "left").select("gram", "pos", "id", F.coalesce("component", "id").alias("part"))
    of = of.withColumn("low", F.min("part").over(here)).withColumn("high", F.max("part").over(here)).where("low < high").drop("low", "high")
    sized = Window.partitionBy("gram", "cls")
    of = _by_size(of.join(reps.select("id", "n"), "id"), similarity).withColumn("low", F.min("part").over(sized)).withColumn("high", F.max("part").over(sized)).withColumn("any", F.max("small").over(sized))
    apart = checkpoint(of.where("low < high and any").drop("low", "high", "any", "n").join(reps.drop("fp"), "id"))
    across = apart.alias("x").join(apart.where("small").alias("y"), ["gram", "cls"]).where("x.part <> y.part").where(_first_meetings("x", "y", similarity)).where(_enough(similarity, "x", "y"))
    rest = _still_possible(across.select(F.least("x.id", "y.id").alias("a"), F.greatest("x.id", "y.id").alias("b")).distinct().join(able, ["a", "b"], "left_anti"), sketches, similarity)
    discard(met, apart)
    if not rest.isEmpty():
        found = checkpoint(connected_components(edges.union(_alike(texts, rest, similarity, words))))

    tied = same.join(found, same.id == found.node, "left").where("copies > 1 or component is not null")
    classes = checkpoint(tied.select("same", F.coalesce("component", "id").alias("component_id")))
    return sketches.join(classes, "same").select(F.col("id").alias(key), "component_id")


def first_of_each_group(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The rows of docs, all columns, but for those that similar_copies ties to a smaller doc_id. A row without an id stays, and so do rows that repeat an id."""
    copies = checkpoint(similar_copies(docs, key=key, text=text, **options).where(F.col(key) != F.col("component_id")).select(key).distinct())
    return docs.join(copies, key, "left_anti")
