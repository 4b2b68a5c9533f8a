"""Exact top-k search by MaxScore over integer vectors.

Vectors are sharded; in a shard each component is a posting list of gains over the list's least possible contribution, so
that gains are never negative, whatever the signs. For a query, terms are ordered by their largest gain. Those whose gains
together can't lift a vector over the current threshold are non-essential: essential lists are traversed, vectors that stay
below the threshold even with all remaining gains are dropped, and the others are probed in the remaining lists while they
can still compete. Shards' best are merged by a rank that Spark limits before it shuffles.

Queries travel in blocks of bounded size to groups of shards; a shard is moved once. Within a task, what a block's queries have
found in one shard is their threshold in the next. Scores are exact 64-bit integers (beyond that they
are clipped); ties go to the smaller id. A vector that is null or holds a null or a non-finite component takes no part; vectors of
unequal lengths, empty ones too, are padded with zeros; of repeated rows of an id each is a candidate, and one of them is the query; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SHARD_ROWS = 4096
BLOCK_ROWS = 512
GROUP = 8
LEAST = int(np.iinfo(np.int64).min)


def quantised(vectors: DataFrame, scale: int = 1024, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(vec_id, v): floor(scale * x) of each component as a long; vectors that take no part are left out."""
    x = F.col(vector)
    finite = lambda y: y.isNotNull() & ~F.isnan(y) & (F.abs(y.cast("double")) != F.lit(float("inf")))
    ok = vectors.where(F.col(key).isNotNull() & x.isNotNull()).where(F.forall(x, finite))
    return ok.select(F.col(key).cast("long").alias("vec_id"), F.transform(x, lambda y: F.floor(F.lit(scale) * y.cast("double")).cast("long")).alias("v"))


def _matrix(column: pa.Array) -> np.ndarray:
    sizes = np.diff(column.offsets.to_numpy())
    width = int(sizes.max()) if len(sizes) else 0
    flat = column.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(sizes), width), np.int64)
    out[np.arange(width)[None, :] < sizes[:, None]] = flat
    return out


def _narrow(m: np.ndarray) -> tuple[str, bytes]:
    """The components in the shortest integers that hold them."""
    peak = int(np.abs(m).max()) if m.size else 0
    kind = "<i2" if peak < 1 << 15 else "<i4" if peak < 1 << 31 else "<i8"
    return kind, m.astype(kind).tobytes()


def _row(number: int, ids: np.ndarray, m: np.ndarray) -> list:
    kind, data = _narrow(m)
    return [number, m.shape[1], kind, ids.astype("<i8").tobytes(), data]


def _unpacked(ids: bytes, width: int, kind: str, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    own = np.frombuffer(ids, "<i8")
    return own, np.frombuffer(data, kind).astype(np.int64).reshape(len(own), width)


_TYPES = [pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.binary()]


def _shards(rows: DataFrame, size: int = SHARD_ROWS, most: int = 1 << 20) -> DataFrame:
    """Rows (vec_id, v) of each task as shards of up to `size` rows and about `most` components."""
    names = ["shard", "width", "kind", "ids", "data"]

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        for b in batches:
            ids, m = b.column(0).to_numpy(zero_copy_only=False), _matrix(b.column(1))
            step = max(1, min(size, most // max(1, m.shape[1])))
            for at in range(0, len(ids), step):
                row = _row(number, ids[at : at + step], m[at : at + step])
                number += 1
                yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, _TYPES, strict=True)], names=names)

    return rows.mapInArrow(of, "shard long, width long, kind string, ids binary, data binary")


def _blocks(asked: DataFrame, number: int) -> DataFrame:
    """Queries (vec_id, v) as `number` rows, by the hash of their id."""

    def of(key: tuple, table: pa.Table) -> pa.Table:
        t = table.combine_chunks()
        row = _row(key[0].as_py(), t.column("vec_id").to_numpy(), _matrix(t.column("v").combine_chunks()))
        return pa.table([pa.array([x], y) for x, y in zip(row, _TYPES, strict=True)], names=["block", "qwidth", "qkind", "qids", "qdata"])

    hashed = asked.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(number)))
    return hashed.groupBy("block").applyInArrow(of, "block long, qwidth long, qkind string, qids binary, qdata binary")


class Shard:
    """Posting lists of one shard: a row of components for each term, and each list's least and largest value."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids = ids[order]
        self.lists = np.ascontiguousarray(vectors[order].T)
        self.low = self.lists.min(axis=1) if len(ids) else np.zeros(len(self.lists), np.int64)
        self.high = self.lists.max(axis=1) if len(ids) else self.low

    def best(self, query: np.ndarray, own: int, k: int, least_score: int = LEAST) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of the k best by score and then id, without the query's own row; those below `least_score` may be left out."""
        q = np.zeros(len(self.lists), np.int64)
        n = min(len(q), len(query))
        q[:n] = query[:n]
        peak = max((int(max(-int(lo), int(hi))) for lo, hi in zip(self.low, self.high, strict=True)), default=0)
        if len(q) * int(np.abs(q).max(initial=0)) * peak >= 1 << 62:
            return self._wide(q, own, k)
        ends = np.stack([q * self.low, q * self.high])
        least, gain = ends.min(axis=0), np.abs(ends[1] - ends[0])
        terms = np.argsort(-gain, kind="stable")
        rest = np.append(np.cumsum(gain[terms][::-1])[::-1], 0)  # what terms from this one on can add
        floor = int(least.sum())
        other = np.flatnonzero(self.ids != own)
        if not len(other):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        # The first guess of the threshold: exact scores of those that lead on the strongest term.
        lead = other
        if len(other) > 4 * k and len(terms):
            signed = q[terms[0]] * self.lists[terms[0], other]
            lead = other[np.argpartition(-signed, 4 * k)[: 4 * k]]
        known = q @ self.lists[:, lead]
        threshold = int(np.partition(known, len(known) - k)[len(known) - k]) if len(known) >= k else LEAST
        threshold = max(threshold, least_score)
        essential = int(np.argmax(floor + rest < threshold)) if (floor + rest < threshold).any() else len(terms)
        alive, partial = other, np.full(len(other), floor, np.int64)
        for i, t in enumerate(terms):
            partial = partial + (q[t] * self.lists[t, alive] - least[t])
            if i + 1 >= min(essential, 8) and (i % 4 == 3 or i + 1 >= essential):
                fit = partial + rest[i + 1] >= threshold
                alive, partial = alive[fit], partial[fit]
                if len(alive) > k:  # partial scores are lower bounds, so they may lift the threshold
                    threshold = max(threshold, int(np.partition(partial, len(partial) - k)[len(partial) - k]))
        order = np.lexsort((self.ids[alive], -partial))[:k]
        return self.ids[alive[order]], partial[order]


    def _wide(self, q: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """The same in integers of any length, for components so large that 64 bits might not hold a bound."""
        scores = (q.astype(object)[:, None] * self.lists.astype(object)).sum(axis=0)
        order = sorted((-s, int(i)) for i, s in zip(self.ids, scores, strict=True) if i != own)[:k]
        clip = lambda s: min(max(s, -(2**63)), 2**63 - 1)
        return np.array([i for _, i in order], np.int64), np.array([clip(-s) for s, _ in order], np.int64)


def search(vectors: DataFrame, every: int = 100, k: int = 10, scale: int = 1024, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k best other rows of each row whose id is divisible by `every`."""
    rows = quantised(vectors, scale, key, vector)
    asked = rows.where(F.pmod(F.col("vec_id"), F.lit(every)) == 0).groupBy("vec_id").agg(F.min("v").alias("v"))
    number = -(-asked.count() // BLOCK_ROWS) or 1
    groups = max(32, rows.count() // (GROUP * SHARD_ROWS))
    return top(_shards(rows), _blocks(asked, number), groups, k)


def top(shards: DataFrame, blocks: DataFrame, groups: int, k: int) -> DataFrame:
    """Match each block of queries with each shard, and merge. Shards are dealt to groups; every group gets all blocks."""

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, shard, reached = None, None, {}
        for b in batches:
            for r in b.to_pylist():
                if r["shard"] != last:
                    last, shard = r["shard"], Shard(*_unpacked(r["ids"], r["width"], r["kind"], r["data"]))
                own, queries = _unpacked(r["qids"], r["qwidth"], r["qkind"], r["qdata"])
                least = reached.setdefault(r["block"], np.full(len(own), LEAST))
                found = []
                for n, (q, v) in enumerate(zip(own, queries, strict=True)):
                    x, s = shard.best(v, int(q), k, int(least[n]))
                    if len(s) == k:
                        least[n] = max(least[n], s.min())
                    found.append((np.full(len(x), q), x, s))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c).astype(np.int64)) for c in zip(*found, strict=True)], names=["query_id", "vec_id", "score"])

    left = shards.withColumn("group", F.pmod(F.xxhash64("shard"), F.lit(groups)))
    right = blocks.withColumn("group", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))))
    found = left.join(right, "group").mapInArrow(of, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
