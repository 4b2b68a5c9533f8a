"""Quality by importance resampling: hashed n-gram models of target and raw text, sampled by Gumbel top-k.

The raw model counts every document; the target model counts those that labels call good (at most `sample` of them, the
ones with the smallest hashed ids). Counts are summed in each task and merged by bucket, so the driver gets one row a bucket
whatever the data. A document's log weight is the log ratio of both models over its words and word pairs, plus a margin a gram
that is the same at every size. The target count of a bucket is smoothed towards what the raw model expects there, so a sample
that says little about a bucket changes little; and a document is left out of the models that judge it, so labelled rows are
judged like others. The k documents with the largest log weight plus Gumbel noise are kept,
where k is the number of documents with a weight of 1 or more; the noise comes from a keyed hash of the id, so a rerun keeps
the same. The k-th draw is found exactly by counting in ever finer intervals.

Edge cases: a null or empty text has the log weight 0, so it counts as explained; ties go to the smaller id, a row without id is drawn
like any other and comes first among ties, also in kept_documents; with no labelled rows, no weight is below 1 and all rows are kept; repeated rows are
each drawn (with equal keys); an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from overlapsolve.llm.common import SLICE, id_and_text, sliced, small_batches
from overlapsolve.llm.hashing import ngram_buckets
from overlapsolve.session import checkpoint, discard

BITS = 14


def target_ids(labels: DataFrame, sample: int = 20_000, key: str = "doc_id") -> list[int]:
    good = labels.where(F.col("quality") == 1).where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias(key)).distinct()
    return [r[0] for r in good.orderBy(F.xxhash64(key), key).limit(sample).collect()]


@dataclass
class Counts:
    """Counts of each bucket in all and in the target's documents, and the ids of these."""

    raw: np.ndarray
    target: np.ndarray
    ids: np.ndarray


def fit(docs: DataFrame, labels: DataFrame, sample: int = 20_000, bits: int = BITS, key: str = "doc_id", text: str = "text") -> Counts:
    """Summed over all documents."""
    ids = np.array(sorted(target_ids(labels, sample, key)), np.int64)  # `sample` at most
    shared = docs.sparkSession.sparkContext.broadcast(ids)

    def counts(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, target = np.zeros(1 << bits, np.int64), np.zeros(1 << bits, np.int64)
        for b in sliced(batches, SLICE, text):
            doc, bucket = ngram_buckets(b.column(1).cast(pa.binary()).to_pylist(), bits)
            chosen = _among(b.column(0), shared.value)
            raw += np.bincount(bucket, minlength=1 << bits)
            target += np.bincount(bucket[chosen[doc]], minlength=1 << bits)
        some = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(raw[some]), pa.array(target[some])], names=["bucket", "raw", "target"])

    parts = id_and_text(docs, key, text).mapInArrow(counts, "bucket long, raw long, target long")
    total = parts.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect()  # 2^bits rows
    raw, target = np.zeros(1 << bits), np.zeros(1 << bits)
    for bucket, r, t in total:
        raw[bucket], target[bucket] = r, t
    return Counts(raw, target, ids)


def _among(column: pa.Array, ids: np.ndarray) -> np.ndarray:
    return np.isin(column.fill_null(-(2**63)).to_numpy(zero_copy_only=False), ids)


def weigher(model: Counts, strength: float = 30.0, per_gram: float = 0.05):
    """A function from (ids, texts) to log weights: `strength` is the expected count at which a bucket's own count and the raw
    model weigh the same; `per_gram` is the margin for each word or pair."""
    raw, target = model.raw, model.target
    all_raw, all_target, size = raw.sum(), target.sum(), len(model.raw)
    bits = size.bit_length() - 1

    def of(ids: pa.Array, texts: list[bytes]) -> np.ndarray:
        doc, bucket = ngram_buckets(texts, bits)
        place, own = np.unique(doc * size + bucket, return_counts=True)
        doc, bucket = place >> bits, place & (size - 1)
        grams = np.bincount(doc, weights=own, minlength=len(texts))
        chosen = _among(ids, model.ids)
        others = (raw[bucket] - own + 1) / (all_raw - grams + size)[doc]
        expected = (all_target - np.where(chosen, grams, 0))[doc] * others
        log_ratio = np.log((strength + target[bucket] - np.where(chosen[doc], own, 0)) / (strength + expected))
        return np.bincount(doc, weights=own * (log_ratio + per_gram), minlength=len(texts))

    return of


def weighed(docs: DataFrame, model: Counts, strength: float = 30.0, per_gram: float = 0.05, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, log_weight) of each row."""
    return with_weights(id_and_text(docs, key, text), model, "log_weight", strength, per_gram, key, text).drop(text)


def with_weights(docs: DataFrame, model: Counts, name: str, strength: float = 30.0, per_gram: float = 0.05, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs, all columns, and the log weight of each row under a name that docs doesn't have. No shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2^bits numbers and `sample` ids, whatever the data

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weigh = weigher(shared.value, strength, per_gram)
        for b in sliced(batches, SLICE, text):
            ids, texts = (b.column(b.schema.get_field_index(c)) for c in (key, text))
            weight = weigh(ids.cast(pa.int64()), [t or b"" for t in texts.cast(pa.binary()).to_pylist()])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(weight, pa.float64())], names=[*b.schema.names, name])

    return small_batches(docs).mapInArrow(of, StructType([*docs.schema.fields, StructField(name, DoubleType())]))


def gumbel(key: str, seed: int) -> Column:
    """Standard Gumbel noise from a keyed hash."""
    u = (F.shiftrightunsigned(F.xxhash64(F.col(key).cast("long"), F.lit(seed)), 11) + F.lit(0.5)) / F.lit(float(1 << 53))
    return -F.log(-F.log(u))


def kth_largest(keys: DataFrame, k: int, column: str, bins: int = 1024, few: int = 10_000) -> float:
    """The k-th largest value of the column, 1 <= k <= rows; only counts, and at last up to `few` values, reach the driver."""
    low, high = keys.agg(F.min(column), F.max(column)).first()
    above = 0
    while low < high:
        width = (high - low) / bins
        place = F.least(F.floor((F.col(column) - F.lit(low)) / F.lit(width)), F.lit(bins - 1)) if width > 0 else F.lit(0)
        inside = keys.where(F.col(column).between(low, high)).withColumn("_bin", place.cast("int"))
        found = {r["_bin"]: r for r in inside.groupBy("_bin").agg(F.count("*").alias("n"), F.min(column).alias("a"), F.max(column).alias("b")).collect()}
        for i in sorted(found, reverse=True):
            if above + found[i]["n"] >= k:
                break
            above += found[i]["n"]
        low, high, n = found[i]["a"], found[i]["b"], found[i]["n"]
        if n <= few:
            return sorted((r[0] for r in keys.where(F.col(column).between(low, high)).select(column).collect()), reverse=True)[k - above - 1]
    return low


def decision(scored: DataFrame, k: int | None, key: str, draw: str = "draw", weight: str = "log_weight") -> Column:
    """The condition on a row's draw and id under which it is among the k largest draws of the scored rows."""
    rows, explained = scored.agg(F.count("*"), F.count_if(F.col(weight) >= 0)).first()
    k = min(rows, explained if k is None else k)
    if k <= 0 or k == rows:
        return F.lit(k > 0)
    cut = kth_largest(scored, k, draw)
    over = scored.where(F.col(draw) > cut).count()
    tied = scored.where(F.col(draw) == cut)
    if over + tied.count() > k:  # repeated rows have equal draws
        last = tied.orderBy(F.asc_nulls_first(key)).limit(k - over).agg(F.max(key)).first()[0]
        return (F.col(draw) > cut) | ((F.col(draw) == cut) & (F.col(key).isNull() | (F.col(key) <= F.lit(last))))
    return F.col(draw) >= cut


def resample(docs: DataFrame, labels: DataFrame, k: int | None = None, seed: int = 11, key: str = "doc_id", text: str = "text", **fitting) -> DataFrame:
    """(doc_id, log_weight, draw, kept): kept marks the k largest draws."""
    weights = weighed(docs, fit(docs, labels, key=key, text=text, **fitting), key=key, text=text)
    scored = checkpoint(weights.withColumn("draw", F.col("log_weight") + gumbel(key, seed)))
    return scored.withColumn("kept", decision(scored, k, key))


def kept_documents(docs: DataFrame, labels: DataFrame, k: int | None = None, seed: int = 11, key: str = "doc_id", text: str = "text", **fitting) -> DataFrame:
    """The rows of docs, all columns, that the draw keeps. Rows are weighed again as they pass, so nothing is joined back by id."""
    model = fit(docs, labels, key=key, text=text, **fitting)
    names = {c.lower() for c in docs.columns}
    weight = next(f"weight{n}" for n in range(len(names) + 1) if f"weight{n}" not in names)
    draw = next(f"draw{n}" for n in range(len(names) + 1) if f"draw{n}" not in names)
    drawn = lambda df: df.withColumn(draw, F.col(weight) + gumbel(key, seed))
    scored = checkpoint(drawn(with_weights(id_and_text(docs, key, text), model, weight, key=key, text=text).drop(text)))
    chosen = decision(scored, k, key, draw, weight)
    discard(scored)
    return drawn(with_weights(docs, model, weight, key=key, text=text)).where(chosen).drop(draw, weight)
