"""Toxicity severity by cumulative-link ordinal regression over sparse hashed words.

P(grade <= g) = sigmoid(cut_g - w.x): one weight vector serves all ordered cuts, and the expected grade is the sum over g of
P(grade > g). A row of grade g contributes the likelihood P(grade <= g) - P(grade <= g - 1). Features are the distinct words of a text, hashed; only those whose document frequency among toxic rows lies
clearly above that among the others are kept, so ordinary words don't add up over long texts. Labels say toxic or not; the
grade of a toxic row is taken from how much of such evidence it holds, cut at the given quantiles, and of a toxic row without
any it is only known that it is not 0, so its likelihood is 1 - P(grade <= 0). The model is fitted on a
bounded sample: at most `sample` toxic and `sample` other labelled rows, those with the smallest hashed ids.

Edge cases: a null or empty text has no features and so the grade of a text without evidence; without labelled toxic rows
every severity is 0; very long texts are read whole; repeated rows are scored alike; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.llm.common import SLICE, id_and_text, sliced
from overlapsolve.llm.hashing import word_hashes

BITS = 18


def _stripped(texts: list[bytes]) -> list[bytes]:
    return [t.translate(_PUNCTUATION) for t in texts]


_PUNCTUATION = bytes(32 if chr(i) in ".,;:!?\"'()[]{}<>#*$%&|/\\+=~^`" else i for i in range(256))


def distinct_buckets(texts: list[bytes], bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text index, bucket) of each distinct word."""
    doc, h = word_hashes(_stripped(texts))
    both = np.unique((doc.astype(np.int64) << bits) | (h >> np.uint64(64 - bits)).astype(np.int64))
    return both >> bits, both & ((1 << bits) - 1)


@dataclass
class Ordinal:
    """weights: by bucket, mostly zero; cuts: ascending, one fewer than grades."""

    weights: np.ndarray
    cuts: np.ndarray

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade > g) for each g."""
        return 1 / (1 + np.exp(np.clip(self.cuts[None, :] - score[:, None], -500, 500)))

    def severity(self, score: np.ndarray) -> np.ndarray:
        return self.tails(score).sum(axis=1)

    def grade(self, score: np.ndarray) -> np.ndarray:
        """The most likely grade."""
        t = np.concatenate([np.ones((len(score), 1)), self.tails(score), np.zeros((len(score), 1))], axis=1)
        return (t[:, :-1] - t[:, 1:]).argmax(axis=1)


def screened(doc: np.ndarray, bucket: np.ndarray, toxic: np.ndarray, bits: int = BITS, z: float = 4.0) -> np.ndarray:
    """Evidence of each bucket: the log odds of its document frequencies, or 0 where they don't differ by z standard errors."""
    n1, n0 = toxic.sum(), (~toxic).sum()
    if not n1 or not n0:
        return np.zeros(1 << bits)
    f1 = np.bincount(bucket[toxic[doc]], minlength=1 << bits)
    f0 = np.bincount(bucket[~toxic[doc]], minlength=1 << bits)
    p = (f1 + f0) / (n1 + n0)
    error = np.sqrt(p * (1 - p) * (1 / n1 + 1 / n0)) + 1e-12
    odds = np.log((f1 + 0.5) / (n1 + 1)) - np.log((f0 + 0.5) / (n0 + 1))
    keep = ((f1 / n1 - f0 / n0) / error > z) & (f1 >= 3) & (odds > 1.5)
    return np.where(keep, odds, 0.0)


def fit(texts: list[bytes], toxic: np.ndarray, grades: int = 4, rounds: int = 400, rate: float = 0.05, ridge: float = 1e-3, bits: int = BITS) -> Ordinal:
    doc, bucket = distinct_buckets(texts, bits)
    evidence = screened(doc, bucket, toxic, bits)
    if not evidence.any():
        return Ordinal(np.zeros(1 << bits), np.full(grades - 1, 1e3))
    used = evidence[bucket] > 0
    doc, bucket = doc[used], bucket[used]
    amount = np.bincount(doc, weights=evidence[bucket], minlength=len(texts))
    steps = np.quantile(amount[toxic & (amount > 0)], np.arange(1, grades - 1) / (grades - 1))
    # A row lies between two cuts, numbered from 0 for no lower one to `grades` for no upper one.
    lower = np.where(toxic, 1 + np.where(amount > 0, np.searchsorted(steps, amount, side="right"), 0), 0)
    upper = np.where(toxic & (amount == 0), grades, lower + 1)
    columns, col = np.unique(bucket, return_inverse=True)
    w = evidence[columns] / 2
    raw = np.concatenate([[1.0], np.full(grades - 2, 0.5)])  # the first cut, and logs of the gaps to the next
    state = [np.zeros(len(w) + len(raw)), np.zeros(len(w) + len(raw))]
    for t in range(1, rounds + 1):
        gaps = np.exp(raw[1:])
        cuts = np.concatenate([raw[:1], raw[0] + np.cumsum(gaps)])
        score = np.bincount(doc, weights=w[col], minlength=len(texts))
        below = np.concatenate([np.zeros((len(texts), 1)), 1 - Ordinal(w, cuts).tails(score), np.ones((len(texts), 1))], axis=1)
        row = np.arange(len(texts))
        up, low = below[row, upper], below[row, lower]
        mass = np.maximum(up - low, 1e-12)
        dscore = (1 - up - low) / len(texts)
        dw = np.bincount(col, weights=dscore[doc], minlength=len(w)) + ridge * w / len(texts)
        slopes = np.bincount(upper, weights=up * (1 - up) / mass, minlength=grades + 1) - np.bincount(lower, weights=low * (1 - low) / mass, minlength=grades + 1)
        dcut = -slopes[1:grades] / len(texts)
        draw = np.concatenate([[dcut.sum()], gaps * np.cumsum(dcut[::-1])[::-1][1:]])
        g = np.concatenate([dw, draw])
        state[0] = 0.9 * state[0] + 0.1 * g
        state[1] = 0.999 * state[1] + 0.001 * g * g
        step = rate * (state[0] / (1 - 0.9**t)) / (np.sqrt(state[1] / (1 - 0.999**t)) + 1e-8)
        w, raw = np.maximum(w - step[: len(w)], 0), raw - step[len(w) :]
    full = np.zeros(1 << bits)
    full[columns] = w
    return Ordinal(full, np.concatenate([raw[:1], raw[0] + np.cumsum(np.exp(raw[1:]))]))


def train(docs: DataFrame, labels: DataFrame, sample: int = 3000, longest: int = 20_000, key: str = "doc_id", text: str = "text", **fitting) -> Ordinal:
    """Fit on up to `sample` labelled rows of each kind; texts of over `longest` characters are no training rows."""
    known = labels.where(F.col("toxic").isNotNull()).groupBy(F.col(key).cast("long").alias("_id")).agg(F.max("toxic").alias("toxic"))
    ids = []
    for kind in (1, 0):
        ids += known.where(F.col("toxic") == kind).orderBy(F.xxhash64("_id", F.lit(5)), "_id").limit(sample).collect()
    chosen = docs.sparkSession.createDataFrame([(r[0], int(r[1])) for r in ids], "_id long, toxic int")  # 2 * sample rows at most
    rows = id_and_text(docs, key, text).where(F.length(text) <= longest).join(F.broadcast(chosen), F.col(key) == F.col("_id")).select(F.col(text).alias("t"), "toxic").collect()
    rows.sort(key=lambda r: (r.toxic, r.t))
    return fit([r.t.encode() for r in rows], np.array([r.toxic == 1 for r in rows], bool), **fitting)


SCHEMA = "doc_id long, severity double, grade int, toxic boolean"


def score(docs: DataFrame, model: Ordinal, least: float = 0.5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: expected severity, most likely grade, and whether the severity is `least` or more."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in sliced(batches, SLICE, text):
            doc, bucket = distinct_buckets(b.column(1).cast(pa.binary()).to_pylist(), len(m.weights).bit_length() - 1)
            s = np.bincount(doc, weights=m.weights[bucket], minlength=b.num_rows)
            severity = m.severity(s)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.round(severity, 6)), pa.array(m.grade(s).astype(np.int32)), pa.array(severity >= least)], names=["doc_id", "severity", "grade", "toxic"])

    return id_and_text(docs, key, text).mapInArrow(of, SCHEMA)
