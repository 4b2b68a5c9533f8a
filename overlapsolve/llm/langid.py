"""Language identification by Bayesian fusion of evidence.

The posterior of a language is proportional to its prior at the host, times the likelihood of the text, of the declared
markup language, and of the address suffix. The text model counts hashed byte triples of a bounded sample of documents with a
known language. Priors are counts of first guesses by host, smoothed by those of the host's site, which are smoothed by
those of all rows; the tables of declared language and suffix given the language are counted alike. All counts are
grouped sums over the whole table, joined back by key; only tables of the size languages x languages reach the driver. A
host or suffix that holds much of the table is summed partially first; its rows are split by Spark where they are joined.

Edge cases: a null or empty text leaves its language to the other evidence; a null or odd address has the host "" and the suffix
""; without training rows the result is empty of languages (null); repeated rows get the same answer; an empty table gives
an empty result; very long texts are read whole.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapsolve.llm.common import SLICE, sliced, small_batches
from overlapsolve.session import checkpoint

BITS = 16
_LOWER = np.arange(256, dtype=np.uint32)
_LOWER[65:91] += 32


def triples(texts: list[bytes], bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text index, bucket) of the run of three bytes from each byte on, A-Z in lower case; two line ends follow a text."""
    data = np.frombuffer(b"\n\n".join([*texts, b""]), np.uint8)
    sizes = np.array([len(t) for t in texts], np.int64)
    if not sizes.sum():
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    c = _LOWER[data]
    h = (c[:-2] << 16 | c[1:-1] << 8 | c[2:]) * np.uint32(0x9E3779B1)
    doc = np.repeat(np.arange(len(texts)), sizes)
    at = np.arange(len(doc)) + 2 * doc  # the texts before have two more bytes each
    return doc, (h[at] >> np.uint32(32 - bits)).astype(np.int64)


@dataclass
class TextModel:
    languages: list[str]
    logs: np.ndarray  # a row of log probabilities for each bucket

    def likelihoods(self, texts: list[bytes], temper: float) -> np.ndarray:
        """Log likelihoods of each text by language. Triples overlap, so their sum counts for `temper` of it."""
        doc, bucket = triples(texts, len(self.logs).bit_length() - 1)
        return np.stack([np.bincount(doc, weights=self.logs[bucket, k], minlength=len(texts)) for k in range(len(self.languages))], axis=1) * temper if self.languages else np.zeros((len(texts), 0))


def train(docs: DataFrame, rows: int = 800, longest: int = 20_000, key: str = "doc_id", text: str = "text", lang: str = "lang", smoothing: float = 0.5) -> TextModel:
    """From up to `rows` documents of each language, those with the smallest hashed ids, of at most `longest` characters.

    Ids are chosen first, so only the chosen texts reach the driver.
    """
    known = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"), F.col(lang).alias("lang")).where("id is not null and text is not null and lang is not null").where(F.length("text") <= longest)
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("id", F.lit(9)), "id"))
    ids = [r[0] for r in known.select("id", "lang").withColumn("place", place).where(F.col("place") <= rows).select("id").collect()]  # `rows` a language
    texts: dict[str, list[bytes]] = {}
    for _, t, language in sorted(map(tuple, known.where(F.col("id").isin(ids)).collect())) if ids else ():
        texts.setdefault(language, []).append(t.encode())
    languages = sorted(texts)
    logs = np.zeros((1 << BITS, len(languages)))
    for k, language in enumerate(languages):
        _, bucket = triples(texts[language])
        n = np.bincount(bucket, minlength=1 << BITS) + smoothing
        logs[:, k] = np.log(n / n.sum())
    return TextModel(languages, logs)


_DROP = re.compile(rb"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>")
_DECLARED = re.compile(rb"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-z]{2})")


def visible(page: bytes) -> bytes:
    return entities.unescape(_DROP.sub(b" ", page).decode("utf-8", "replace")).encode()


def address(url: Column) -> tuple[Column, Column, Column]:
    """(host, site, suffix): the host, its last two labels, and its last label with a two-letter first path part."""
    u = F.lower(F.coalesce(url.cast("string"), F.lit("")))
    host = F.regexp_extract(u, r"^[a-z][a-z0-9+.-]*://([^/:?#]*)", 1)
    site = F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1)
    part = F.regexp_extract(u, r"^[a-z][a-z0-9+.-]*://[^/?#]*/([a-z]{2})(?:[/?#]|$)", 1)
    return host, site, F.concat(F.regexp_extract(host, r"([^.]+)$", 1), F.lit("/"), part)


def evidence(rows: DataFrame, model: TextModel, markup: bool, temper: float = 0.2) -> DataFrame:
    """(id, host, site, suffix, declared, ll): from (id, host, site, suffix, text); declared is "" if the text isn't markup."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def of(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, SLICE):
            texts = b.column(b.schema.get_field_index("text")).cast(pa.binary()).to_pylist()
            found = [_DECLARED.search(t) if markup else None for t in texts]
            ll = shared.value.likelihoods([visible(t) for t in texts] if markup else texts, temper)
            ll = ll - ll.max(axis=1, keepdims=True) if ll.size else ll
            columns = [b.column(i) for i in range(4)] + [pa.array([m[1].decode().lower() if m else "" for m in found], pa.string()), pa.array(list(ll), pa.list_(pa.float64()))]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "host", "site", "suffix", "declared", "ll"])

    return small_batches(rows).select("id", "host", "site", "suffix", "text").mapInArrow(of, "id long, host string, site string, suffix string, declared string, ll array<double>")


def _counts(rows: DataFrame, keys: list[str], name: str, k: int) -> DataFrame:
    """Counts of the first guess by key, as an array over languages; partial sums are made before the shuffle."""
    return rows.groupBy(*keys).agg(F.array(*[F.sum((F.col("guess") == i).cast("double")) for i in range(k)]).alias(name))


def fused(rows: DataFrame, model: TextModel, kappa: float = 5.0) -> DataFrame:
    """(id, lang, probability) from evidence rows."""
    k = len(model.languages)
    if not k:
        return rows.select("id", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("probability"))
    first = checkpoint(rows.withColumn("guess", F.array_position("ll", F.array_max("ll")).cast("int") - 1))
    whole = first.agg(*[F.sum((F.col("guess") == i).cast("double")) for i in range(k)]).first()
    whole = np.array([x or 0.0 for x in whole]) + 1
    top = (whole / whole.sum()).tolist()
    literal = lambda xs: F.array(*[F.lit(float(x)) for x in xs])
    hosts = _counts(first, ["host", "site"], "nh", k)
    # A host's site counts come from its own sums, so the rows themselves are aggregated once.
    sites = hosts.groupBy("site").agg(F.array(*[F.sum(F.get("nh", F.lit(i))) for i in range(k)]).alias("ns"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda x, y: x + y)
    smooth = lambda n, p: F.zip_with(n, p, lambda x, y: (x + F.lit(kappa) * y) / (total(n) + F.lit(kappa)))
    priors = hosts.join(sites, "site").select("host", "site", smooth(F.col("nh"), smooth(F.col("ns"), literal(top))).alias("prior"))
    priors = checkpoint(priors)
    # A suffix not seen with a language counts half; there may be as many suffixes as rows.
    suffixes = _counts(first, ["suffix"], "nx", k)
    many = max(1, suffixes.count())
    per = literal(1 / (x - 1 + 0.5 * many) for x in whole)
    suffixes = suffixes.select("suffix", F.zip_with("nx", per, lambda n, p: F.log((n + 0.5) * p)).alias("ends"))
    domain = [*model.languages, "", "other"]
    said = F.when(F.col("declared").isin(domain[:-1]), F.col("declared")).otherwise("other")
    marked = first.withColumn("declared", said)
    n = np.full((len(domain), k), 0.1)
    for value, guess, count in marked.groupBy("declared", "guess").count().collect():  # languages x languages
        n[domain.index(value), guess] += count
    table = np.log(n / n.sum(axis=0))
    declared_at = F.array_position(F.array(*[F.lit(v) for v in domain]), F.col("declared")).cast("int") - 1
    joined = marked.join(priors, ["host", "site"]).join(suffixes, "suffix")
    add = lambda a, b: F.zip_with(a, b, lambda x, y: x + y)
    logs = add(add(F.col("ll"), F.transform("prior", lambda p: F.log(p))), add(F.get(F.array(*[literal(r) for r in table]), declared_at), F.col("ends")))
    best = joined.select("id", logs.alias("s")).withColumn("m", F.array_max("s"))
    mass = F.aggregate("s", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("m")))
    return best.select("id", F.get(F.array(*[F.lit(v) for v in model.languages]), F.array_position("s", F.col("m")).cast("int") - 1).alias("lang"), F.round(1 / mass, 6).alias("probability"))


def of_pages(pages: DataFrame, model: TextModel, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(id, lang, probability) of web pages."""
    host, site, suffix = address(F.col(url))
    rows = pages.select(F.col(key).cast("long").alias("id"), host.alias("host"), site.alias("site"), suffix.alias("suffix"), F.coalesce(F.col(html), F.lit("")).alias("text"))
    return fused(evidence(rows, model, markup=True), model)


def of_documents(docs: DataFrame, model: TextModel, key: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """(id, lang, probability) of plain documents: their source stands for the host; nothing is declared and no address is known."""
    rows = docs.select(F.col(key).cast("long").alias("id"), F.coalesce(F.col(source).cast("string"), F.lit("")).alias("host"), F.lit("").alias("site"), F.lit("").alias("suffix"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return fused(evidence(rows, model, markup=False), model)
